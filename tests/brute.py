"""Answers by trying all vertex sets and cuts, for graphs of a few vertices."""

import itertools


def parts(vertices, edges):
    """How many components the vertices have under the edges among them."""
    up = {v: v for v in vertices}

    def top(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in edges:
        if a in up and b in up:
            up[top(a)] = top(b)
    return len({top(v) for v in vertices})


def k_vertex(vertices, edges, k):
    return all(parts([v for v in vertices if v not in gone], edges) <= 1 for size in range(k) for gone in itertools.combinations(vertices, size))


def cut(edges, side):
    return sum((a in side) != (b in side) for a, b in edges)


def local_edge(vertices, edges, x, y):
    rest = [v for v in vertices if v not in (x, y)]
    return min(cut(edges, {x, *some}) for size in range(len(rest) + 1) for some in itertools.combinations(rest, size))


def local_vertex(vertices, edges, x, y, k):
    """An edge between the two is a path of its own, copies of it included."""
    direct = any({a, b} == {x, y} for a, b in edges)
    others, rest = [e for e in edges if set(e) != {x, y}], [v for v in vertices if v not in (x, y)]
    for size in range(k):
        for gone in itertools.combinations(rest, size):
            left = [v for v in vertices if v not in gone]
            up = {v: v for v in left}

            def top(z, up=up):
                while up[z] != z:
                    z = up[z]
                return z

            for a, b in others:
                if a in up and b in up:
                    up[top(a)] = top(b)
            if top(x) != top(y):
                return min(k, size + direct)
    return k

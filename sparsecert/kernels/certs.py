"""Certificate kernels: each takes a merged graph as arrays and returns the places of the edges to keep.

All of them are strong certificates of their property: they may be united, and certified again.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from heapq import heapify, heappop, heappush

import numpy as np

from sparsecert.kernels.forest import compact, forest


@dataclass
class Edges:
    """Edges as arrays of equal length; w may stand for no weight at all."""

    u: np.ndarray
    v: np.ndarray
    w: np.ndarray
    eid: np.ndarray

    def __len__(self) -> int:
        return len(self.u)

    def take(self, at: np.ndarray) -> Edges:
        return Edges(self.u[at], self.v[at], self.w[at], self.eid[at])

    def slice(self, low: int, high: int) -> Edges:
        """Views, not copies."""
        return Edges(self.u[low:high], self.v[low:high], self.w[low:high], self.eid[low:high])

    @staticmethod
    def join(*parts: Edges) -> Edges:
        return Edges(*(np.concatenate([getattr(p, c) for p in parts]) for c in ("u", "v", "w", "eid")))

    @staticmethod
    def empty() -> Edges:
        return Edges(*(np.empty(0, dtype=np.int64) for _ in range(4)))


def spanning_forest(e: Edges) -> np.ndarray:
    """At most n - 1 edges with the same components."""
    ids, a, b = compact(e.u, e.v)
    return forest(len(ids), a, b)[0]


def sides(n: int, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Component and side of each vertex, from the components of the double cover; side 2 marks odd components."""
    comp = forest(n, a, b)[1]
    double = forest(2 * n, np.concatenate([2 * a, 2 * a + 1]), np.concatenate([2 * b + 1, 2 * b]))[1]
    odd = double[0::2] == double[1::2]
    return comp, np.where(odd, 2, double[0::2] & 1)


def forest_and_odd(e: Edges, per_component: bool = False) -> np.ndarray:
    """A spanning forest, and the first edge that closes an odd cycle with it (or one in each component)."""
    ids, a, b = compact(e.u, e.v)
    kept = forest(len(ids), a, b)[0]
    comp, side = sides(len(ids), a[kept], b[kept])
    odd = np.flatnonzero((side[a] == side[b]) & (a != b))
    if per_component and len(odd):
        odd = odd[np.unique(comp[a[odd]], return_index=True)[1]]
    return np.sort(np.concatenate([kept, odd if per_component else odd[:1]]))


def first_copies(e: Edges) -> np.ndarray:
    """Places of one edge for each pair of vertices."""
    low, high = np.minimum(e.u, e.v), np.maximum(e.u, e.v)
    order = np.lexsort((np.arange(len(e)), high, low))
    new = np.ones(len(order), dtype=bool)
    new[1:] = (low[order[1:]] != low[order[:-1]]) | (high[order[1:]] != high[order[:-1]])
    return np.sort(order[new])


def capped_copies(e: Edges, k: int) -> np.ndarray:
    """Places of at most k edges for each pair, first ones first."""
    low, high = np.minimum(e.u, e.v), np.maximum(e.u, e.v)
    order = np.lexsort((np.arange(len(e)), high, low))
    new = np.ones(len(order), dtype=bool)
    new[1:] = (low[order[1:]] != low[order[:-1]]) | (high[order[1:]] != high[order[:-1]])
    starts = np.flatnonzero(new)
    copy = np.arange(len(order)) - np.repeat(starts, np.diff(np.concatenate([starts, [len(order)]])))
    return np.sort(order[copy < k])


def adjacency(n: int, a: np.ndarray, b: np.ndarray) -> tuple[list[int], list[int], list[int]]:
    """Offsets, neighbours and edge places, vertex by vertex."""
    ends, others, place = np.concatenate([a, b]), np.concatenate([b, a]), np.tile(np.arange(len(a)), 2)
    order = np.argsort(ends, kind="stable")
    offsets = np.concatenate([[0], np.cumsum(np.bincount(ends, minlength=n))])
    return offsets.tolist(), others[order].tolist(), place[order].tolist()


def back_order(n: int, a: np.ndarray, b: np.ndarray) -> tuple[list[int], np.ndarray]:
    """Vertices by most edges to those taken before, and each edge's number among its later end's back edges."""
    offsets, others, place = adjacency(n, a, b)
    back, taken, order = [0] * n, [False] * n, []
    index = np.zeros(len(a), dtype=np.int64)
    levels: list[list[int]] = [list(range(n - 1, -1, -1))]
    top = 0
    while top >= 0:
        if not levels[top]:
            top -= 1
            continue
        x = levels[top].pop()
        if taken[x] or back[x] != top:
            continue
        taken[x] = True
        order.append(x)
        for i in range(offsets[x], offsets[x + 1]):
            y = others[i]
            if not taken[y]:
                back[y] += 1
                index[place[i]] = back[y]
                if back[y] == len(levels):
                    levels.append([])
                levels[back[y]].append(y)
        top = min(len(levels) - 1, top + 1)
        while top + 1 < len(levels) and levels[top + 1]:
            top += 1
    return order, index


def max_back(e: Edges, k: int) -> np.ndarray:
    """Edges whose number among back edges is at most k: at most k forests' worth."""
    ids, a, b = compact(e.u, e.v)
    index = back_order(len(ids), a, b)[1]
    return np.flatnonzero((index >= 1) & (index <= k))


WIDE = 64  # vertices of a layer from which whole arrays are faster than a loop


def breadth_forest(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Places of a breadth-first forest's edges, from the least vertex of each component, layer by layer.

    A vertex is reached from the first of the layer before it, in that layer's order, so this is what
    scanning the vertices one by one in that order gives.
    """
    ends, others, place = np.concatenate([a, b]), np.concatenate([b, a]), np.tile(np.arange(len(a)), 2)
    order = np.argsort(ends, kind="stable")
    others, place = others[order], place[order]
    offsets = np.concatenate([[0], np.cumsum(np.bincount(ends, minlength=n))])
    seen, got = np.zeros(n, dtype=bool), []
    layer = np.unique(forest(n, a, b)[1])
    seen[layer] = True
    while len(layer):
        if len(layer) < WIDE:
            fresh = []
            for x in layer.tolist():
                for i in range(offsets[x], offsets[x + 1]):
                    y = others[i]
                    if not seen[y]:
                        seen[y] = True
                        fresh.append(y)
                        got.append(place[i : i + 1])
            layer = np.array(fresh, dtype=np.int64)
            continue
        sizes = offsets[layer + 1] - offsets[layer]
        at = np.arange(sizes.sum()) + np.repeat(offsets[layer] - np.concatenate([[0], np.cumsum(sizes)[:-1]]), sizes)
        at = at[~seen[others[at]]]
        layer, first = np.unique(others[at], return_index=True)
        seen[layer] = True
        got.append(place[at[first]])
    return np.concatenate(got) if got else np.empty(0, np.int64)


def breadth_forests(e: Edges, k: int) -> np.ndarray:
    """k times a breadth-first forest of what the ones before left."""
    ids, a, b = compact(e.u, e.v)
    left, kept = np.flatnonzero(a != b), []
    for _ in range(k):
        kept.append(left[breadth_forest(len(ids), a[left], b[left])])
        left = np.setdiff1d(left, kept[-1], assume_unique=True)
    return np.sort(np.concatenate(kept)) if kept else np.empty(0, np.int64)


def cascade(e: Edges, k: int) -> np.ndarray:
    """Each edge goes to the first of k forests in which it closes no cycle. For edge connectivity only."""
    ids, a, b = compact(e.u, e.v)
    left, kept = np.flatnonzero(a != b), []
    for _ in range(k):
        got = left[forest(len(ids), a[left], b[left])[0]]
        kept.append(got)
        left = np.setdiff1d(left, got, assume_unique=True)
    return np.sort(np.concatenate(kept)) if kept else np.empty(0, np.int64)


#: Edges from which forests on whole arrays, the faster kernel then, are taken for edge connectivity where no kernel is asked for.
LARGE = 1 << 14

VERTEX_KERNELS: dict[str, Callable[[Edges, int], np.ndarray]] = {"maxback": max_back, "bfs": breadth_forests, "auto": max_back}
EDGE_KERNELS: dict[str, Callable[[Edges, int], np.ndarray]] = {"maxback": max_back, "bfs": breadth_forests, "cascade": cascade, "auto": lambda e, k: (max_back if len(e) < LARGE else cascade)(e, k)}


def vertex_cert(e: Edges, k: int, kernel: str = "auto") -> np.ndarray:
    """Keeps min(vertex connectivity, k) of all pairs. Copies of a pair are dropped first: they would crowd out needed edges."""
    first = first_copies(e)
    return first[VERTEX_KERNELS[kernel](e.take(first), k)]


def edge_cert(e: Edges, k: int, kernel: str = "auto") -> np.ndarray:
    """Keeps min(edge connectivity, k) of all pairs; copies count, more than k of a pair can't."""
    some = capped_copies(e, k)
    return some[EDGE_KERNELS[kernel](e.take(some), k)]


# ---- minimum spanning forests; the order (w, u, v, eid) breaks ties


def weight_order(e: Edges) -> np.ndarray:
    return np.lexsort((e.eid, np.maximum(e.u, e.v), np.minimum(e.u, e.v), e.w))


def sorted_forest(e: Edges) -> np.ndarray:
    order = weight_order(e)
    return np.sort(order[spanning_forest(e.take(order))])


def grown_forest(e: Edges) -> np.ndarray:
    """From each vertex not yet reached, the least edge out of the tree is added again and again."""
    ids, a, b = compact(e.u, e.v)
    rank = np.empty(len(e), dtype=np.int64)
    order = weight_order(e)
    rank[order] = np.arange(len(e))
    offsets, others, place = adjacency(len(ids), a, b)
    ranks, seen, got = rank.tolist(), [False] * len(ids), []
    for root in range(len(ids)):
        if seen[root]:
            continue
        seen[root] = True
        heap = [(ranks[place[i]], others[i]) for i in range(offsets[root], offsets[root + 1])]
        heapify(heap)
        while heap:
            r, x = heappop(heap)
            if seen[x]:
                continue
            seen[x] = True
            got.append(r)
            for i in range(offsets[x], offsets[x + 1]):
                if not seen[others[i]]:
                    heappush(heap, (ranks[place[i]], others[i]))
    return np.sort(order[np.array(got, dtype=np.int64)]) if got else np.empty(0, np.int64)


def round_forest(e: Edges) -> np.ndarray:
    """Rounds: each component takes its least edge out, found by sorting edges by component."""
    ids, a, b = compact(e.u, e.v)
    comp, live, kept = np.arange(len(ids)), np.flatnonzero(a != b), []
    low, high = np.minimum(e.u, e.v), np.maximum(e.u, e.v)
    while len(live):
        both, at = np.concatenate([comp[a[live]], comp[b[live]]]), np.tile(live, 2)
        order = np.lexsort((e.eid[at], high[at], low[at], e.w[at], both))
        first = np.flatnonzero(np.concatenate([[True], both[order][1:] != both[order][:-1]]))
        picked = np.unique(at[order[first]])
        kept.append(picked)
        joined = forest(len(ids), comp[a[picked]], comp[b[picked]])[1]
        comp = joined[comp]
        live = live[comp[a[live]] != comp[b[live]]]
    return np.sort(np.concatenate(kept)) if kept else np.empty(0, np.int64)


class _Compared:
    """A place in weight order that counts how often it is compared."""

    __slots__ = ("at", "tally")

    def __init__(self, at: tuple, tally: list[int]):
        self.at, self.tally = at, tally

    def __lt__(self, other: _Compared) -> bool:
        self.tally[0] += 1
        return self.at < other.at


def weight_comparisons(e: Edges, kernel: str) -> int:
    """How many comparisons of weights a kernel's method needs on these edges: by sorting, by a heap, or by rounds of least edges."""
    tally = [0]
    keys = [_Compared(k, tally) for k in zip(e.w.tolist(), np.minimum(e.u, e.v).tolist(), np.maximum(e.u, e.v).tolist(), e.eid.tolist(), strict=True)]
    ids, a, b = compact(e.u, e.v)
    if kernel == "sort":
        sorted(keys)
    elif kernel == "grow":
        offsets, others, place = adjacency(len(ids), a, b)
        seen = [False] * len(ids)
        for root in range(len(ids)):
            if seen[root]:
                continue
            seen[root] = True
            line = [_Step(keys[place[i]], others[i]) for i in range(offsets[root], offsets[root + 1])]
            heapify(line)
            while line:
                y = heappop(line).to
                if seen[y]:
                    continue
                seen[y] = True
                for i in range(offsets[y], offsets[y + 1]):
                    if not seen[others[i]]:
                        heappush(line, _Step(keys[place[i]], others[i]))
    else:
        comp, live = np.arange(len(ids)), np.flatnonzero(a != b)
        rank = np.empty(len(e), dtype=np.int64)
        rank[weight_order(e)] = np.arange(len(e))
        while len(live):
            ends, at = np.concatenate([comp[a[live]], comp[b[live]]]), np.tile(live, 2)
            tally[0] += len(ends) - len(np.unique(ends))  # a least of c values takes c - 1 comparisons
            order = np.lexsort((rank[at], ends))
            picked = np.unique(at[order[np.flatnonzero(np.concatenate([[True], ends[order][1:] != ends[order][:-1]]))]])
            comp = forest(len(ids), comp[a[picked]], comp[b[picked]])[1][comp]
            live = live[comp[a[live]] != comp[b[live]]]
    return tally[0]


class _Step:
    """A heap's entry: only the weight is compared."""

    __slots__ = ("key", "to")

    def __init__(self, key: _Compared, to: int):
        self.key, self.to = key, to

    def __lt__(self, other: _Step) -> bool:
        return self.key < other.key


FOREST_KERNELS: dict[str, Callable[[Edges], np.ndarray]] = {"sort": sorted_forest, "grow": grown_forest, "rounds": round_forest}


def heaviest_on_path(e: Edges, kept: np.ndarray, u: np.ndarray, v: np.ndarray) -> np.ndarray:
    """For pairs (u, v), the place in weight order of the heaviest forest edge between them; -1 if in no tree together.

    Trees are rooted, and ancestors 1, 2, 4, ... steps up stand in tables with the heaviest edge on the way.
    """
    ids, a, b = compact(np.concatenate([e.u, u]), np.concatenate([e.v, v]))
    n, fa, fb = len(ids), a[kept], b[kept]
    rank = np.empty(len(e), dtype=np.int64)
    rank[weight_order(e)] = np.arange(len(e))
    offsets, others, place = adjacency(n, fa, fb)
    up, heavy, depth, tree = np.arange(n), np.full(n, -1), np.zeros(n, dtype=np.int64), np.full(n, -1)
    for root in range(n):
        if tree[root] >= 0:
            continue
        tree[root], stack = root, [root]
        while stack:
            x = stack.pop()
            for i in range(offsets[x], offsets[x + 1]):
                y = others[i]
                if tree[y] < 0:
                    tree[y], up[y], depth[y], heavy[y] = root, x, depth[x] + 1, rank[kept[place[i]]]
                    stack.append(y)
    ups, heavies = [up], [heavy]
    for _ in range(int(depth.max(initial=0)).bit_length()):
        heavies.append(np.maximum(heavies[-1], heavies[-1][ups[-1]]))
        ups.append(ups[-1][ups[-1]])
    x, y = a[len(e) :].copy(), b[len(e) :].copy()
    swap = depth[x] < depth[y]
    x[swap], y[swap] = y[swap], x[swap]
    best, gap = np.full(len(x), -1), depth[x] - depth[y]
    for j, (p, h) in enumerate(zip(ups, heavies, strict=True)):
        step = (gap >> j) & 1 == 1
        best[step] = np.maximum(best[step], h[x[step]])
        x[step] = p[x[step]]
    for p, h in zip(ups[::-1], heavies[::-1], strict=True):
        step = (p[x] != p[y]) & (tree[x] == tree[y])
        best[step] = np.maximum(best[step], np.maximum(h[x[step]], h[y[step]]))
        x[step], y[step] = p[x[step]], p[y[step]]
    last = (x != y) & (tree[x] == tree[y])
    best[last] = np.maximum(best[last], np.maximum(heavies[0][x[last]], heavies[0][y[last]]))
    return np.where(tree[a[len(e) :]] == tree[b[len(e) :]], best, -2)


def lighter_than_path(cert: Edges, buffered: Edges) -> np.ndarray:
    """The cycle rule: places of buffered edges that aren't the heaviest on a cycle with the forest."""
    if not len(cert) or not len(buffered):
        return np.arange(len(buffered))
    merged = Edges.join(cert, buffered)
    rank = np.empty(len(merged), dtype=np.int64)
    rank[weight_order(merged)] = np.arange(len(merged))
    heavy = heaviest_on_path(merged, np.arange(len(cert)), buffered.u, buffered.v)
    return np.flatnonzero((heavy == -2) | (rank[len(cert) :] < heavy))

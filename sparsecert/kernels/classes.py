"""Classes of vertices that k paths join, without a flow for each pair or vertex.

Edge connectivity of at least k is an equivalence, and merging what is equivalent changes no cut
below k. Vertex connectivity isn't one; there a core grows by vertices with k paths into it.
"""

from __future__ import annotations

import numpy as np

from sparsecert.kernels.certs import Edges, back_order, capped_copies
from sparsecert.kernels.forest import forest


class Contracted:
    """A multigraph whose vertices may be merged: copies by neighbour, and who a vertex was merged into."""

    def __init__(self) -> None:
        self.near: list[dict[int, int]] = []
        self.up: list[int] = []
        self.degree: list[int] = []
        self.found = 0  # paths of the last search, and what it moved along edges
        self.moved: dict[tuple[int, int], int] = {}

    @staticmethod
    def of(n: int, a: np.ndarray, b: np.ndarray) -> Contracted:
        graph = Contracted()
        for _ in range(n):
            graph.new()
        for x, y in zip(a.tolist(), b.tolist(), strict=True):
            if x != y:
                graph.link(x, y)
        return graph

    def new(self) -> int:
        self.near.append({})
        self.up.append(len(self.up))
        self.degree.append(0)
        return len(self.up) - 1

    def find(self, x: int) -> int:
        up = self.up
        while up[x] != x:
            up[x] = x = up[up[x]]
        return x

    def link(self, s: int, t: int, copies: int = 1) -> None:
        self.near[s][t] = self.near[s].get(t, 0) + copies
        self.near[t][s] = self.near[t].get(s, 0) + copies
        self.degree[s] += copies
        self.degree[t] += copies

    def merge(self, s: int, t: int) -> tuple[int, int]:
        """(who stays, who is gone): the one with fewer neighbours goes."""
        near = self.near
        into, gone = (s, t) if len(near[s]) >= len(near[t]) else (t, s)
        between = near[into].pop(gone, 0)
        near[gone].pop(into, None)
        mine = near[into]
        for q, copies in near[gone].items():
            mine[q] = mine.get(q, 0) + copies
            other = near[q]
            del other[gone]
            other[into] = mine[q]
        self.degree[into] += self.degree[gone] - 2 * between
        self.near[gone], self.up[gone] = {}, into
        return into, gone

    def reach(self, s: int, t: int, k: int) -> tuple[bool, set[int]]:
        """Whether k edge-disjoint paths join two vertices, and one side of a smaller cut if not.

        Paths are searched from both ends, each time from the one whose next layer is cheaper.
        """
        near, self.found = self.near, 0
        for x in (s, t):
            if self.degree[x] < k:
                return False, {x}
        found = near[s].get(t, 0)
        self.moved = moved = {(s, t): found, (t, s): -found}
        while found < k:
            self.found = found
            came, goes = {s: s}, {t: t}
            ahead, behind = [s], [t]
            meet = None
            while meet is None:
                if not ahead:
                    return False, set(came)
                if not behind:
                    return False, set(goes)
                if sum(len(near[p]) for p in ahead) <= sum(len(near[p]) for p in behind):
                    layer, ahead = ahead, []
                    for p in layer:
                        for q, room in near[p].items():
                            if q not in came and room > moved.get((p, q), 0):
                                came[q] = p
                                if q in goes:
                                    meet = q
                                    break
                                ahead.append(q)
                        if meet is not None:
                            break
                else:
                    layer, behind = behind, []
                    for p in layer:
                        for q, room in near[p].items():
                            if q not in goes and room > moved.get((q, p), 0):
                                goes[q] = p
                                if q in came:
                                    meet = q
                                    break
                                behind.append(q)
                        if meet is not None:
                            break
            chain = [meet]
            while chain[-1] != s:
                chain.append(came[chain[-1]])
            chain.reverse()
            while chain[-1] != t:
                chain.append(goes[chain[-1]])
            for p, q in zip(chain, chain[1:], strict=False):
                moved[p, q] = moved.get((p, q), 0) + 1
                moved[q, p] = moved.get((q, p), 0) - 1
            found += 1
        self.found = found
        return True, set()

    def shared(self, s: int, t: int, k: int) -> list[int]:
        """Vertices that have k paths to s and t taken as one, as k / 2 or more of the last search's paths run through them.

        From a vertex within a path one part leads to s and the other to t.
        """
        out: dict[int, list[int]] = {}
        for (p, q), some in self.moved.items():
            if some > 0 and (p, q) != (s, t):
                out.setdefault(p, []).extend([q] * some)
        count: dict[int, int] = {}
        while out.get(s):
            x, inner = out[s].pop(), set()
            while x != t:
                inner.add(x)
                x = out[x].pop()
            for x in inner:
                count[x] = count.get(x, 0) + 1
        return [x for x, paths in count.items() if 2 * paths >= k and x != s]

    def reach_more(self, s: int, t: int, k: int) -> tuple[bool, set[int]]:
        """As reach, but for odd k one path more where the two may have it: paths in twos merge what they share."""
        more = k % 2 and min(self.degree[s], self.degree[t]) > k > self.near[s].get(t, 0)
        joined, side = self.reach(s, t, k + 1 if more else k)
        return joined or self.found >= k, side

    def unite(self, s: int, t: int, k: int) -> int:
        """Merges two vertices that the last search, or an edge besides, showed to have k paths, and what shares them; who stays."""
        for x in (t, *self.shared(s, t, k)):
            s = self.merge(s, x)[0]
        return s

    def cut(self, k: int) -> list[int] | None:
        """Vertices on one side of fewer than k edges, or none: a flow to one vertex from each that is left. Merges on the way."""
        up, near = self.up, self.near
        ends = [x for x in range(len(up)) if up[x] == x and near[x]]
        head = max(ends, key=lambda x: len(near[x]), default=0)
        for x in ends:
            head = self.find(head)
            if up[x] != x or x == head:
                continue
            joined, side = self.reach_more(x, head, k)
            if not joined:
                return [y for y in range(len(up)) if self.find(y) in side]
            head = self.unite(x, head, k)
        return None


class Bridges:
    """Classes of vertices that two edge-disjoint paths join, and the trees that their bridges make of them.

    An edge within a tree makes one class of all classes between its ends; they are found by steps up
    from both ends in turn, as many as twice those that are merged. The smaller of two trees is hung
    below the other by its end of the edge.
    """

    def __init__(self) -> None:
        self.top: list[int] = []
        self.tree: list[int] = []
        self.size: list[int] = []
        self.over: list[tuple[int, int] | None] = []  # a class's bridge up: its own end and the other

    def new(self) -> int:
        for up in (self.top, self.tree):
            up.append(len(up))
        self.size.append(1)
        self.over.append(None)
        return len(self.top) - 1

    @staticmethod
    def _find(up: list[int], x: int) -> int:
        while up[x] != x:
            up[x] = x = up[up[x]]
        return x

    def add(self, s: int, t: int) -> tuple[int, list[tuple[int, int]]]:
        """(paths between two vertices before this edge, 2 for more; edges that with it no longer are bridges)."""
        top, over, find = self.top, self.over, self._find
        a, b = find(top, s), find(top, t)
        if a == b:
            return 2, []
        x, y = find(self.tree, s), find(self.tree, t)
        if x != y:
            if self.size[x] > self.size[y]:
                s, t, a, x, y = t, s, b, y, x
            self.tree[x] = y
            self.size[y] += self.size[x]
            edge: tuple[int, int] | None = (s, t)
            while edge is not None:
                over[a], edge = edge, over[a]
                if edge is not None:
                    edge = edge[::-1]
                    a = find(top, edge[0])
            return 0, []
        mine, theirs, lines = {a}, {b}, [a, b]
        meet, i = -1, 0
        while meet < 0:
            up = over[lines[i]] if lines[i] >= 0 else None
            if up is None:
                lines[i] = -1
            else:
                z = lines[i] = find(top, up[1])
                (theirs if i else mine).add(z)
                if z in (mine if i else theirs):
                    meet = z
            i = 1 - i
        freed = [(s, t)]
        for x in (a, b):
            while x != meet:
                freed.append(over[x])
                top[x], x = meet, find(top, over[x][1])
        return 1, freed


def edge_classes(e: Edges, vertices: np.ndarray | None, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Classes of vertices that are pairwise joined by k edge-disjoint paths, named by their least vertex.

    In rounds, until neither changes the graph: pairs that the order by most back edges shows to be
    joined are merged; a vertex of degree below k is a class of its own, and where at least half of
    its edges go to one neighbour it goes there, as no cut between others then grows. For k up to 3
    nothing is left; what is left for larger k is told apart by flows.
    """
    ids = np.unique(np.concatenate([e.u, e.v] if vertices is None else [e.u, e.v, vertices]))
    some = e.take(capped_copies(e, k))
    a, b = np.searchsorted(ids, some.u), np.searchsorted(ids, some.v)
    n, label = len(ids), np.arange(len(ids))
    live = a != b
    a, b = a[live], b[live]
    if k == 1:
        return ids, ids[forest(n, a, b)[1]]
    while len(a):  # rounds on whole arrays while they merge much
        sure = back_order(n, a, b)[1] >= k
        joined = forest(n, a[sure], b[sure])[1]
        merged = int((joined != np.arange(n)).sum())
        label = joined[label]
        a, b = joined[a], joined[b]
        live = a != b
        a, b = a[live], b[live]
        if merged * 8 < len(np.unique(np.concatenate([a, b]))):
            break
    names, places = np.unique(np.concatenate([a, b]), return_inverse=True)
    graph = Contracted()
    for _ in names:
        graph.new()
    for x, y in zip(places[: len(a)].tolist(), places[len(a) :].tolist(), strict=True):
        graph.link(x, y)
    same = np.arange(len(names))  # classes that are one
    holds = same.tolist()  # the class that a vertex of the graph stands for
    _settle(graph, holds, same, k)
    _flows(graph, holds, same, k)
    same = _tops(same)
    label = np.where(np.isin(label, names), names[same[np.searchsorted(names, label).clip(max=max(0, len(names) - 1))]] if len(names) else label, label)
    least = np.full(n, n)
    np.minimum.at(least, label, np.arange(n))
    return ids, ids[least[label]]


def _tops(up: np.ndarray) -> np.ndarray:
    while not np.array_equal(up[up], up):
        up = up[up]
    return up


def _united(graph: Contracted, holds: list[int], same: np.ndarray, s: int, t: int) -> int:
    """Two vertices of the graph are one class; the vertex that stands for it."""
    x, y = holds[s], holds[t]
    into, _ = graph.merge(s, t)
    same[y] = x
    holds[into] = x
    return into


def _absorbed(graph: Contracted, holds: list[int], k: int, line: list[int]) -> None:
    """Vertices of degree below k go to the neighbour that has half of their edges or more."""
    near, degree, up = graph.near, graph.degree, graph.up
    while line:
        x = line.pop()
        if up[x] != x or not near[x] or degree[x] >= k:
            continue
        y = max(near[x], key=near[x].get)
        if 2 * near[x][y] < degree[x]:
            continue
        stays, around = holds[y], list(near[x])  # fewer than k; where they are y's too, their copies grow
        into, _ = graph.merge(x, y)
        holds[into] = stays
        line.append(into)
        line.extend(q for q in around if q != y)


def _settle(graph: Contracted, holds: list[int], same: np.ndarray, k: int) -> None:
    near, up = graph.near, graph.up
    line = list(range(len(up)))
    while True:
        _absorbed(graph, holds, k, line)
        live = [x for x in range(len(up)) if up[x] == x and near[x]]
        if not live:
            return
        place = {x: i for i, x in enumerate(live)}
        ends = [(place[x], place[y], min(c, k)) for x in live for y, c in near[x].items() if x < y]
        a, b, copies = (np.array(c, dtype=np.int64) for c in zip(*ends, strict=True))
        a, b = np.repeat(a, copies), np.repeat(b, copies)
        sure = back_order(len(live), a, b)[1] >= k
        if not sure.any():
            return
        joined = forest(len(live), a[sure], b[sure])[0]
        line = []
        for i, j in zip(a[sure][joined].tolist(), b[sure][joined].tolist(), strict=True):
            s, t = graph.find(live[i]), graph.find(live[j])
            into = _united(graph, holds, same, s, t)
            line.append(into)
        line = [x for s in {graph.find(x) for x in line} for x in (s, *near[s])]


def _flows(graph: Contracted, holds: list[int], same: np.ndarray, k: int) -> None:
    """Tells apart vertices of degree k and more that the rounds left, by flows and the cuts they end at."""
    near, up, degree = graph.near, graph.up, graph.degree
    parts = [{x for x in range(len(up)) if up[x] == x and degree[x] >= k}]
    while parts:
        part = parts.pop()
        if len(part) < 2:
            continue
        head = max(part, key=lambda x: len(near[x]))
        part.discard(head)
        while part:
            x = part.pop()
            joined, side = graph.reach(x, head, k)
            if joined:
                head = _united(graph, holds, same, x, head)
                continue
            inside = {y for y in side if y in part} if len(side) < len(part) else part & side
            part -= inside
            if head in side:
                inside, part = part, inside
            if x not in side and head not in side:
                raise AssertionError("a cut leaves its two vertices together")
            inside.add(x)
            parts.append(inside)


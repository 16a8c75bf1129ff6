"""Post-passes: what a certificate says about components, sides, cuts and separators.

All run in space linear in the certificate. Flows are unit flows that stop at k.
"""

from __future__ import annotations

from collections import deque
from collections.abc import Callable, Iterable

import numpy as np

from sparsecert.kernels.certs import Edges, adjacency, back_order, first_copies
from sparsecert.kernels.classes import Contracted, edge_classes  # noqa: F401  (a post-pass like those here)
from sparsecert.kernels.forest import compact, forest


def with_vertices(e: Edges, vertices: np.ndarray | None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Ids of all vertices, isolated ones too, and the edges' ends as places; loops stay."""
    ids = np.unique(np.concatenate([e.u, e.v] if vertices is None else [e.u, e.v, vertices]))
    return ids, np.searchsorted(ids, e.u), np.searchsorted(ids, e.v)


def odd_cycle(e: Edges) -> list[int]:
    """Vertices of an odd cycle in order, or none."""
    ids, a, b = compact(e.u, e.v)
    offsets, others, _ = adjacency(len(ids), a, b)
    depth, parent = [-1] * len(ids), [-1] * len(ids)
    for root in range(len(ids)):
        if depth[root] >= 0:
            continue
        depth[root], line = 0, deque([root])
        while line:
            x = line.popleft()
            for y in others[offsets[x] : offsets[x + 1]]:
                if depth[y] < 0:
                    depth[y], parent[y] = depth[x] + 1, x
                    line.append(y)
                elif (depth[x] - depth[y]) % 2 == 0 and x != y:
                    left, right = [x], [y]
                    while left[-1] != right[-1]:
                        if depth[left[-1]] >= depth[right[-1]]:
                            left.append(parent[left[-1]])
                        else:
                            right.append(parent[right[-1]])
                    return [int(ids[i]) for i in left + right[-2::-1]]
    return []


class VertexFlow:
    """Vertex-disjoint paths: each vertex is an entry and an exit joined by one unit."""

    def __init__(self, n: int, a: np.ndarray, b: np.ndarray):
        self.n = n
        self.near: list[list[int]] = [[] for _ in range(n)]
        self.through: set[int] = set()  # the vertices of the last flow's paths but for their ends, where it found all
        for x, y in zip(a.tolist(), b.tolist(), strict=True):
            if x != y:
                self.near[x].append(y)
                self.near[y].append(x)

    def paths(self, sources: list[int], sink: int, most: int, direct: set[int] | None = None) -> tuple[int, list[int]]:
        """Disjoint paths up to `most` from the sources (one exit unit each if several) to sink, and a separator if fewer.

        Several sources act as neighbours of a super-source; a single source has unbounded exits.
        direct: neighbours of the sink whose edge isn't used.
        """
        single = len(sources) == 1
        origin = sources[0] if single else -1
        following: dict[int, int] = {}  # flow leaves x to
        before: dict[int, int] = {}  # flow enters x from; a vertex carries one unit
        flow = 0
        starts = self.near[origin] if single else sources
        banned = direct or set()
        used_first: set[int] = set()
        while flow < most:
            # states: (x, 0) at the entry of x, (x, 1) at its exit
            came: dict[tuple[int, int], tuple[int, int] | None] = {}
            line: deque[tuple[int, int]] = deque()
            for y in starts:
                if y == sink:
                    continue
                if y not in used_first and (y, 0) not in came and y != origin:
                    came[y, 0] = None
                    line.append((y, 0))
            reached = None
            while line and reached is None:
                x, out = line.popleft()
                if not out:
                    if x in before or x in used_first:
                        # occupied: only back along the flow that enters x
                        p = before.get(x)
                        if p is not None and (p, 1) not in came:
                            came[p, 1] = (x, 0)
                            line.append((p, 1))
                    elif (x, 1) not in came:
                        came[x, 1] = (x, 0)
                        line.append((x, 1))
                    continue
                if (x in before or x in used_first) and (x, 0) not in came:
                    came[x, 0] = (x, 1)
                    line.append((x, 0))
                for y in self.near[x]:
                    if y == sink:
                        if following.get(x) != sink and x not in banned:
                            reached = x
                            break
                        continue
                    if y == origin or following.get(x) == y:
                        continue
                    if (y, 0) not in came:
                        came[y, 0] = (x, 1)
                        line.append((y, 0))
            if reached is None:
                cut = [x for (x, out) in came if not out and (x, 1) not in came]
                return flow, cut
            # walk back, flipping flow
            chain, state = [], (reached, 1)
            while state is not None:
                chain.append(state)
                state = came[state]
            chain.reverse()
            adds, cancels = [], []
            for (x, ox), (y, oy) in zip(chain, chain[1:], strict=False):
                if ox == 1 and oy == 0 and x != y:
                    adds.append((x, y))
                elif ox == 0 and oy == 1 and x != y:
                    cancels.append((y, x))
            for x, y in cancels:
                if following.get(x) == y:
                    del following[x]
                if before.get(y) == x:
                    del before[y]
            for x, y in [*adds, (reached, sink)]:
                following[x] = y
                if y != sink:
                    before[y] = x
            used_first.add(chain[0][0])
            flow += 1
        self.through = set(following)
        return flow, []


class VertexAsked:
    """Vertex connectivities of pairs in one graph, which is laid out once for all of them.

    An edge between the two counts once, as a path that no vertex can cut.
    """

    def __init__(self, e: Edges, more: np.ndarray | None = None):
        e = e.take(first_copies(e))
        self.ids, a, b = with_vertices(e, more)
        self.flow = VertexFlow(len(self.ids), a, b)
        self.place = {int(x): i for i, x in enumerate(self.ids.tolist())}

    def value(self, x: int, y: int, k: int) -> tuple[int, list[int]]:
        """min(connectivity, k), and a separator if it is below k."""
        s, t = self.place.get(x), self.place.get(y)
        if s is None or t is None:
            return 0, []
        near = self.flow.near
        joined = t in near[s]
        if joined:
            near[s].remove(t)
            near[t].remove(s)
        found, cut = self.flow.paths([s], t, k - joined)
        if joined:
            near[s].append(t)
            near[t].append(s)
        return min(k, found + joined), [int(self.ids[i]) for i in cut]


class EdgeAsked:
    """Edge connectivities of pairs in one graph: its capacities are laid out once, and a flow is undone after its pair."""

    def __init__(self, e: Edges, more: np.ndarray | None = None):
        self.ids, a, b = with_vertices(e, more)
        self.place = {int(x): i for i, x in enumerate(self.ids.tolist())}
        self.near: list[dict[int, int]] = [{} for _ in range(len(self.ids))]
        for p, q in zip(a.tolist(), b.tolist(), strict=True):
            if p != q:
                self.near[p][q] = self.near[p].get(q, 0) + 1
                self.near[q][p] = self.near[q].get(p, 0) + 1

    def value(self, x: int, y: int, k: int) -> tuple[int, np.ndarray]:
        """min(connectivity, k), and the side of x as ids if it is below k."""
        s, t, near, flow = self.place.get(x), self.place.get(y), self.near, 0
        none = np.empty(0, dtype=np.int64)
        if s is None or t is None:
            return 0, none
        used: list[tuple[int, int]] = []
        while True:
            came: dict[int, int] = {s: s}
            line = deque([s])
            while line and t not in came:
                p = line.popleft()
                for q, room in near[p].items():
                    if room > 0 and q not in came:
                        came[q] = p
                        line.append(q)
            if t not in came:
                side = self.ids[np.array(sorted(came))]
                break
            if flow + 1 >= k:
                flow, side = k, none
                break
            q = t
            while q != s:
                p = came[q]
                near[p][q] -= 1
                near[q][p] = near[q].get(p, 0) + 1
                used.append((p, q))
                q = p
            flow += 1
        for p, q in used:
            near[p][q] += 1
            near[q][p] -= 1
        return flow, side


def local_vertex(e: Edges, x: int, y: int, k: int) -> tuple[int, list[int]]:
    return VertexAsked(e, np.array([x, y])).value(x, y, k)


def local_edge(e: Edges, x: int, y: int, k: int) -> tuple[int, np.ndarray]:
    return EdgeAsked(e, np.array([x, y])).value(x, y, k)


def k_vertex_connected(e: Edges, vertices: np.ndarray | None, k: int, strict: bool = False) -> tuple[bool, list[int]]:
    """Whether deleting any k - 1 vertices leaves the graph connected, and a separator if not.

    Vertices are taken by most back edges: pairs among the first k, then each later one against all
    before it by a super-source, unless it already has k neighbours among them.
    """
    if k < 1:
        raise ValueError("k must be at least 1")
    e = e.take(first_copies(e))
    e = e.take(np.flatnonzero(e.u != e.v))
    ids, a, b = with_vertices(e, vertices)
    n = len(ids)
    if strict and n < k + 1:
        return False, []
    if n <= 1 or len(e) == n * (n - 1) // 2:
        return True, []
    k = min(k, n - 1)
    degree = np.bincount(np.concatenate([a, b]), minlength=n)
    low = int(degree.argmin())
    if degree[low] < k:
        return False, [int(x) for x in ids[np.concatenate([b[a == low], a[b == low]])]]
    flow = VertexFlow(n, a, b)
    near = [set(x) for x in flow.near]
    order = back_order(n, a, b)[0]
    for i, x in enumerate(order[:k]):
        for y in order[:i]:
            if y not in near[x]:
                got, cut = flow.paths([x], y, k)
                if got < k:
                    return False, [int(ids[c]) for c in cut]
    before = set(order[:k])
    for x in order[k:]:
        if len(near[x] & before) < k:
            got, cut = flow.paths(sorted(before), x, k)
            if got < k:
                return False, [int(ids[c]) for c in cut]
        before.add(x)
    return True, []


def k_edge_connected(e: Edges, vertices: np.ndarray | None, k: int) -> tuple[bool, np.ndarray]:
    """Whether deleting any k - 1 edges leaves the graph connected, and one side of a smaller cut if not.

    In rounds: a super-vertex of degree below k is a cut; else pairs whose connectivity the order
    shows to be at least k are contracted. Where a round contracts few, as on long chains, flows to
    one vertex tell about the rest.
    """
    if k < 1:
        raise ValueError("k must be at least 1")
    ids, a, b = with_vertices(e, vertices)
    comp = np.arange(len(ids))
    none = np.empty(0, dtype=np.int64)
    while True:
        names, places = np.unique(comp, return_inverse=True)
        if len(names) <= 1:
            return True, none
        x, y = places[a], places[b]
        live = x != y
        x, y = x[live], y[live]
        degree = np.bincount(np.concatenate([x, y]), minlength=len(names))
        if degree.min() < k:
            return False, ids[places == int(degree.argmin())]
        index = back_order(len(names), x, y)[1]
        sure = index >= k
        merged, joined = forest(len(names), x[sure], y[sure])[:2]
        comp = joined[places]
        if len(merged) * 8 < len(names):
            side = Contracted.of(len(names), joined[x], joined[y]).cut(k)
            return side is None, none if side is None else ids[np.isin(comp, side)]


def low_points(e: Edges) -> tuple[list[int], list[int]]:
    """Cut vertices as ids, and places of bridges; an edge with a copy is no bridge."""
    ids, a, b = compact(e.u, e.v)
    n = len(ids)
    offsets, others, place = adjacency(n, a, b)
    enter, low, cuts, bridges, clock = [-1] * n, [0] * n, set(), [], 0
    for root in range(n):
        if enter[root] >= 0:
            continue
        enter[root] = low[root] = clock
        clock += 1
        stack, children = [(root, -1, offsets[root])], 0
        while stack:
            x, via, i = stack.pop()
            if i < offsets[x + 1]:
                stack.append((x, via, i + 1))
                y = others[i]
                if place[i] == via or x == y:
                    continue
                if enter[y] >= 0:
                    low[x] = min(low[x], enter[y])
                else:
                    enter[y] = low[y] = clock
                    clock += 1
                    children += x == root
                    stack.append((y, place[i], offsets[y]))
            elif stack:
                p = stack[-1][0]
                low[p] = min(low[p], low[x])
                if low[x] > enter[p]:
                    bridges.append(via)
                if p != root and low[x] >= enter[p]:
                    cuts.add(p)
        if children > 1:
            cuts.add(root)
    return sorted(int(ids[x]) for x in cuts), sorted(bridges)


def weighted_forest_clusters(e: Edges, most: int) -> tuple[np.ndarray, np.ndarray]:
    """Single linkage: components of the forest's edges of weight `most` or less."""
    ids, a, b = compact(e.u, e.v)
    keep = e.w <= most
    return ids, ids[forest(len(ids), a[keep], b[keep])[1]]


def is_cert(g: Edges, c: Edges, answer: Callable[[Edges], object]) -> bool:
    """Whether c answers like g."""
    return answer(g) == answer(c)


def is_strong_cert(g: Edges, c: Edges, answer: Callable[[Edges], object], others: Iterable[Edges]) -> bool:
    """Whether c answers like g also together with each of the other graphs on the same vertices."""
    return all(answer(Edges.join(g, h)) == answer(Edges.join(c, h)) for h in others)

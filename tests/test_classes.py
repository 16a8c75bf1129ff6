"""Classes and connectivities of pairs without a flow for each vertex or pair."""

import itertools

import numpy as np

from sparsecert.baselines.per_edge import ForestStep, run_steps
from sparsecert.kernels import answers, classes, cores, fold
from sparsecert.kernels.certs import Edges
from sparsecert.kernels.forest import labels_of
from sparsecert.operators.graph import vertex_connectivities
from sparsecert.plans import relational
from sparsecert.workloads.methods import preserved


def drawn(n: int, m: int, seed: int) -> Edges:
    draw = np.random.default_rng(seed)
    return Edges(draw.integers(0, n, m) * 3, draw.integers(0, n, m) * 3, draw.integers(0, 9, m), np.arange(m))


def test_edge_classes_are_those_of_all_pairs():
    for seed in range(120):
        n = 3 + seed % 9
        e = drawn(n, n + seed % (2 * n), seed)
        asked = answers.EdgeAsked(e)
        for k in (1, 2, 3, 4, 5):
            ids, label = answers.edge_classes(e, None, k)
            of = dict(zip(ids.tolist(), label.tolist(), strict=True))
            for x, y in itertools.combinations(of, 2):
                assert (of[x] == of[y]) == (asked.value(x, y, k)[0] >= k)
            assert all(of[of[x]] == of[x] <= x for x in of)


def test_edge_classes_up_to_three_take_no_flows(monkeypatch):
    """A flow for each vertex is what made large graphs too slow."""

    def none(*_):
        raise AssertionError("a flow was asked for")

    e = drawn(400, 600, 5)
    want = [answers.edge_classes(e, None, k)[1].tolist() for k in (1, 2, 3)]
    monkeypatch.setattr(answers.EdgeAsked, "value", none)
    monkeypatch.setattr(classes.Contracted, "reach", none)
    assert [answers.edge_classes(e, None, k)[1].tolist() for k in (1, 2, 3)] == want
    assert all(1 < len(set(x)) < 400 for x in want)


def kept_by_flows(e: Edges, k: int, vertex: bool) -> list[int]:
    """A flow on the kept edges for each edge."""
    kept: list[int] = []
    pairs = list(zip(e.u.tolist(), e.v.tolist(), strict=True))
    for i, (u, v) in enumerate(pairs):
        held = e.take(np.array(kept, dtype=np.int64))
        if vertex and any({u, v} == set(pairs[j]) for j in kept):
            continue
        if (answers.local_vertex if vertex else answers.local_edge)(held, u, v, k)[0] < k:
            kept.append(i)
    return kept


def test_per_edge_methods_keep_what_a_flow_an_edge_keeps():
    for seed in range(60):
        n = 4 + seed % 8
        e = drawn(n, 5 * n, seed)
        e = e.take(np.flatnonzero(e.u != e.v))
        for k in (1, 2, 3, 4):
            assert run_steps(e, "edge_flow", k)[0].tolist() == kept_by_flows(e, k, False)
            assert run_steps(e, "vertex", k)[0].tolist() == kept_by_flows(e, k, True)


def test_per_edge_methods_ask_few_flows(monkeypatch):
    """Not one for each of 20,000 edges; counted are the searches of both kinds."""
    asked = {"edge": 0, "vertex": 0}
    paths, find = answers.VertexFlow.paths, classes.Contracted.reach

    def counted_paths(*a, **kw):
        asked["vertex"] += 1
        return paths(*a, **kw)

    def counted_reach(*a):
        asked["edge"] += 1
        return find(*a)

    monkeypatch.setattr(answers.VertexFlow, "paths", counted_paths)
    monkeypatch.setattr(classes.Contracted, "reach", counted_reach)
    draw = np.random.default_rng(4)
    m = 20_000
    e = Edges(draw.integers(0, 300, m), 1000 + draw.integers(0, 5, m), draw.integers(0, 99, m), np.arange(m))
    run_steps(e, "edge_flow", 5)
    run_steps(e, "vertex", 4)
    assert 0 < asked["edge"] <= 6 * 305 and asked["vertex"] < 300


def test_parts_that_share_no_vertex_take_few_flows(monkeypatch):
    """Copies of events with users and types of their own: one core left the edges of all copies but one to flows."""
    asked = []
    paths = answers.VertexFlow.paths
    monkeypatch.setattr(answers.VertexFlow, "paths", lambda *a, **kw: asked.append(1) or paths(*a, **kw))
    draw = np.random.default_rng(6)
    m, copies = 2_000, 6
    u, v = draw.integers(0, 60, m), 1000 + draw.integers(0, 5, m)
    one = {k: run_steps(Edges(u, v, u * 0, np.arange(m)), "vertex", k)[0] for k in (3, 4)}
    for order in (np.arange(m * copies), np.arange(m * copies).reshape(copies, m).T.ravel()):
        shift = 10_000 * np.repeat(np.arange(copies), m)
        e = Edges(np.tile(u, copies) + shift, np.tile(v, copies) + shift, np.zeros(m * copies, dtype=np.int64), np.arange(m * copies)).take(order)
        for k, kept in one.items():
            asked.clear()
            got = np.sort(order[run_steps(e, "vertex", k)[0]])
            assert got.tolist() == (kept + m * np.arange(copies)[:, None]).ravel().tolist()
            assert len(asked) < 60 * copies


def test_parts_that_share_few_vertices_keep_what_a_flow_an_edge_keeps():
    """Cores that have less than k vertices in common, k, or more."""
    for seed in range(40):
        draw = np.random.default_rng(seed)
        parts, size, shared = 3, 8, seed % 6
        at = draw.integers(0, parts, 240)
        e = Edges(draw.integers(0, size, 240) + (size - shared) * at, draw.integers(0, size, 240) + (size - shared) * at, at * 0, np.arange(240))
        e = e.take(np.flatnonzero(e.u != e.v))
        for k in (2, 3, 4):
            assert run_steps(e, "vertex", k)[0].tolist() == kept_by_flows(e, k, True)


def searched(monkeypatch) -> list[int]:
    """One item for each flow that has to look for paths: its ends have k edges each, and fewer between them."""
    asked: list[int] = []
    find = classes.Contracted.reach

    def counted(graph, s, t, k):
        if min(graph.degree[s], graph.degree[t]) >= k > graph.near[s].get(t, 0):
            asked.append(k)
        return find(graph, s, t, k)

    monkeypatch.setattr(classes.Contracted, "reach", counted)
    return asked


def test_chains_of_copies_take_few_flows(monkeypatch):
    """Copies of a table at equal times make chains of copies of a vertex; each edge of a chain took a flow through all of it, and bridges one through a tree."""
    draw = np.random.default_rng(8)
    copies, users = 40, 50
    ends = (1000 * np.arange(copies) + draw.integers(0, users, 600)[:, None]).ravel()
    e = Edges(ends[:-1], ends[1:], np.ones(len(ends) - 1, dtype=np.int64), np.arange(len(ends) - 1))
    asked = searched(monkeypatch)
    for k, most in ((2, 0), (3, 3 * users), (4, 3 * users)):
        del asked[:]
        kept = e.take(run_steps(e, "edge_flow", k)[0])
        assert len(asked) <= most
        assert answers.edge_classes(kept, None, k)[1].tolist() == answers.edge_classes(e, None, k)[1].tolist()


def test_verdicts_on_chains_take_few_rounds(monkeypatch):
    """Each round contracted a few of a chain's vertices, so that there were hundreds."""
    users, copies, rounds = 30, 60, []
    find = answers.back_order

    def counted(*a):
        rounds.append(1)
        return find(*a)

    monkeypatch.setattr(answers, "back_order", counted)
    draw = np.random.default_rng(10)
    ends = (1000 * np.arange(copies) + draw.integers(0, users, 600)[:, None]).ravel()
    e = Edges(ends[:-1], ends[1:], np.ones(len(ends) - 1, dtype=np.int64), np.arange(len(ends) - 1))
    far = Edges(np.array([ends[0]] * 2), np.array([99_999] * 2), np.array([1, 1]), np.array([-1, -2]))
    for k in (2, 3, 4):
        kept = e.take(run_steps(e, "edge_flow", k)[0])
        for some in (kept, Edges.join(kept, far)):
            del rounds[:]
            holds, side = answers.k_edge_connected(some, None, k)
            assert holds == (len(set(answers.edge_classes(some, None, k)[1].tolist())) == 1)
            assert holds or 0 < (np.isin(some.u, side) != np.isin(some.v, side)).sum() < k
            assert len(rounds) <= 3


def test_hubs_are_drawn_in(monkeypatch):
    """Customers of a few edges met suppliers of many that stayed apart, and took a flow each; where the suppliers are one, copies of an edge tell."""
    draw = np.random.default_rng(9)
    m = 12_000
    e = Edges(draw.integers(0, 3000, m), 10_000 + draw.integers(0, 60, m), np.ones(m, dtype=np.int64), np.arange(m))
    asked = searched(monkeypatch)
    for k in (3, 4):
        del asked[:]
        kept = e.take(run_steps(e, "edge_flow", k)[0])
        assert 0 < len(asked) <= 120
        assert answers.edge_classes(kept, None, k)[1].tolist() == answers.edge_classes(e, None, k)[1].tolist()


def test_forest_walks_are_few():
    """Edges heavier than their path are told from a table, where each took a walk of the tree."""
    e = drawn(500, 20_000, 6)
    e = e.take(np.flatnonzero(e.u != e.v))
    step, walks = ForestStep(), 0
    for i, (u, v, w) in enumerate(zip(e.u.tolist(), e.v.tolist(), e.w.tolist(), strict=True)):
        before = step.walks
        step.add(i, u, v, w)
        walks += step.walks != before
    assert sorted(step.kept) == sorted(run_steps(e, "min_forest_linkcut")[0].tolist())
    assert walks < len(e) // 3


def test_groups_grow_with_vertices_beyond_n():
    """n told too small gave groups of n edges, and a certificate many times as large was solved for each."""
    e = drawn(5000, 20_000, 7)
    e = e.take(np.flatnonzero(e.u != e.v))
    f = fold.fold_all(e, fold.of("components"), fold.GroupPolicy.linear(), 150)
    assert len(f.groups) < 20 and all(np.array_equal(x, y) for x, y in zip(labels_of(f.cert.u, f.cert.v), labels_of(e.u, e.v), strict=True))
    assert [g["edges_in"] for g in fold.fold_all(e, fold.of("components"), fold.GroupPolicy.linear(), 5000).groups][:3] == [5000] * 3


def test_rounds_of_a_forest_label_in_one_task(spark, monkeypatch):
    """Rounds of joins inside each round of the forest took most of its time; what tasks keep of the picked edges is small."""
    rows = [(i, (i * 7 + j) % 40, (i * j) % 11, i * 8 + j) for i in range(40) for j in range(1, 6) if i != (i * 7 + j) % 40]
    want = sorted(rows[i][3] for i in run_steps(Edges(*(np.array(c) for c in zip(*rows, strict=True))), "min_forest_linkcut")[0])

    def none(*_, **__):
        raise AssertionError("rounds were asked for")

    monkeypatch.setattr(relational, "relational_components", none)
    found = relational.relational_min_forest(spark.createDataFrame(rows, "u bigint, v bigint, w bigint, eid bigint"))
    assert sorted(r.eid for r in found.collect()) == want


def told_by_rows(rows, vertices):
    """Values of all pairs from the rows of vertex_connectivities."""
    given = {(r.x, r.y): r.value for r in rows if r.y is not None}
    places = [r for r in rows if r.y is None]
    component, level = {r.x: r.component for r in places}, {(r.x, r.block): r.value for r in places}
    assert len(level) + len(given) == len(rows) and set(component) == set(vertices)
    blocks = {v: {b for x, b in level if x == v and b is not None} for v in component}
    told = {}
    for x, y in itertools.combinations(sorted(vertices), 2):
        shared = blocks[x] & blocks[y]
        assert len(shared) < 2
        ends = [level[v, b] for v in (x, y) for b in shared] or [int(component[x] == component[y])]
        if None not in ends:
            assert (x, y) not in given
            told[x, y] = min(ends)
    return given | told


def test_levels_bound_and_tell_vertex_connectivities():
    for seed in range(80):
        n = 4 + seed % 8
        e = drawn(n, n + seed % (3 * n), seed)
        asked = answers.VertexAsked(e)
        for k in (1, 2, 3, 4):
            ids, level, known = cores.vertex_levels(e, k)
            of = dict(zip(ids.tolist(), zip(level.tolist(), known.tolist(), strict=True), strict=True))
            for x, y in itertools.combinations(of, 2):
                value, least = asked.value(x, y, k)[0], min(of[x][0], of[y][0])
                assert value == least if of[x][1] and of[y][1] else value >= least


def test_vertex_connectivities_come_without_all_pairs(spark):
    """A dense graph: a row per vertex, where all pairs took a flow each. A graph of parts: other pairs one by one."""
    rows = [(i, j, 1, i * 100 + j) for i in range(60) for j in range(i + 1, 60) if (i * j) % 3 != 1]
    dense = spark.createDataFrame(rows, "u bigint, v bigint, w bigint, eid bigint")
    got = vertex_connectivities(dense, 4).collect()
    assert len(got) == 60 and {r.value for r in got} == {4}
    for seed in (1, 2, 3):
        e = drawn(14, 22, seed)
        asked = answers.VertexAsked(e)
        edges = spark.createDataFrame(list(zip(*(c.tolist() for c in (e.u, e.v, e.w, e.eid)), strict=True)), "u bigint, v bigint, w bigint, eid bigint")
        ends = set(e.u.tolist()) | set(e.v.tolist())
        want = {(x, y): asked.value(x, y, 4)[0] for x, y in itertools.combinations(sorted(ends), 2)}
        assert told_by_rows(vertex_connectivities(edges, 4).collect(), ends) == want
        pairs = len(want)
        assert preserved(edges).first().asDict() == {"pairs": pairs, "same_lambda": pairs, "same_kappa": pairs}


def test_blocks_bound_and_tell_vertex_connectivities():
    for seed in range(120):
        n = 4 + seed % 14
        e = drawn(n, n + seed % (2 * n), seed)
        asked = answers.VertexAsked(e)
        for k in (1, 2, 3, 4):
            places = list(zip(*(c.tolist() for c in cores.vertex_blocks(e, k)), strict=True))
            component = {v: c for v, c, *_ in places}
            told = {(v, block): (level, known) for v, _, block, level, known in places if block >= 0}
            for x, y in itertools.combinations(sorted(component), 2):
                value = asked.value(x, y, k)[0]
                both = [(told[x, b], told[y, b]) for v, b in told if v == x and (y, b) in told]
                if not both:
                    assert value == (component[x] == component[y])
                    continue
                ((one, sure), (other, too)), = both
                assert value == min(one, other) if sure and too else value >= min(one, other)


def test_a_row_a_vertex_where_copies_hang_on_an_edge_or_on_none(spark):
    """All vertices outside one dense part were asked about with all others, a flow for each pair."""
    part = [(i, j) for i in range(20) for j in range(i + 1, 20) if (i * j) % 3 != 1]
    pairs = [(c * 100 + i, c * 100 + j) for c in range(6) for i, j in part] + [(c * 100 + 3, c * 100 + 100) for c in range(3)]
    e = Edges(*(np.array(x, dtype=np.int64) for x in zip(*((u, v, 1, i) for i, (u, v) in enumerate(pairs)), strict=True)))
    rows = vertex_connectivities(spark.createDataFrame([(u, v, 1, i) for i, (u, v) in enumerate(pairs)], "u bigint, v bigint, w bigint, eid bigint"), 4).collect()
    ends, asked = {x for p in pairs for x in p}, answers.VertexAsked(e)
    assert len(rows) == len(ends) == 120
    assert told_by_rows(rows, ends) == {(x, y): asked.value(x, y, 4)[0] for x, y in itertools.combinations(sorted(ends), 2)}


def test_levels_of_a_hub_graph_take_no_flows(monkeypatch):
    """All pairs of 16 vertices took a flow each, on every level that had no core yet; common neighbours tell as much."""

    def none(*_, **__):
        raise AssertionError("a flow was asked for")

    monkeypatch.setattr(answers.VertexFlow, "paths", none)
    u = np.repeat(np.arange(300), 5)
    ids, level, known = cores.vertex_levels(Edges(u, 1000 + np.tile(np.arange(5), 300), u * 0, np.arange(len(u))), 4)
    assert len(ids) == 305 and (level == 4).all() and known.all()

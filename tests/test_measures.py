"""One pass, gaps that don't grow, groups solved while the next fills, answers in mid-stream, every tier."""

import itertools
import time

import numpy as np
import pytest

from sparsecert.kernels import answers
from sparsecert.kernels.certs import Edges, vertex_cert, weight_comparisons
from sparsecert.kernels.fold import Fold, GroupPolicy, fold_all, of, over_time
from sparsecert.operators import edges as E
from sparsecert.operators import graph as g
from sparsecert.operators import measures as me
from sparsecert.plans import batch
from sparsecert.plans.batch import as_edges, certs_by_key, clean, map_tasks, planned, tree_widths
from sparsecert.sources import generated
from sparsecert.sources.graphs import graph
from sparsecert.sources.tables import read_edges, save_bucketed, stream_table, write_edges
from sparsecert.workloads import measures, methods  # noqa: F401
from tests import brute
from tests.compare import SMALLEST


def random_edges(n, m, seed=0):
    draw = np.random.default_rng(seed)
    return Edges(draw.integers(0, n, m), draw.integers(0, n, m), draw.integers(0, 1000, m), np.arange(m))


def test_vertices_are_counted_when_groups_close(monkeypatch):
    """No work on all vertices for an arrival: with a group far from full, a batch costs the same at any number seen."""
    import sparsecert.kernels.fold as kernel

    calls = []
    monkeypatch.setattr(kernel.np, "unique", lambda *a, _f=np.unique, **k: calls.append(len(a[0])) or _f(*a, **k))
    f = Fold(of("components"), GroupPolicy.edges(1 << 40))
    for i in range(50):
        f.add(random_edges(10_000, 1000, i))
    assert not calls and f.held == 50_000 and len(f.buffer) == 50


def test_the_gap_stays_flat_as_vertices_grow():
    """Time for an edge, all that happens between arrivals counted, at 10^5 and 4 x 10^6 vertices."""
    gaps = []
    for n in (100_000, 4_000_000):
        f, draw = Fold(of("components"), GroupPolicy.adaptive()), np.random.default_rng(1)
        began = time.perf_counter()
        read = 0
        while read < 2 * n:
            u, v = draw.integers(0, n, 10_000), draw.integers(0, n, 10_000)
            f.add(Edges(u, v, u, v))
            read += 10_000
        f.finish()
        gaps.append((time.perf_counter() - began) / read)
    assert gaps[1] < 8 * gaps[0], gaps  # caches and the logarithm of sorting; a sort of all vertices a batch would be 40 times


@pytest.mark.parametrize("name", ["components", "bipartite", "min_forest", "vertex", "edge"])
@pytest.mark.parametrize("overlap", [False, True])
def test_overlap_gives_the_same_certificate(name, overlap):
    e = random_edges(60, 3000, 5)
    e = e.take(np.flatnonzero(e.u != e.v))
    f = Fold(of(name, 2), GroupPolicy.edges(137), 60, overlap)
    for i in range(0, len(e), 91):
        f.add(e.slice(i, i + 91))
    cert = f.finish(resolve=True)
    alone = Fold(of(name, 2), GroupPolicy.edges(137), 60)
    alone.add(e)
    assert sorted(cert.eid.tolist()) == sorted(alone.finish(resolve=True).eid.tolist())
    assert [r["edges_in"] for r in f.groups[:-1]] == [137] * (len(f.groups) - 1)
    assert f.edges_read == sum(r["edges_in"] for r in f.groups) == len(e)
    assert f.peak <= of(name, 2).bound(60) + 137 * (2 if overlap else 1)


def test_an_error_in_an_overlapped_group_is_raised():
    f = Fold(of("no such property"), GroupPolicy.edges(2), 4, overlap=True)
    with pytest.raises(ValueError, match="no such"):
        f.add(random_edges(4, 20, 1))
        f.finish()


def test_answers_in_mid_stream_are_those_of_prefixes():
    e = random_edges(40, 400, 3)
    e = e.take(np.flatnonzero(e.u != e.v))
    got = list(over_time((e.slice(i, i + 33) for i in range(0, len(e), 33)), of("components"), GroupPolicy.edges(50), 40, me.rank_of))
    assert [read for _, read, _ in got] == [*range(50, len(e), 50), len(e)]
    assert all(told == me.rank_of(e.slice(0, read)) for _, read, told in got)


def test_a_last_group_is_padded_to_whole_size():
    """Dummy edges fill a group of n log n, however large; none of them is kept."""
    e = random_edges(300, 2000, 4)
    e = e.take(np.flatnonzero(e.u != e.v))
    plain, padded = (fold_all(e, of("min_forest", pad_tail=p), GroupPolicy.nlogn(), 300).cert for p in (False, True))
    assert sorted(plain.eid.tolist()) == sorted(padded.eid.tolist())


def test_predicates_of_certificates():
    """On four vertices, with every other graph on them: a spanning forest is strong, a bare verdict isn't."""
    n = 4
    pairs = list(itertools.combinations(range(n), 2))
    others = []
    for mask in range(1 << len(pairs)):
        some = [p for i, p in enumerate(pairs) if mask >> i & 1]
        u, v = (np.array([p[k] for p in some], dtype=np.int64) for k in (0, 1))
        others.append(Edges(u, v, u, u))
    answer = lambda k: lambda e: answers.k_vertex_connected(e, np.arange(n), k)[0]
    for h in others:
        cert = h.take(vertex_cert(h, 2)) if len(h) else h
        assert answers.is_cert(h, cert, answer(2))
        assert answers.is_strong_cert(h, cert, answer(2), others)
    path = others[next(i for i, h in enumerate(others) if len(h) == 2)]
    assert answers.is_cert(path, Edges.empty(), answer(1)) and not answers.is_strong_cert(path, Edges.empty(), answer(1), others)


def test_pairs_are_asked_in_one_layout():
    """Flows are undone: asking all pairs in one object equals asking each afresh, and brute force."""
    draw = np.random.default_rng(2)
    for _ in range(20):
        n = int(draw.integers(4, 8))
        e = random_edges(n, int(draw.integers(n, 3 * n)), int(draw.integers(1000)))
        e = e.take(np.flatnonzero(e.u != e.v))
        byv, bye = answers.VertexAsked(e, np.arange(n)), answers.EdgeAsked(e, np.arange(n))
        simple = sorted({(min(a, b), max(a, b)) for a, b in zip(e.u.tolist(), e.v.tolist(), strict=True)})
        for x, y in itertools.permutations(range(n), 2):
            assert byv.value(x, y, 3)[0] == answers.local_vertex(e, x, y, 3)[0]
            assert bye.value(x, y, 3)[0] == answers.local_edge(e, x, y, 3)[0]
            if (min(x, y), max(x, y)) not in simple:
                assert byv.value(x, y, 3)[0] == brute.local_vertex(list(range(n)), simple, x, y, 3)
    assert byv.value(0, 99, 3) == (0, []) and bye.value(99, 0, 3)[0] == 0


def test_comparisons_of_weights():
    e = random_edges(50, 2000, 9)
    e = e.take(np.flatnonzero(e.u != e.v))
    m = len(e)
    sort, grow, rounds = (weight_comparisons(e, k) for k in ("sort", "grow", "rounds"))
    assert m - 1 <= sort <= m * np.ceil(np.log2(m))
    assert m <= grow
    assert m <= rounds <= 2 * m * 6


@pytest.mark.parametrize(("tasks", "want"), [(1, [1]), (8, [1]), (9, [2, 1]), (200, [25, 4, 1]), (5000, [625, 79, 10, 2, 1])])
def test_merge_trees_have_a_bounded_fan_in(tasks, want):
    assert tree_widths(tasks) == want
    for before, after in zip([tasks, *want], want, strict=False):
        assert -(-before // after) <= batch.FAN_IN


def test_map_tasks_follow_the_input(spark, tmp_path):
    path = str(tmp_path / "edges")
    write_edges(generated.random_graph(spark, 50, 400), path)
    e = read_edges(spark, path)
    least = max(int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism)
    assert map_tasks(e) == least
    before = spark.conf.get("spark.sql.files.maxPartitionBytes")
    try:
        spark.conf.set("spark.sql.files.maxPartitionBytes", "64")
        assert map_tasks(e) > least
    finally:
        spark.conf.set("spark.sql.files.maxPartitionBytes", before)
    assert planned(e).tier == "merge_tree"
    assert planned(e, task_bytes=100).tier == "relational"
    assert map_tasks(e.checkpoint()) < 100, "a checkpoint's partitions count, not its unknown size"


def test_marks_bring_vertices_without_a_second_pass(spark):
    e = spark.createDataFrame([(1, 2, 0, 0), (3, 3, 0, 1), (4, None, 0, 2), (None, 5, 0, 3), (None, None, 0, 4), (2, 2, 0, 5)], "u bigint, v bigint, w bigint, eid bigint")
    for tier in ("merge_tree", "grid", "relational"):
        assert sorted(map(tuple, g.components(e, tier=tier).collect())) == [(1, 1), (2, 1), (3, 3), (4, 4), (5, 5)], tier
        assert sorted((r.v, r.component, r.side, r.bipartite) for r in g.bipartition(e, tier=tier).collect()) == [(1, 1, 0, True), (2, 1, 1, True), (3, 3, 0, True), (4, 4, 0, True), (5, 5, 0, True)], tier
        assert not g.is_k_vertex_connected(e, 1, tier=tier).first().holds
        assert not g.is_k_edge_connected(e, 1, tier=tier).first().holds
    whole = spark.createDataFrame([(1,), (9,)], "v bigint")
    assert (9, 9) in set(map(tuple, g.components(e, whole).collect()))


def test_odd_graphs_in_every_tier(spark):
    e = generated.cycle(spark, 5).select("u", "v", "w", "eid").union(generated.path(spark, 4).selectExpr("u + 100 as u", "v + 100 as v", "w", "eid + 1"))
    for tier in ("merge_tree", "grid", "relational"):
        each = {r.v: r.bipartite for r in g.bipartition(e, tier=tier).collect()}
        assert {v for v, even in each.items() if not even} == set(range(5)), tier
        assert not any(r.bipartite for r in g.bipartition(e, tier=tier, per_component=False).collect()), tier
        cycle = g.odd_cycle(e, tier=tier).first()
        assert not cycle.holds and len(cycle.witness) == 5


def test_certificates_by_key_leave_tasks_small(spark):
    """A key with most edges: what tasks send is certificates. Null keys are a key."""
    e = spark.range(30_000).selectExpr("case when id % 10 = 0 then null when id % 3 = 0 then 'b' else 'a' end as k", "pmod(xxhash64(id, 1), 40) as u", "pmod(xxhash64(id, 2), 40) as v", "pmod(xxhash64(id, 3), 1000) as w", "id as eid").filter("u <> v")
    for held in (100, 1 << 20):
        got = certs_by_key(e, "k", of("min_forest"), most_held=held)
        for k in ("a", "b", None):
            mine = e.filter(e["k"].eqNullSafe(k)).select("u", "v", "w", "eid").toArrow()
            edges = as_edges(mine.combine_chunks().to_batches()[0])
            want = edges.take(of("min_forest").keep(edges))
            assert sorted(r.eid for r in got.filter(got["k"].eqNullSafe(k)).collect()) == sorted(want.eid.tolist())
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert plan.rindex("MapInArrow") > plan.rindex("Exchange")


def test_dictionary_is_exact(spark):
    df = spark.createDataFrame([(x,) for x in ["b", "a", "c", "a", None, "", "é", "b"]], "x string")
    assert sorted(map(tuple, E.dictionary(df, "x", 3).collect())) == [("", 0), ("a", 1), ("b", 2), ("c", 3), ("é", 4)]
    assert E.dictionary(df.filter("false"), "x").count() == 0


def test_places_beyond_their_bits_are_an_error(spark):
    from sparsecert.sources.graphs import F, numbered

    ok = spark.range(5).select(numbered(F.lit(3), F.col("id"), 3).alias("n"))
    assert [r.n for r in ok.collect()] == [24, 25, 26, 27, 28]
    with pytest.raises(Exception, match="places"):
        spark.range(9).select(numbered(F.lit(3), F.col("id"), 3).alias("n")).collect()


def test_bridges_and_cut_vertices_of_the_premium_graph(spark):
    """Against removal of each edge and vertex in turn."""
    e = graph(spark, SMALLEST, "premium_cust_supp")
    rows = [(r.u, r.v, r.eid) for r in e.select("u", "v", "eid").collect()]
    parts = lambda edges, gone=None: _count({x for u, v, _ in rows for x in (u, v)} - {gone}, edges)
    whole = parts(rows)
    want = [r for i, r in enumerate(rows) if parts(rows[:i] + rows[i + 1 :]) > whole]  # by place: line numbers repeat in the tables
    assert sorted((r.u, r.v, r.eid) for r in methods.QUERIES["bridges_whole_premium_cust_supp"](spark, SMALLEST).collect()) == sorted((min(u, v), max(u, v), i) for u, v, i in want)
    cut = {x for x in {x for u, v, _ in rows for x in (u, v)} if parts([r for r in rows if x not in r[:2]], x) > whole}
    assert {r.v for r in methods.QUERIES["cut_vertices_whole_premium_cust_supp"](spark, SMALLEST).collect()} == cut


def _count(vertices, edges):
    up = {v: v for v in vertices}

    def top(x):
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    for u, v, _ in edges:
        up[top(u)] = top(v)
    return sum(up[v] == v for v in vertices)


def test_the_forest_of_supplier_part_equals_the_per_edge_one(spark):
    from sparsecert.baselines.per_edge import per_edge_min_forest

    e = graph(spark, SMALLEST, "supplier_part")
    got = methods.QUERIES["min_forest_weight_supplier_part"](spark, SMALLEST).first()
    other = per_edge_min_forest(e, "linkcut").agg({"w": "sum", "*": "count"}).first()
    assert (got.weight, got.edges) == (other["sum(w)"], other["count(1)"])


def test_times_tell_what_they_are_made_of(spark):
    for name in ("computing_time_components", "computing_time_overlap_components", "computing_time_whole_components", "computing_time_min_forest"):
        r = methods.QUERIES[name](spark, SMALLEST).first()
        assert r.total_ns == r.stream_ns + r.post_ns and r.passes == 1.0 and r.peak_bits == r.peak_edges * 256
        assert (r.comparisons or 0) >= (r.m if "forest" in name else 0)
    old = methods.QUERIES["gap_old_vs_new_edge_2_3"](spark, SMALLEST).first()
    assert old.edge_worst_ns >= old.edge_mean_ns > 0 and old.group_gap_ns > 0


def test_gaps_of_no_edges_and_of_less_than_a_group(spark):
    """Means and speed-ups divided by nothing."""
    few = spark.createDataFrame([(i, 100 + i % 3, 1, i, i) for i in range(5)], "u bigint, v bigint, w bigint, eid bigint, seq bigint")
    for e, m in ((few, 5), (few.filter("u > 10"), 0)):
        r = methods.gap_row(e, "vertex_4", "vertex", "vertex", 4).collect()
        assert [(x.m, x.n, x.groups, x.edge_mean_ns is None, x.speedup_worst, x.speedup_mean) for x in r] == [(m, 8 * (m > 0), int(m > 0), not m, None, None)]


def test_bucketed_certificates_join_without_a_shuffle(spark):
    cert = g.spanning_forest(generated.random_graph(spark, 200, 900)).edges
    save_bucketed(cert, "bucketed_cert", 4)
    try:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
        a, b = (spark.table("bucketed_cert").selectExpr("u", f"v as {n}") for n in ("x", "y"))
        plan = a.join(b, "u")._jdf.queryExecution().executedPlan().toString()
        assert "Exchange" not in plan
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
        spark.sql("DROP TABLE bucketed_cert")


def test_tables_and_rates_as_streams(spark, tmp_path):
    from sparsecert.plans.shared import shared_path
    from sparsecert.streaming.certs import CertSink

    assert stream_table(spark, SMALLEST, "events").isStreaming
    sink = CertSink(shared_path(spark, "cert"), of("components"))
    q = sink.start(generated.rate_edges(spark, 30, 200).drop("seq"), str(tmp_path / "progress"), processingTime="0 seconds")
    end = time.time() + 60
    while q.lastProgress is None or q.lastProgress["batchId"] < 2:
        assert time.time() < end and q.exception() is None
        time.sleep(0.2)
    q.stop()
    labels = g.components(sink.latest(spark))
    assert labels.select("component").distinct().count() == 1 and labels.count() == 30


def test_vector_pairs_equal_plain_products(spark):
    from sparsecert.sources.graphs import vector_pairs

    draw = np.random.default_rng(3)
    x = draw.standard_normal((70, 5)).astype(np.float32)
    df = spark.createDataFrame([(i, [float(c) for c in r]) for i, r in enumerate(x)], "vec_id bigint, embedding array<float>")
    got = {(r.u % (1 << 56), r.v % (1 << 56)): r.w for r in vector_pairs(df, block=16).collect()}
    x = x.astype(float)
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    assert set(got) == set(itertools.combinations(range(70), 2))
    assert all(abs(w - 1e6 * (1 - unit[i] @ unit[j])) < 0.51 for (i, j), w in got.items())


def test_clean_marks(spark):
    e = spark.createDataFrame([(1, 1), (None, 2), (3, 4), (None, None)], "u bigint, v bigint")
    assert sorted((r.u, r.v) for r in clean(e, "mark").collect()) == [(1, 1), (2, 2), (3, 4)]
    assert sorted((r.u, r.v) for r in clean(e).collect()) == [(3, 4)]


def test_passes_are_counted_in_runs(spark):
    """From plans alone no task would read a table."""
    events = spark.read.parquet(f"{SMALLEST}/events.parquet").count()
    orders = spark.read.parquet(f"{SMALLEST}/orders.parquet").count()
    costs = {r.answer: r for r in methods.QUERIES["plan_costs_of_answers"](spark, SMALLEST).collect()}
    assert {n: r.rows_read for n, r in costs.items()} == {n: orders if n in ("cut_vertices", "bridges", "min_forest", "component_sizes") else events for n in costs}
    e = graph(spark, SMALLEST, "user_type")
    twice = e.select("u", "w").join(e.select("u", "v").filter("v is not null"), "u")
    assert me.passes(me.rows_read(twice), me.rows_read(e)) == 2


def test_totals_put_each_graph_in_order_once(spark, monkeypatch):
    """Fifteen rows on three graphs: each joined, counted and sorted its graph anew, and compared weights that no column tells."""
    sorts, compared, first = [], [], me.in_order
    monkeypatch.setattr(me, "in_order", lambda *a: sorts.append(1) or first(*a))
    monkeypatch.setattr(me, "weight_comparisons", lambda *a: compared.append(1) or 0)
    rows = methods.QUERIES["total_times_stream_vs_whole"](spark, SMALLEST).collect()
    assert len(rows) == 15 and len(sorts) == 3
    want = {n: graph(spark, SMALLEST, measures.ROWS[p][0]).count() for n, p in measures.TOTALS.items()}
    assert {(r.problem, r.m) for r in rows} == set(want.items()) and all(r.groups == 1 for r in rows if r.mode == "whole")


def test_inverse_column_beyond_two_to_the_sixteenth(spark):
    from pyspark.sql import functions as F

    from sparsecert.functions.bounds import inv_ackermann, inv_ackermann_column

    rows = [(m, n) for n in (2, 16, 17, 65536, 65537, 989_994, 10**9) for m in (1, n, 2 * n, 3 * n, 40 * n)]
    got = spark.createDataFrame(rows, "m bigint, n bigint").select("m", "n", inv_ackermann_column(F.col("m"), F.col("n")).alias("i")).collect()
    assert {(r.m, r.n): r.i for r in got} == {(m, n): inv_ackermann(m, n) for m, n in rows}

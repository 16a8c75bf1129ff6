"""The DataFrame methods: edge cases, plans, tiers, streams and table functions."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from sparsecert.baselines import per_edge
from sparsecert.functions import sql as table_functions
from sparsecert.kernels.fold import GroupPolicy, of
from sparsecert.operators import edges as E
from sparsecert.operators import graph as g
from sparsecert.plans import relational
from sparsecert.plans.batch import CertEngine, choose, clean, local_certs, measured, rejected
from sparsecert.plans.shared import shared_path
from sparsecert.sources import edge_stream, generated
from sparsecert.sources.tables import read_edges, write_edges
from sparsecert.streaming.certs import CertSink, RateListener

SCHEMA = "u bigint, v bigint, w bigint, eid bigint, seq bigint"


def made(spark, rows):
    return spark.createDataFrame([(u, v, w, i, i) for i, (u, v, w) in enumerate(rows)], SCHEMA)


def pairs_of(df, *columns):
    return sorted(tuple(r) for r in df.select(*columns).collect())


def test_components_of_a_graph_with_loops_nulls_and_isolated_vertices(spark):
    e = made(spark, [(5, 5, 0), (1, 2, 0), (2, 3, 0), (None, 1, 0), (7, 8, 0)])
    vertices = spark.createDataFrame([(9,), (1,)], "v bigint")
    assert pairs_of(g.components(e, vertices), "v", "component") == [(1, 1), (2, 1), (3, 1), (5, 5), (7, 7), (8, 7), (9, 9)]
    assert sorted(r.reason for r in rejected(e).collect()) == ["an end is missing", "loop"]
    with pytest.raises(Exception, match="loop"):
        clean(e, on_loop="fail").collect()


def test_empty_graph(spark):
    e = made(spark, [])
    assert g.components(e).count() == 0
    assert g.min_forest(e).count() == 0
    assert g.is_connected(e).first().connected
    assert g.is_k_vertex_connected(e, 2).first().holds
    assert g.is_k_edge_connected(e, 2).first().holds
    assert relational.relational_components(e).count() == 0
    assert relational.relational_min_forest(e).count() == 0


def test_refused_edges(spark):
    with pytest.raises(Exception, match="negative"):
        g.min_forest(made(spark, [(1, 2, -1)])).collect()
    gone = made(spark, [(1, 2, 1)]).withColumn("op", F.lit("D"))
    with pytest.raises(Exception, match="insertions"):
        g.components(gone).collect()


@pytest.mark.parametrize(("name", "k", "vertex", "edge"), [("path", 2, False, False), ("cycle", 2, True, True), ("clique", 4, True, True), ("star", 1, True, True), ("grid", 2, True, True), ("grid", 3, False, False)])
def test_golden_connectivity(spark, name, k, vertex, edge):
    e = {"path": lambda: generated.path(spark, 6), "cycle": lambda: generated.cycle(spark, 6), "clique": lambda: generated.clique(spark, 6), "star": lambda: generated.star(spark, 6), "grid": lambda: generated.grid(spark, 3, 4)}[name]()
    assert g.is_k_vertex_connected(e, k, parts=2).first().holds == vertex
    assert g.is_k_edge_connected(e, k, parts=2).first().holds == edge


def test_complete_bipartite(spark):
    e = generated.complete_bipartite(spark, 3, 4)
    assert g.is_bipartite(e).first().holds
    assert {r.side for r in g.bipartition(e).filter("v < 3").collect()} == {0}
    assert g.is_k_vertex_connected(e, 3).first().holds
    assert not g.is_k_vertex_connected(e, 4).first().holds
    assert not g.is_bipartite(generated.cycle(spark, 7)).first().holds


def test_sides_of_one_odd_and_one_even_component(spark):
    e = made(spark, [(1, 2, 0), (2, 3, 0), (3, 1, 0), (10, 11, 0)])
    assert pairs_of(g.bipartition(e).filter("bipartite"), "v", "side") == [(10, 0), (11, 1)]
    assert g.bipartition(e, per_component=False).filter("bipartite").count() == 0
    assert not g.stop_when_odd(e).first().holds


def test_answers_are_the_same_in_any_order_and_tier(spark):
    e = generated.random_graph(spark, 60, 70, seed=3)
    want = pairs_of(g.components(e, parts=1), "v", "component")
    assert pairs_of(g.components(e, parts=5, policy=GroupPolicy.edges(4)), "v", "component") == want
    assert pairs_of(g.components(e, tier="relational"), "v", "component") == want
    assert pairs_of(per_edge.whole_components(e), "v", "component") == want
    forest = pairs_of(g.min_forest(e, parts=1), "eid")
    assert pairs_of(g.min_forest(e, parts=6, policy=GroupPolicy.linear()), "eid") == forest
    assert pairs_of(relational.relational_min_forest(clean(e)), "eid") == forest
    assert pairs_of(per_edge.per_edge_min_forest(e, "linkcut"), "eid") == forest
    assert pairs_of(per_edge.per_edge_min_forest(e, "walk"), "eid") == forest


def test_relational_certificates(spark):
    e = generated.random_graph(spark, 12, 60, seed=5)
    for k in (2, 3):
        want = g.is_k_edge_connected(e, k).first().holds
        assert g.is_k_edge_connected(relational.relational_edge_cert(clean(e), k), k).first().holds == want
        want = g.is_k_vertex_connected(e, k).first().holds
        assert g.is_k_vertex_connected(relational.relational_vertex_cert(clean(e), k), k).first().holds == want


def test_min_tree_needs_a_connected_graph(spark):
    assert g.min_tree(generated.cycle(spark, 5)).count() == 4
    with pytest.raises(Exception, match="connected"):
        g.min_tree(made(spark, [(1, 2, 1), (3, 4, 1)])).collect()


def test_a_cert_is_made_before_any_shuffle_and_reads_once(spark, tmp_path):
    path = str(tmp_path / "edges")
    write_edges(generated.random_graph(spark, 50, 400), path)
    cert = CertEngine(of("components")).run(read_edges(spark, path))
    plan = cert.edges._jdf.queryExecution().executedPlan().toString()
    assert plan.count("FileScan") == 1
    assert plan.rindex("MapInArrow") > plan.rindex("Exchange"), "the deepest node above the scan is the certificate"
    assert "ReadSchema: struct<u:bigint,v:bigint,w:bigint,eid:bigint>" in plan
    assert cert.size_bound_ok(50)


def test_measures(spark):
    e = generated.random_graph(spark, 20, 205, seed=1)
    m = e.count()
    rows = measured(e, of("components"), GroupPolicy.linear(), 20).collect()
    assert len(rows) == -(-m // 20)
    assert sum(r.edges_in for r in rows) == m == rows[0].edges_read
    assert all(r.peak_edges <= 19 + 20 for r in rows)


def test_planner():
    assert choose(1000, 10_000).tier == "merge_tree"
    assert choose(10**9, 6 * 10**12).tier == "relational"
    assert choose(3 * 10**7, 10**9).tier in ("merge_tree", "grid")


@pytest.mark.parametrize("fmt", ["parquet", "csv", "json", "orc"])
def test_edge_files(spark, tmp_path, fmt):
    e = generated.random_graph(spark, 9, 30)
    write_edges(e, str(tmp_path / fmt), fmt)
    assert pairs_of(read_edges(spark, str(tmp_path / fmt), fmt), "u", "v", "w", "eid") == pairs_of(e, "u", "v", "w", "eid")


def test_stream_restarts_where_it_stopped(spark, tmp_path):
    e = generated.random_graph(spark, 40, 90, seed=8)
    source, sink = str(tmp_path / "in"), CertSink(shared_path(spark, "cert"), of("min_forest"))
    stream = lambda: spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", 1).parquet(source)
    write_edges(e.filter("eid % 2 = 0").repartition(2), source)
    sink.start(stream(), str(tmp_path / "progress")).awaitTermination()
    write_edges(e.filter("eid % 2 = 1").repartition(2), source, mode="append")
    sink.start(stream(), str(tmp_path / "progress")).awaitTermination()
    assert pairs_of(sink.latest(spark), "eid") == pairs_of(g.min_forest(e), "eid")


def test_batch_that_runs_again_writes_the_same_version(spark):
    e = generated.random_graph(spark, 30, 60, seed=2)
    sink = CertSink(shared_path(spark, "cert"), of("edge", 2))
    sink(e.filter("eid < 30"), 0)
    sink(e.filter("eid >= 30"), 1)
    once = pairs_of(sink.latest(spark), "eid")
    sink(e.filter("eid >= 30"), 1)
    assert pairs_of(sink.latest(spark), "eid") == once


def test_ordered_edge_stream(spark, tmp_path):
    path = str(tmp_path / "edges")
    e = generated.random_graph(spark, 25, 60, seed=4)
    write_edges(e, path)
    edge_stream.register(spark)
    listener = RateListener()
    spark.streams.addListener(listener)
    sink = CertSink(shared_path(spark, "cert"), of("components"))
    q = sink.start(spark.readStream.format("edge_stream").option("path", path).option("edgesPerBatch", "25").load(), str(tmp_path / "progress"), processingTime="0 seconds")
    q.processAllAvailable()
    q.stop()
    spark.streams.removeListener(listener)
    assert pairs_of(g.components(sink.latest(spark)), "v", "component") == pairs_of(g.components(e), "v", "component")


def test_table_functions(spark):
    table_functions.register(spark)
    made(spark, [(1, 2, 3), (2, 3, 1), (3, 1, 2), (5, 6, 9)]).createOrReplaceTempView("some_edges")
    one = "WITH SINGLE PARTITION"
    assert sorted(map(tuple, spark.sql(f"SELECT * FROM graph_components(TABLE(SELECT u, v FROM some_edges) {one})").collect())) == [(1, 1), (2, 1), (3, 1), (5, 5), (6, 5)]
    assert sorted(r.w for r in spark.sql(f"SELECT * FROM graph_min_forest(TABLE(SELECT u, v, w FROM some_edges) {one})").collect()) == [1, 2, 9]
    assert sorted(r.side for r in spark.sql(f"SELECT * FROM graph_bipartition(TABLE(SELECT u, v FROM some_edges) {one}) WHERE side IS NOT NULL").collect()) == [0, 1]
    assert tuple(spark.sql(f"SELECT * FROM graph_connectivity(TABLE(SELECT u, v FROM some_edges) {one}, 1, 2, 5)").first()) == (1, 2, 2, 2)
    assert spark.sql(f"SELECT * FROM graph_vertex_cert(TABLE(SELECT u, v FROM some_edges) {one}, 1)").count() == 3
    assert spark.sql("SELECT inv_ackermann(16, 16)").first()[0] == 3


def test_joins_of_time_and_bands(spark):
    left = spark.createDataFrame([(1, 1.0), (2, 5.0)], "i int, a double")
    right = spark.createDataFrame([(1, 1.9), (2, 4.0), (3, 9.0)], "j int, b double")
    assert pairs_of(E.band_join(left, right, "a", "b", 1.0), "i", "j") == [(1, 1), (2, 2)]


def test_weak_certificates_fail_under_union():
    got = per_edge.weak_cert_counterexample()
    assert got["halves_agree"]
    assert not got["union_agrees"]


def test_local_certs_keep_vertices_numbers_of_any_size(spark):
    big = (1 << 62) + 5
    e = made(spark, [(big, 1, 0), (1, big - 1, 0)])
    assert local_certs(clean(e), of("components"), GroupPolicy.linear()).count() == 2
    assert np.array_equal(sorted(r.v for r in g.components(e).collect()), [1, big - 1, big])

"""The operators around the methods as queries: filters, joins, aggregates, windows, sets, scalar functions."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from sparsecert.functions import sql as table_functions
from sparsecert.kernels.fold import of
from sparsecert.operators import edges as E
from sparsecert.operators import graph as g
from sparsecert.plans.batch import CertEngine, certs_by_key
from sparsecert.plans.relational import cut
from sparsecert.sources.graphs import DUCK_SQL, KIND, cosine, event_order, graph, hashed, hashed_sql
from sparsecert.sources.tables import load
from sparsecert.workloads.methods import bipartition_sql, components_sql, k_edge_slice_sql, k_vertex_slice_sql, min_forest_sql, query, ready


def t(name: str):
    return lambda s, d: load(s, d, name)


def gr(name: str) -> str:
    return f"({DUCK_SQL[name]})"


# ---- projection and predicates

query("project_edges", "SELECT CAST(l_suppkey AS BIGINT) AS u, CAST(l_partkey AS BIGINT) AS v, CAST(round(l_quantity * 100) AS BIGINT) AS w FROM lineitem")(lambda s, d: E.project_edges(load(s, d, "lineitem"), F.col("l_suppkey"), F.col("l_partkey"), F.round(F.col("l_quantity") * 100)))
query("filter_compare", "SELECT l_orderkey, l_linenumber FROM lineitem WHERE l_quantity >= 45 AND l_discount < 0.03")(lambda s, d: load(s, d, "lineitem").filter((F.col("l_quantity") >= 45) & (F.col("l_discount") < 0.03)).select("l_orderkey", "l_linenumber"))
query("filter_between", "SELECT o_orderkey FROM orders WHERE o_totalprice BETWEEN 1000 AND 50000")(lambda s, d: load(s, d, "orders").filter(F.col("o_totalprice").between(1000, 50000)).select("o_orderkey"))
query("filter_in", "SELECT o_orderkey FROM orders WHERE o_orderstatus IN ('F', 'P')")(lambda s, d: load(s, d, "orders").filter(F.col("o_orderstatus").isin("F", "P")).select("o_orderkey"))
query("filter_like", "SELECT p_partkey, p_name FROM part WHERE p_name LIKE '%a%e%'")(lambda s, d: load(s, d, "part").filter(F.col("p_name").like("%a%e%")).select("p_partkey", "p_name"))
query("filter_rlike", "SELECT p_partkey FROM part WHERE regexp_matches(p_type, '^[A-M].*[L-Z]$')")(lambda s, d: load(s, d, "part").filter(F.col("p_type").rlike("^[A-M].*[L-Z]$")).select("p_partkey"))
query("filter_nullsafe", "SELECT c_custkey FROM customer LEFT JOIN orders ON c_custkey = o_custkey WHERE o_orderstatus IS NOT DISTINCT FROM NULL")(lambda s, d: load(s, d, "customer").join(load(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left").filter(F.col("o_orderstatus").eqNullSafe(F.lit(None).cast("string"))).select("c_custkey"))
query("filter_three_valued", "SELECT c_custkey FROM customer LEFT JOIN orders ON c_custkey = o_custkey WHERE NOT (o_totalprice > 100000)")(lambda s, d: load(s, d, "customer").join(load(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left").filter(~(F.col("o_totalprice") > 100000)).select("c_custkey"))
query("case_bucket", "SELECT CASE WHEN w > 10000000 THEN 'high' WHEN w > 5000000 THEN 'middle' ELSE 'low' END AS class, count(*) AS n FROM " + gr("premium_cust_supp") + " GROUP BY 1")(lambda s, d: graph(s, d, "premium_cust_supp").groupBy(F.when(F.col("w") > 10_000_000, "high").when(F.col("w") > 5_000_000, "middle").otherwise("low").alias("class")).agg(F.count(F.lit(1)).alias("n")))
query("drop_loops", "SELECT count(*) AS n FROM (SELECT user_id AS a, lead(user_id) OVER (ORDER BY ts, event_id) AS b FROM events) WHERE a <> b")(lambda s, d: E.drop_loops(event_order(load(s, d, "events")).select(F.col("user_id").alias("u"), F.col("next_user").alias("v"))).agg(F.count(F.lit(1)).alias("n")))
query("canonical_pairs", f"SELECT least(u, v) AS u, greatest(u, v) AS v, w, eid FROM {gr('co_purchase')} WHERE w > 15000000")(lambda s, d: E.canonical(graph(s, d, "co_purchase").filter("w > 15000000")).select("u", "v", "w", "eid"))
query("dedupe_pairs", f"SELECT DISTINCT least(u, v) AS u, greatest(u, v) AS v FROM {gr('supplier_part')}")(lambda s, d: E.dedupe_pairs(graph(s, d, "supplier_part")))
query("cap_multiplicity", f"SELECT u, v, eid FROM (SELECT *, row_number() OVER (PARTITION BY u, v ORDER BY eid) AS n FROM {gr('nation_trade')}) WHERE n <= 3")(lambda s, d: E.cap_multiplicity(graph(s, d, "nation_trade"), 3).select("u", "v", "eid"))
query("lightest_per_pair", f"SELECT least(u, v) AS u, greatest(u, v) AS v, min((w, eid))[1] AS w, min((w, eid))[2] AS eid FROM {gr('supplier_part')} GROUP BY 1, 2")(lambda s, d: g.lightest_per_pair(graph(s, d, "supplier_part")))
query("induced_subgraph", f"SELECT * FROM {gr('small_user_slice')}")(lambda s, d: E.induced_subgraph(e := graph(s, d, "user_adjacent"), g.all_vertices(e).filter(F.col("v") < 6 * KIND + 14)).select("u", "v", "w", "eid"))
query("remove_vertices", f"SELECT * FROM {gr('user_adjacent')} WHERE u >= {6 * KIND + 14} AND v >= {6 * KIND + 14}")(lambda s, d: g.remove_vertices(e := graph(s, d, "user_adjacent"), g.all_vertices(e).filter(F.col("v") < 6 * KIND + 14)).select("u", "v", "w", "eid"))
query("remove_edges", f"SELECT * FROM {gr('user_adjacent')} WHERE w >= 100")(lambda s, d: g.remove_edges(e := graph(s, d, "user_adjacent"), e.filter("w < 100")).select("u", "v", "w", "eid"))
query("union_graph", f"SELECT u, v, w, eid FROM {gr('supplier_part')}")(lambda s, d: E.union_graph((e := graph(s, d, "supplier_part").drop("seq")).filter("eid % 2 = 0"), e.filter("eid % 2 = 1")))
query("prefix_graph", f"SELECT u, v, w, eid FROM {gr('user_adjacent')} x WHERE (SELECT seq FROM (SELECT event_id, row_number() OVER (ORDER BY ts, event_id) AS seq FROM events) o WHERE o.event_id = x.eid) <= 500")(lambda s, d: E.prefix_graph(graph(s, d, "user_adjacent"), 500).select("u", "v", "w", "eid"))
query("degree_filter", f"WITH e AS {gr('user_type')}, k AS (SELECT v FROM (SELECT u AS v FROM e UNION ALL SELECT v FROM e) GROUP BY v HAVING count(*) >= 70) SELECT u, v, eid FROM e WHERE u IN (SELECT v FROM k) AND v IN (SELECT v FROM k)")(lambda s, d: E.degree_filter(graph(s, d, "user_type"), 70).select("u", "v", "eid"))
query("sample_edges")(lambda s, d: E.sample_edges(graph(s, d, "co_purchase"), 0.1, 7).select("u", "v", "eid"))


@query("sample_edges_share", f"SELECT count(*) AS m, true AS near_a_tenth, CAST(0 AS BIGINT) AS foreign_edges FROM {gr('co_purchase')}")
def _(s: SparkSession, d: str) -> DataFrame:
    """A sample of a tenth is near a tenth (5 standard errors), and of the graph."""
    e = graph(s, d, "co_purchase").select("u", "v", "eid")
    some = E.sample_edges(e, 0.1, 7)
    m, n = e.agg(F.count(F.lit(1)).alias("m")), some.agg(F.count(F.lit(1)).alias("n"))
    foreign = some.exceptAll(e).agg(F.count(F.lit(1)).alias("foreign_edges"))
    return m.crossJoin(n).crossJoin(foreign).select("m", (F.abs(F.col("n") - 0.1 * F.col("m")) <= 5 * F.sqrt(0.09 * F.col("m"))).alias("near_a_tenth"), "foreign_edges")

# ---- joins

query("nation_region_supplier", "SELECT s_suppkey, n_name, r_name FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey")(
    lambda s, d: load(s, d, "supplier").join(F.broadcast(load(s, d, "nation").join(load(s, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))), F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", "n_name", "r_name")
)  # nations and regions are fixed in number
for _hint in ("shuffle_hash", "merge"):
    query(f"customer_part_edges_{_hint}", f"SELECT u, v, count(*) AS copies FROM {gr('customer_part')} GROUP BY u, v")(
        lambda s, d, h=_hint: load(s, d, "orders").hint(h).join(load(s, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy((3 * KIND + F.col("o_custkey")).alias("u"), (2 * KIND + F.col("l_partkey")).alias("v")).agg(F.count(F.lit(1)).alias("copies"))
    )
query("nation_trade_edges", f"SELECT u, v, count(*) AS copies, CAST(sum(w) AS BIGINT) AS weight FROM {gr('nation_trade')} GROUP BY u, v")(lambda s, d: graph(s, d, "nation_trade").groupBy("u", "v").agg(F.count(F.lit(1)).alias("copies"), F.sum("w").alias("weight")))
query("co_purchase_edges", f"SELECT u, v, count(*) AS copies FROM {gr('co_purchase')} GROUP BY u, v HAVING count(*) > 1")(lambda s, d: graph(s, d, "co_purchase").groupBy("u", "v").agg(F.count(F.lit(1)).alias("copies")).filter("copies > 1"))
query("degree_of_all_parts", "SELECT p_partkey, count(l_partkey) AS degree FROM part LEFT JOIN lineitem ON p_partkey = l_partkey GROUP BY p_partkey")(lambda s, d: load(s, d, "part").join(load(s, d, "lineitem").groupBy("l_partkey").agg(F.count(F.lit(1)).alias("n")), F.col("p_partkey") == F.col("l_partkey"), "left").select("p_partkey", F.coalesce("n", F.lit(0)).alias("degree")))
query("right_join_orders", "SELECT c_custkey, count(o_orderkey) AS n FROM orders RIGHT JOIN customer ON o_custkey = c_custkey GROUP BY c_custkey")(lambda s, d: load(s, d, "orders").join(load(s, d, "customer"), F.col("o_custkey") == F.col("c_custkey"), "right").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n")))
query("isolated_vertices", "SELECT c_custkey FROM customer LEFT JOIN orders ON c_custkey = o_custkey WHERE o_custkey IS NULL")(lambda s, d: load(s, d, "customer").join(load(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey"))
query("nation_full_outer", "SELECT n_nationkey, s_nationkey, coalesce(n, 0) AS suppliers FROM (SELECT * FROM nation WHERE n_nationkey < 20) FULL JOIN (SELECT s_nationkey, count(*) AS n FROM supplier WHERE s_nationkey > 5 GROUP BY 1) ON n_nationkey = s_nationkey")(
    lambda s, d: load(s, d, "nation").filter("n_nationkey < 20").join(load(s, d, "supplier").filter("s_nationkey > 5").groupBy("s_nationkey").agg(F.count(F.lit(1)).alias("n")), F.col("n_nationkey") == F.col("s_nationkey"), "full").select("n_nationkey", "s_nationkey", F.coalesce("n", F.lit(0)).alias("suppliers"))
)
query("nation_full_outer_whole", "SELECT n_nationkey, s_nationkey, coalesce(n, 0) AS suppliers FROM nation FULL JOIN (SELECT s_nationkey, count(*) AS n FROM supplier GROUP BY 1) ON n_nationkey = s_nationkey")(
    lambda s, d: load(s, d, "nation").join(load(s, d, "supplier").groupBy("s_nationkey").agg(F.count(F.lit(1)).alias("n")), F.col("n_nationkey") == F.col("s_nationkey"), "full").select("n_nationkey", "s_nationkey", F.coalesce("n", F.lit(0)).alias("suppliers"))
)
query("customers_with_orders", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")(lambda s, d: load(s, d, "customer").join(load(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey"))
query("customers_without_orders", "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_totalprice > 200000)")(lambda s, d: load(s, d, "customer").join(load(s, d, "orders").filter("o_totalprice > 200000"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey"))


@query("not_in_null", "SELECT count(*) AS n FROM customer WHERE c_custkey NOT IN (SELECT CASE WHEN o_orderkey > 10 THEN o_custkey END FROM orders)")
def _(s: SparkSession, d: str) -> DataFrame:
    load(s, d, "customer").createOrReplaceTempView("customer")
    load(s, d, "orders").createOrReplaceTempView("orders")
    return s.sql("SELECT count(*) AS n FROM customer WHERE c_custkey NOT IN (SELECT CASE WHEN o_orderkey > 10 THEN o_custkey END FROM orders)")


query("embedding_pairs_near", f"SELECT u, v, w FROM {gr('embedding_pairs')} WHERE w < 500000")(lambda s, d: graph(s, d, "embedding_pairs").filter("w < 500000").select("u", "v", "w"))
query("balance_band_edges", "SELECT a.s_suppkey AS u, b.s_suppkey AS v FROM supplier a JOIN supplier b ON a.s_suppkey < b.s_suppkey AND abs(a.s_acctbal - b.s_acctbal) <= 50")(
    lambda s, d: E.band_join(load(s, d, "supplier").select(F.col("s_suppkey").alias("u"), F.col("s_acctbal").alias("a")), load(s, d, "supplier").select(F.col("s_suppkey").alias("v"), F.col("s_acctbal").alias("b")), "a", "b", 50.0).filter("u < v").select("u", "v")
)
query("event_asof_purchase", "SELECT e.event_id, p.event_id AS last_id FROM events e ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE value > 150 GROUP BY 1, 2) p ON e.user_id = p.user_id AND e.ts >= p.ts")(
    lambda s, d: E.asof_join(load(s, d, "events").select("event_id", "user_id", "ts"), load(s, d, "events").filter("value > 150").groupBy("user_id", "ts").agg(F.max("event_id").alias("last_id")).withColumn("event_id", F.col("last_id")), "user_id", "ts", "last_id", "event_id").select("event_id", "last_id")
)
query("events_within_10min", "SELECT a.event_id AS first_id, b.event_id AS next_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE")(
    lambda s, d: E.interval_join(load(s, d, "events").select("user_id", F.col("ts").alias("a"), F.col("event_id").alias("first_id")), load(s, d, "events").select("user_id", F.col("ts").alias("b"), F.col("event_id").alias("next_id")), "user_id", "a", "b", 600).select("first_id", "next_id")
)


@query("top3_partners", f"WITH c AS (SELECT u, v, count(*) AS copies FROM {gr('nation_trade')} GROUP BY 1, 2), b AS (SELECT u, v, copies FROM c UNION ALL SELECT v, u, copies FROM c) SELECT u, v, copies FROM (SELECT *, row_number() OVER (PARTITION BY u ORDER BY copies DESC, v) AS r FROM b) WHERE r <= 3")
def _(s: SparkSession, d: str) -> DataFrame:
    c = E.multiplicity(graph(s, d, "nation_trade"))
    both = c.union(c.select(F.col("v").alias("u"), F.col("u").alias("v"), "copies"))
    vertices = both.select(F.col("u").alias("x")).distinct()
    best = both.withColumn("r", F.row_number().over(Window.partitionBy("u").orderBy(F.col("copies").desc(), "v"))).filter("r <= 3")
    return vertices.join(best, F.col("x") == F.col("u")).select("u", "v", "copies")


@query("top3_partners_lateral", f"WITH c AS (SELECT u, v, count(*) AS copies FROM {gr('nation_trade')} GROUP BY 1, 2) SELECT n.u, l.v, l.copies FROM (SELECT DISTINCT u FROM c) n, LATERAL (SELECT v, copies FROM c WHERE c.u = n.u ORDER BY copies DESC, v LIMIT 3) l")
def _(s: SparkSession, d: str) -> DataFrame:
    c = E.multiplicity(graph(s, d, "nation_trade"))
    c.createOrReplaceTempView("trade_copies")
    return s.sql("SELECT n.u, l.v, l.copies FROM (SELECT DISTINCT u FROM trade_copies) n, LATERAL (SELECT v, copies FROM trade_copies c WHERE c.u = n.u ORDER BY copies DESC, v LIMIT 3) l")


query("hub_join", f"SELECT count(*) AS n, CAST(sum(e.w) AS BIGINT) AS weight FROM {gr('nation_trade')} e JOIN (SELECT u, count(*) AS degree FROM {gr('nation_trade')} GROUP BY u) k ON k.u = e.u WHERE degree > 1000")(
    lambda s, d: E.salted_join(e := graph(s, d, "nation_trade"), e.groupBy("u").agg(F.count(F.lit(1)).alias("degree")).filter("degree > 1000"), "u").agg(F.count(F.lit(1)).alias("n"), F.sum("w").alias("weight"))
)

# ---- aggregates

query("degree", f"SELECT v, count(*) AS degree, CAST(sum(w) AS BIGINT) AS weight FROM (SELECT u AS v, w FROM {gr('supplier_part')} UNION ALL SELECT v, w FROM {gr('supplier_part')}) GROUP BY v")(lambda s, d: E.degrees(graph(s, d, "supplier_part")))
query("multiplicity", f"SELECT u, v, count(*) AS copies FROM {gr('supplier_part')} GROUP BY u, v")(lambda s, d: E.multiplicity(graph(s, d, "supplier_part")))
query("neighbour_list", f"SELECT v, list_aggregate(list_sort(list_distinct(list(x))), 'string_agg', ',') AS near FROM (SELECT u AS v, v AS x FROM {gr('small_user_slice')} UNION ALL SELECT v, u FROM {gr('small_user_slice')}) GROUP BY v")(lambda s, d: E.neighbours(graph(s, d, "small_user_slice")).select("v", F.concat_ws(",", F.col("near").cast("array<string>")).alias("near")))
query("neighbour_list_whole")(lambda s, d: E.neighbours(graph(s, d, "user_adjacent")).select("v", F.concat_ws(",", F.col("near").cast("array<string>")).alias("near")))
query("distinct_neighbours", f"SELECT v, count(DISTINCT x) AS near FROM (SELECT u AS v, v AS x FROM {gr('supplier_part')} UNION ALL SELECT v, u FROM {gr('supplier_part')}) GROUP BY v")(lambda s, d: E.distinct_neighbours(graph(s, d, "supplier_part")))


@query("approx_vertices", f"SELECT count(DISTINCT v) AS vertices, true AS within_5_percent, true AS sketch_within_5_percent FROM (SELECT u AS v FROM {gr('supplier_part')} UNION ALL SELECT v FROM {gr('supplier_part')})")
def _(s: SparkSession, d: str) -> DataFrame:
    """The exact count, and whether two sketches come near it."""
    ends = graph(s, d, "supplier_part").select(F.explode(F.array("u", "v")).alias("v"))
    n = F.count_distinct("v")
    return ends.agg(n.alias("vertices"), (F.abs(F.approx_count_distinct("v", 0.01) - n) <= 0.05 * n).alias("within_5_percent"), (F.abs(F.hll_sketch_estimate(F.hll_sketch_agg("v")) - n) <= 0.05 * n).alias("sketch_within_5_percent"))


@query("weight_quantiles_kll", f"SELECT q, true AS within_2_percent, n FROM (SELECT unnest([0.25, 0.5, 0.75]) AS q) t, (SELECT count(*) AS n FROM {gr('supplier_part')})")
def _(s: SparkSession, d: str) -> DataFrame:
    """Quantiles by a KLL sketch: the exact rank of each is near what was asked for."""
    e = graph(s, d, "supplier_part").select("w")
    asked = (0.25, 0.5, 0.75)
    sketch = e.agg(F.kll_sketch_agg_bigint("w").alias("k")).select(*[F.kll_sketch_get_quantile_bigint("k", F.lit(q)).alias(f"q{i}") for i, q in enumerate(asked)])
    ranks = e.crossJoin(F.broadcast(sketch)).agg(F.count(F.lit(1)).alias("n"), *[c for i in range(3) for c in (F.count_if(F.col("w") < F.col(f"q{i}")).alias(f"lo{i}"), F.count_if(F.col("w") <= F.col(f"q{i}")).alias(f"hi{i}"))])
    near = lambda i, q: (F.col(f"lo{i}") <= (q + 0.02) * F.col("n")) & (F.col(f"hi{i}") >= (q - 0.02) * F.col("n"))
    rows = F.explode(F.array(*[F.struct(F.lit(q).alias("q"), near(i, q).alias("ok")) for i, q in enumerate(asked)])).alias("r")
    return ranks.select("n", rows).select(F.col("r.q").cast("decimal(3,2)").alias("q"), F.col("r.ok").alias("within_2_percent"), "n")


query("weight_quantiles", f"SELECT round(quantile_cont(w, 0.25), 4) AS q1, round(quantile_cont(w, 0.5), 4) AS q2, round(quantile_cont(w, 0.75), 4) AS q3 FROM {gr('supplier_part')}")(lambda s, d: graph(s, d, "supplier_part").agg(*[F.round(F.percentile("w", q), 4).alias(n) for n, q in (("q1", 0.25), ("q2", 0.5), ("q3", 0.75))]))
@query("weight_quantiles_sketch", f"SELECT true AS within_1_percent, count(*) AS n FROM {gr('supplier_part')}")
def _(s: SparkSession, d: str) -> DataFrame:
    """The median by a sketch: its exact rank is near the middle."""
    e = graph(s, d, "supplier_part").select("w")
    middle = e.agg(F.percentile_approx("w", 0.5, 1000).alias("q"))
    ranks = e.crossJoin(F.broadcast(middle)).agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("w") < F.col("q")).alias("lo"), F.count_if(F.col("w") <= F.col("q")).alias("hi"))
    return ranks.select(((F.col("lo") <= 0.51 * F.col("n")) & (F.col("hi") >= 0.49 * F.col("n"))).alias("within_1_percent"), "n")


query("heaviest_lightest_partner", f"SELECT u, arg_max(v, (w, -eid)) AS heaviest, arg_min(v, (w, eid)) AS lightest FROM {gr('nation_trade')} GROUP BY u")(lambda s, d: graph(s, d, "nation_trade").groupBy("u").agg(F.max_by("v", F.struct("w", -F.col("eid"))).alias("heaviest"), F.min_by("v", F.struct("w", "eid")).alias("lightest")))
query("degree_moments", f"SELECT round(avg(c), 6) AS mean, round(var_samp(c), 4) AS variance, round(stddev_pop(c), 6) AS deviation FROM (SELECT count(*) AS c FROM {gr('supplier_part')} GROUP BY u)")(lambda s, d: graph(s, d, "supplier_part").groupBy("u").agg(F.count(F.lit(1)).alias("c")).agg(F.round(F.avg("c"), 6).alias("mean"), F.round(F.var_samp("c"), 4).alias("variance"), F.round(F.stddev_pop("c"), 6).alias("deviation")))
query("price_qty_corr", "SELECT round(corr(l_extendedprice, l_quantity), 6) AS r FROM lineitem")(lambda s, d: load(s, d, "lineitem").agg(F.round(F.corr("l_extendedprice", "l_quantity"), 6).alias("r")))

_TRADE = "SELECT r_name AS region, n_name AS nation, year(o_orderdate) AS y FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


def _trade(s: SparkSession, d: str) -> DataFrame:
    o = load(s, d, "orders").join(load(s, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).join(load(s, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(load(s, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return o.select(F.col("r_name").alias("region"), F.col("n_name").alias("nation"), F.year("o_orderdate").cast("long").alias("y"))


query("trade_cube", f"SELECT region, y, count(*) AS n, CAST(grouping_id(region, y) AS BIGINT) AS gid FROM ({_TRADE}) GROUP BY CUBE (region, y)")(lambda s, d: _trade(s, d).cube("region", "y").agg(F.count(F.lit(1)).alias("n"), F.grouping_id("region", "y").alias("gid")))
query("trade_rollup", f"SELECT region, nation, count(*) AS n, CAST(grouping_id(region, nation) AS BIGINT) AS gid FROM ({_TRADE}) GROUP BY ROLLUP (region, nation)")(lambda s, d: _trade(s, d).rollup("region", "nation").agg(F.count(F.lit(1)).alias("n"), F.grouping_id("region", "nation").alias("gid")))


@query("trade_grouping_sets", f"SELECT region, nation, y, count(*) AS n FROM ({_TRADE}) GROUP BY GROUPING SETS ((region, y), (nation), ())")
def _(s: SparkSession, d: str) -> DataFrame:
    _trade(s, d).createOrReplaceTempView("trade_rows")
    return s.sql("SELECT region, nation, y, count(*) AS n FROM trade_rows GROUP BY GROUPING SETS ((region, y), (nation), ())")


query("segment_pivot", "SELECT c_mktsegment, count(*) FILTER (WHERE o_orderstatus = 'F') AS f, count(*) FILTER (WHERE o_orderstatus = 'O') AS o, count(*) FILTER (WHERE o_orderstatus = 'P') AS p FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")(
    lambda s, d: load(s, d, "orders").join(load(s, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1))).select("c_mktsegment", *[F.coalesce(c, F.lit(0)).alias(c.lower()) for c in "FOP"])
)
query("having_hubs", f"SELECT v, count(*) AS n FROM {gr('user_type')} GROUP BY v HAVING count(*) > 1000")(lambda s, d: graph(s, d, "user_type").groupBy("v").agg(F.count(F.lit(1)).alias("n")).filter("n > 1000"))
query("filtered_agg", f"SELECT u, count(*) FILTER (WHERE w > 5000) AS heavy, count(*) AS n FROM {gr('user_type')} GROUP BY u")(lambda s, d: graph(s, d, "user_type").groupBy("u").agg(F.count_if(F.col("w") > 5000).alias("heavy"), F.count(F.lit(1)).alias("n")))
query("all_any", f"SELECT u, bool_and(w > 10) AS every, bool_or(w > 9000) AS some FROM {gr('user_type')} GROUP BY u")(lambda s, d: graph(s, d, "user_type").groupBy("u").agg(F.bool_and(F.col("w") > 10).alias("every"), F.bool_or(F.col("w") > 9000).alias("some")))
query("string_agg_types", "SELECT user_id, string_agg(DISTINCT event_type, ',' ORDER BY event_type) AS types FROM events GROUP BY user_id")(lambda s, d: load(s, d, "events").groupBy("user_id").agg(F.array_join(F.array_sort(F.collect_set("event_type")), ",").alias("types")))
query("empty_and_global", f"SELECT count(*) AS n, sum(w) AS total, max(w) AS top FROM {gr('tiny_sparse')} WHERE w < 0")(lambda s, d: graph(s, d, "tiny_sparse").filter("w < 0").agg(F.count(F.lit(1)).alias("n"), F.sum("w").cast("double").alias("total"), F.max("w").alias("top")))


@query("components_per_segment", components_sql("SELECT c_mktsegment, " + DUCK_SQL["customer_order"].removeprefix("SELECT ") + " JOIN customer ON c_custkey = o_custkey").replace("SELECT v, c AS component FROM cc", "SELECT s.c_mktsegment AS segment, count(DISTINCT cc.c) AS components FROM cc JOIN (SELECT DISTINCT c_mktsegment, u FROM e) s ON s.u = cc.v GROUP BY 1"))
def _(s: SparkSession, d: str) -> DataFrame:
    """One count of components per market segment: tasks certify what they read of each, then a grouped aggregate in Arrow."""
    e = graph(s, d, "customer_order")
    seg = load(s, d, "customer").select((3 * KIND + F.col("c_custkey")).alias("u"), F.col("c_mktsegment").alias("segment"))
    return certs_by_key(e.join(seg, "u"), "segment", of("components")).groupBy("segment").agg(table_functions.component_count_agg("u", "v").alias("components"))


def _typed_edges(s: SparkSession, d: str) -> DataFrame:
    """Edges between users in turn, with the type of the event that made them."""
    return graph(s, d, "user_adjacent").join(load(s, d, "events").select(F.col("event_id").alias("eid"), "event_type"), "eid")


_TYPED = f"SELECT event_type AS t, u, v, w, eid FROM ({DUCK_SQL['user_adjacent']}) JOIN events ON event_id = eid"


@query("bipartite_per_event_type", f"""WITH RECURSIVE e AS ({_TYPED}), a AS (SELECT t, 2 * u AS u, 2 * v + 1 AS v FROM e UNION SELECT t, 2 * u + 1, 2 * v FROM e), b AS (SELECT t, u, v FROM a UNION SELECT t, v, u FROM a),
cc(t, v, c) USING KEY (t, v) AS (
  SELECT t, u, u FROM b GROUP BY t, u
  UNION
  (SELECT b.t, b.v, min(f.c) FROM cc f JOIN b ON b.t = f.t AND b.u = f.v JOIN recurring.cc r ON r.t = b.t AND r.v = b.v WHERE f.c < r.c GROUP BY b.t, b.v)
) SELECT x.t AS event_type, bool_and(x.c <> y.c) AS bipartite, count(*) AS vertices FROM cc x JOIN cc y ON y.t = x.t AND y.v = x.v + 1 AND x.v % 2 = 0 GROUP BY x.t""")
def _(s: SparkSession, d: str) -> DataFrame:
    certs = certs_by_key(_typed_edges(s, d), "event_type", of("bipartite"))
    ends = certs.select("event_type", F.explode(F.array("u", "v")).alias("v")).groupBy("event_type").agg(F.count_distinct("v").alias("vertices"))
    return certs.groupBy("event_type").agg(table_functions.is_bipartite_agg("u", "v").alias("bipartite")).join(ends, "event_type")


query("min_forest_per_kind", f"""WITH e AS ({_TYPED}), l AS (SELECT t, u, v, min((w, eid)) AS m FROM e GROUP BY 1, 2, 3),
k AS (SELECT t, u, v, m[1] AS w, row_number() OVER (PARTITION BY t ORDER BY m[1], u, v, m[2]) AS r FROM l),
d0 AS MATERIALIZED (SELECT t, u, v, r FROM k UNION ALL SELECT t, v, u, r FROM k UNION ALL SELECT DISTINCT t, u, u, 0 FROM (SELECT t, u FROM k UNION SELECT t, v FROM k)),
{", ".join(f"d{i + 1} AS MATERIALIZED (SELECT a.t, a.u, b.v, min(greatest(a.r, b.r)) AS r FROM d{i} a JOIN d{i} b ON a.t = b.t AND a.v = b.u GROUP BY 1, 2, 3)" for i in range(8))}
SELECT k.t AS kind, CAST(sum(k.w) AS BIGINT) AS weight, count(*) AS edges FROM k JOIN d8 d ON d.t = k.t AND d.u = k.u AND d.v = k.v WHERE d.r = k.r GROUP BY k.t""")(
    lambda s, d: certs_by_key(_typed_edges(s, d), "event_type", of("min_forest")).groupBy(F.col("event_type").alias("kind")).agg(F.sum("w").alias("weight"), F.count(F.lit(1)).alias("edges"))
)

_IN_YEAR = f"SELECT x.* FROM {gr('nation_trade')} x JOIN lineitem ON l_orderkey * 8 + l_linenumber = x.eid WHERE year(l_shipdate) = "
query("min_forest_per_year", " UNION ALL ".join(f"SELECT * FROM (SELECT CAST({y} AS BIGINT) AS y, CAST(sum(w) AS BIGINT) AS weight FROM ({min_forest_sql(_IN_YEAR + str(y), 25)})) WHERE weight IS NOT NULL" for y in range(1992, 2003)))(
    lambda s, d: certs_by_key(graph(s, d, "nation_trade").join(load(s, d, "lineitem").select((F.col("l_orderkey") * 8 + F.col("l_linenumber")).alias("eid"), F.year("l_shipdate").cast("long").alias("y")), "eid"), "y", of("min_forest")).groupBy("y").agg(F.sum("w").alias("weight"))
)

# ---- windows

_ORDERED = "SELECT *, row_number() OVER (ORDER BY ts, event_id) AS seq FROM events"
query("group_schedule", f"WITH e AS {gr('user_adjacent')}, n AS (SELECT count(*) AS m, (SELECT count(*) FROM (SELECT u FROM e UNION SELECT v FROM e)) AS r FROM e) SELECT t.gid AS group_id, CAST(least(r, m - t.gid * r) AS BIGINT) AS edges_in, m - t.gid * r < r AS is_tail FROM n, range(0, (m + r - 1) // r) t(gid)")(lambda s, d: E.group_schedule(e := graph(s, d, "user_adjacent"), g.all_vertices(e).count()))
_PAIR = f"SELECT u, v, count(*) AS copies FROM {gr('nation_trade')} GROUP BY 1, 2"
_by_u = lambda: Window.partitionBy("u").orderBy(F.col("copies").desc(), "v")  # noqa: E731  (a window needs a session)
_by_copies = lambda: Window.partitionBy("u").orderBy(F.col("copies").desc())  # noqa: E731  (a window needs a session)
query("rank_partners", f"SELECT u, v, rank() OVER w AS r, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd, ntile(4) OVER (PARTITION BY u ORDER BY copies DESC, v) AS q FROM ({_PAIR}) WINDOW w AS (PARTITION BY u ORDER BY copies DESC)")(
    lambda s, d: E.multiplicity(graph(s, d, "nation_trade")).select("u", "v", F.rank().over(_by_copies()).cast("long").alias("r"), F.dense_rank().over(_by_copies()).cast("long").alias("dr"), F.round(F.percent_rank().over(_by_copies()), 6).alias("pr"), F.round(F.cume_dist().over(_by_copies()), 6).alias("cd"), F.ntile(4).over(_by_u()).cast("long").alias("q"))
)
query("adjacent_users", "SELECT event_id, lead(user_id) OVER (ORDER BY ts, event_id) AS next_user FROM events")(lambda s, d: event_order(load(s, d, "events")).select("event_id", "next_user"))
_conv = lambda: Window.partitionBy("conv_id").orderBy("turn")  # noqa: E731  (a window needs a session)
query("turn_edges", "SELECT conv_id, turn, lag(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS before, lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS after FROM conversations")(lambda s, d: load(s, d, "conversations").select("conv_id", "turn", F.lag("turn").over(_conv()).alias("before"), F.lead("turn").over(_conv()).alias("after")))
_user = lambda: Window.partitionBy("user_id").orderBy("ts", "event_id")  # noqa: E731  (a window needs a session)
_whole = lambda: _user().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)  # noqa: E731  (a window needs a session)
query("first_last_value", "SELECT event_id, first_value(event_type) OVER w AS f, last_value(event_type) OVER w AS l, nth_value(event_type, 2) OVER w AS n2 FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")(lambda s, d: load(s, d, "events").select("event_id", F.first("event_type").over(_whole()).alias("f"), F.last("event_type").over(_whole()).alias("l"), F.nth_value("event_type", 2).over(_whole()).alias("n2")))


@query("running_new_vertices", f"WITH o AS ({_ORDERED}), f AS (SELECT user_id, min(seq) AS seq FROM o GROUP BY 1) SELECT o.event_id, CAST((SELECT count(*) FROM f WHERE f.seq <= o.seq) AS BIGINT) AS seen FROM o")
def _(s: SparkSession, d: str) -> DataFrame:
    """Users seen by each event: firsts are counted by day, then within the day."""
    o = event_order(load(s, d, "events")).withColumn("day", F.to_date("ts"))
    firsts = o.groupBy("user_id").agg(F.min("seq").alias("seq")).withColumn("new", F.lit(1)).select("seq", "new")
    marked = o.join(firsts, "seq", "left").withColumn("new", F.coalesce("new", F.lit(0)))
    days = marked.groupBy(F.col("day").alias("_d")).agg(F.sum("new").alias("k")).select("_d", F.coalesce(F.sum("k").over(Window.orderBy("_d").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    within = Window.partitionBy("day").orderBy("seq").rowsBetween(Window.unboundedPreceding, 0)
    return marked.withColumn("local", F.sum("new").over(within)).join(days, F.col("day") == F.col("_d")).select("event_id", (F.col("before") + F.col("local")).alias("seen"))


_hour = lambda: Window.partitionBy("user_id").orderBy(F.unix_seconds(F.col("ts").cast("timestamp"))).rangeBetween(-3600, 0)  # noqa: E731  (a window needs a session)
query("edges_last_hour", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY CAST(floor(epoch(ts)) AS BIGINT) RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS n FROM events")(lambda s, d: load(s, d, "events").select("event_id", F.count(F.lit(1)).over(_hour()).alias("n")))
query("moving_weight", "SELECT event_id, round(avg(CAST(round(value * 100) AS BIGINT)) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING), 4) AS mean FROM events")(lambda s, d: load(s, d, "events").select("event_id", F.round(F.avg(F.round(F.col("value") * 100).cast("long")).over(_user().rowsBetween(-2, 2)), 4).alias("mean")))
query("running_max_weight", f"SELECT eid, max(w) OVER (PARTITION BY u ORDER BY eid, v, w ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS top, round(w / sum(w) OVER (PARTITION BY u), 8) AS share FROM {gr('supplier_part')}")(lambda s, d: graph(s, d, "supplier_part").select("eid", F.max("w").over(Window.partitionBy("u").orderBy("eid", "v", "w").rowsBetween(Window.unboundedPreceding, 0)).alias("top"), F.round(F.col("w") / F.sum("w").over(Window.partitionBy("u")), 8).alias("share")))

@query("share_of_total", f"SELECT eid, v, round(w / sum(w) OVER (), 12) AS share FROM {gr('supplier_part')}")
def _(s: SparkSession, d: str) -> DataFrame:
    """Each edge's share of all weight: one total goes to all rows, where a window without a partition would hold them in one task."""
    e = graph(s, d, "supplier_part")
    return e.crossJoin(F.broadcast(e.agg(F.sum("w").alias("total")))).select("eid", "v", F.round(F.col("w") / F.col("total"), 12).alias("share"))


# ---- identity of strings

_STRINGS = {"line": ("documents", "SELECT unnest(string_split(text, chr(10))) AS x FROM documents"), "host": ("pages", "SELECT regexp_extract(url, '^[a-z]+://([^/?#]*)', 1) AS x FROM pages"), "type": ("events", "SELECT event_type AS x FROM events")}


def _strings(s: SparkSession, d: str, kind: str) -> DataFrame:
    t = load(s, d, _STRINGS[kind][0])
    return t.select({"line": lambda: F.explode(F.split("text", "\n")), "host": lambda: F.regexp_extract("url", r"^[a-z]+://([^/?#]*)", 1), "type": lambda: F.col("event_type")}[kind]().alias("x"))


@query("hash_collisions", " UNION ALL ".join(f"SELECT '{k}' AS kind, count(DISTINCT x) AS strings, count(DISTINCT x) - count(DISTINCT {hashed_sql('x')}) AS lost FROM ({sql})" for k, (_, sql) in _STRINGS.items()))
def _(s: SparkSession, d: str) -> DataFrame:
    """Strings that share their vertex with another: partial distinct counts by hash, no string is gathered."""
    out = None
    for kind in _STRINGS:
        x = _strings(s, d, kind).filter("x is not null")
        row = x.agg(F.count_distinct("x").alias("strings"), F.count_distinct(hashed(F.col("x"))).alias("hashes")).select(F.lit(kind).alias("kind"), "strings", (F.col("strings") - F.col("hashes")).alias("lost"))
        out = row if out is None else out.union(row)
    return out


for _kind, (_table, _sql) in _STRINGS.items():
    query(f"dictionary_of_{_kind}s", f"SELECT x, row_number() OVER (ORDER BY x) - 1 AS id FROM (SELECT DISTINCT x FROM ({_sql}) WHERE x IS NOT NULL)")(lambda s, d, k=_kind: E.dictionary(_strings(s, d, k), "x"))

# ---- order, limits, sets


@query("edges_by_weight", f"SELECT eid, row_number() OVER (ORDER BY w, u, v, eid) AS place FROM {gr('user_adjacent')}")
def _(s: SparkSession, d: str) -> DataFrame:
    """A global rank: weights are dealt to ranges by value, counted, and ranked within."""
    e = graph(s, d, "user_adjacent").withColumn("_b", F.floor(F.col("w") / 500))
    counts = e.groupBy(F.col("_b").alias("_k")).agg(F.count(F.lit(1)).alias("c")).select("_k", F.coalesce(F.sum("c").over(Window.orderBy("_k").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    return e.withColumn("local", F.row_number().over(Window.partitionBy("_b").orderBy("w", "u", "v", "eid"))).join(counts, F.col("_b") == F.col("_k")).select("eid", (F.col("before") + F.col("local")).alias("place"))


@query("sort_in_partition_order", f"SELECT count(*) AS n, CAST(0 AS BIGINT) AS out_of_order FROM {gr('supplier_part')}")
def _(s: SparkSession, d: str) -> DataFrame:
    """Rows whose predecessor in their partition is greater: none."""
    placed = graph(s, d, "supplier_part").repartition(4, "u").sortWithinPartitions("u", "w").select("u", "w", F.monotonically_increasing_id().alias("i"))
    one = Window.partitionBy(F.shiftright("i", 33)).orderBy("i")
    before = F.lag(F.struct("u", "w")).over(one)
    return placed.select((before > F.struct("u", "w")).alias("wrong")).agg(F.count(F.lit(1)).alias("n"), F.count_if("wrong").alias("out_of_order"))


query("sort_in_partition")(lambda s, d: graph(s, d, "supplier_part").repartition(4, "u").sortWithinPartitions("u", "w").select("u", "v", "w"))
query("k_lightest_edges", f"SELECT eid, w FROM {gr('supplier_part')} ORDER BY w, eid LIMIT 25")(lambda s, d: graph(s, d, "supplier_part").orderBy("w", "eid").limit(25).select("eid", "w"))
query("offset_page", f"SELECT eid, w FROM {gr('supplier_part')} ORDER BY w, eid LIMIT 20 OFFSET 40")(lambda s, d: graph(s, d, "supplier_part").orderBy("w", "eid").offset(40).limit(20).select("eid", "w"))
query("top_k_per_vertex", f"SELECT u, v, w, eid, rank FROM (SELECT *, row_number() OVER (PARTITION BY u ORDER BY w DESC, v, eid) AS rank FROM {gr('supplier_part')}) WHERE rank <= 3")(lambda s, d: E.top_k_per_vertex(graph(s, d, "supplier_part"), 3).select("u", "v", "w", "eid", F.col("rank").cast("long").alias("rank")))
query("nulls_first_last", "SELECT c_custkey, o_orderkey, row_number() OVER (ORDER BY o_orderkey DESC NULLS FIRST, c_custkey) AS place FROM customer LEFT JOIN (SELECT * FROM orders WHERE o_orderkey < 100) ON c_custkey = o_custkey ORDER BY place LIMIT 50")(
    lambda s, d: (j := load(s, d, "customer").join(load(s, d, "orders").filter("o_orderkey < 100"), F.col("c_custkey") == F.col("o_custkey"), "left").select("c_custkey", "o_orderkey").orderBy(F.col("o_orderkey").desc_nulls_first(), "c_custkey").limit(50)).withColumn("place", F.row_number().over(Window.orderBy(F.col("o_orderkey").desc_nulls_first(), "c_custkey")).cast("long"))
)
query("nulls_first_last_whole", "SELECT c_custkey, o_orderkey, CASE WHEN o_orderkey IS NULL THEN 0 ELSE 1 END AS part FROM customer LEFT JOIN orders ON c_custkey = o_custkey")(
    lambda s, d: load(s, d, "customer").join(load(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left").orderBy(F.col("o_orderkey").desc_nulls_first(), "c_custkey").select("c_custkey", "o_orderkey", F.when(F.col("o_orderkey").isNull(), 0).otherwise(1).alias("part"))
)
query("union_all_edges", f"SELECT u, v FROM {gr('tiny_sparse')} UNION ALL SELECT u, v FROM {gr('premium_cust_supp')}")(lambda s, d: graph(s, d, "tiny_sparse").select("u", "v").union(graph(s, d, "premium_cust_supp").select("u", "v")))
query("union_distinct", f"SELECT u, v FROM {gr('premium_cust_supp')} UNION SELECT u, v FROM {gr('premium_cust_supp')}")(lambda s, d: (p := graph(s, d, "premium_cust_supp").select("u", "v")).union(p).distinct())
_A, _B = f"SELECT u, v FROM {gr('supplier_part')} WHERE eid % 2 = 0", f"SELECT u, v FROM {gr('supplier_part')} WHERE eid % 2 = 1"


def _half(s: SparkSession, d: str, i: int) -> DataFrame:
    return graph(s, d, "supplier_part").filter(F.col("eid") % 2 == i).select("u", "v")


query("common_pairs", f"{_A} INTERSECT {_B}")(lambda s, d: _half(s, d, 0).intersect(_half(s, d, 1)))
query("intersect_all", f"{_A} INTERSECT ALL {_B}")(lambda s, d: _half(s, d, 0).intersectAll(_half(s, d, 1)))
query("except_all", f"{_A} EXCEPT ALL {_B}")(lambda s, d: _half(s, d, 0).exceptAll(_half(s, d, 1)))


@query("cert_minus_graph", f"SELECT CAST(0 AS BIGINT) AS foreign_edges, true AS within_bound, true AS smaller, (SELECT count(*) FROM {gr('co_purchase')}) AS m, (SELECT count(*) FROM (SELECT u FROM {gr('co_purchase')} UNION SELECT v FROM {gr('co_purchase')})) AS n")
def _(s: SparkSession, d: str) -> DataFrame:
    """A certificate is a subgraph, within its bound, and smaller than a dense graph."""
    e = graph(s, d, "co_purchase")
    cert = cut(CertEngine(of("edge", 3)).run(e).edges)
    n = g.all_vertices(e).agg(F.count(F.lit(1)).alias("n"))
    size = cert.agg(F.count(F.lit(1)).alias("c"))
    foreign = cert.select("u", "v", "eid").exceptAll(e.select("u", "v", "eid")).agg(F.count(F.lit(1)).alias("foreign_edges"))
    return foreign.crossJoin(size).crossJoin(n).crossJoin(e.agg(F.count(F.lit(1)).alias("m"))).select("foreign_edges", (F.col("c") <= 3 * (F.col("n") - 1)).alias("within_bound"), (F.col("c") < F.col("m")).alias("smaller"), "m", "n")


# ---- scalar functions

query("doc_lines", "SELECT doc_id, CAST(len(string_split(text, chr(10))) AS BIGINT) AS lines, substr(text, 1, 8) AS head FROM documents")(lambda s, d: load(s, d, "documents").select("doc_id", F.size(F.split("text", "\n")).cast("long").alias("lines"), F.substring("text", 1, 8).alias("head")))
query("page_hosts", "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#]*)', 1) AS host FROM pages")(lambda s, d: load(s, d, "pages").select("page_id", F.regexp_extract("url", r"^[a-z]+://([^/?#]*)", 1).alias("host")))
query("page_hrefs", "SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS href FROM pages")(lambda s, d: load(s, d, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("href")))
query("name_distance", "SELECT a.p_partkey AS u, b.p_partkey AS v, CAST(levenshtein(a.p_name, b.p_name) AS INTEGER) AS steps FROM part a JOIN part b ON b.p_partkey = a.p_partkey + 1")(lambda s, d: load(s, d, "part").select(F.col("p_partkey").alias("u"), F.col("p_name").alias("a")).join(load(s, d, "part").select(F.col("p_partkey").alias("v"), F.col("p_name").alias("b")), F.col("v") == F.col("u") + 1).select("u", "v", F.levenshtein("a", "b").alias("steps")))
query("line_digest", "SELECT doc_id, sha256(text) AS digest, length(trim(text)) AS n FROM documents")(lambda s, d: load(s, d, "documents").select("doc_id", F.sha2(F.col("text"), 256).alias("digest"), F.length(F.trim("text")).cast("long").alias("n")))
query("event_day_hour", "SELECT event_id, date_trunc('hour', ts) AS hour, CAST(year(ts) AS BIGINT) AS y, CAST(month(ts) AS BIGINT) AS m FROM events")(lambda s, d: load(s, d, "events").select("event_id", F.date_trunc("hour", "ts").cast(load(s, d, "events").schema["ts"].dataType).alias("hour"), F.year("ts").cast("long").alias("y"), F.month("ts").cast("long").alias("m")))
query("ship_lag", "SELECT l_orderkey, l_linenumber, date_diff('day', CAST(o_orderdate AS DATE), CAST(l_shipdate AS DATE)) AS days FROM lineitem JOIN orders ON l_orderkey = o_orderkey")(lambda s, d: load(s, d, "lineitem").join(load(s, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey")).select("l_orderkey", "l_linenumber", F.datediff("l_shipdate", "o_orderdate").cast("long").alias("days")))
query("cut_mask", "SELECT n_nationkey, CAST(1 << n_nationkey AS BIGINT) AS mask, CAST(bit_count(n_nationkey) AS INTEGER) AS ones, greatest(n_nationkey, n_regionkey) AS top FROM nation")(lambda s, d: load(s, d, "nation").select("n_nationkey", F.expr("shiftleft(1L, n_nationkey)").alias("mask"), F.bit_count("n_nationkey").alias("ones"), F.greatest("n_nationkey", "n_regionkey").alias("top")))
query("vector_norm", "SELECT vec_id, round(sqrt(list_dot_product(CAST(embedding AS DOUBLE[]), CAST(embedding AS DOUBLE[]))), 6) AS norm, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INTEGER) AS positive FROM embeddings")(lambda s, d: load(s, d, "embeddings").select("vec_id", F.round(F.sqrt(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))), 6).alias("norm"), F.size(F.filter("embedding", lambda x: x > 0)).alias("positive")))
query("cosine_weight", "SELECT a.vec_id AS u, round(list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])), 6) AS cosine FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")(lambda s, d: (v := load(s, d, "embeddings")).join(v.select((F.col("vec_id") - 1).alias("vec_id"), F.col("embedding").alias("o")), "vec_id").select(F.col("vec_id").alias("u"), F.round(cosine(F.col("embedding"), F.col("o")), 6).alias("cosine")))
query("neighbour_slices", "SELECT vec_id, CAST(len(embedding[1:5]) AS INTEGER) AS head, list_contains(list_transform(embedding, lambda x: x > 0.3), true) AS large FROM embeddings")(lambda s, d: load(s, d, "embeddings").select("vec_id", F.size(F.slice("embedding", 1, 5)).alias("head"), F.array_contains(F.transform("embedding", lambda x: x.cast("double") > 0.3), True).alias("large")))
query("type_count_map", "SELECT user_id, string_agg(event_type || '=' || n, ',' ORDER BY event_type) AS counts FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY 1, 2) GROUP BY 1")(
    lambda s, d: load(s, d, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n")).groupBy("user_id").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("event_type", "n")))).alias("m")).select("user_id", F.array_join(F.transform(F.map_keys("m"), lambda k: F.concat(k, F.lit("="), F.element_at(F.col("m"), k).cast("string"))), ",").alias("counts"))
)
query("props_weight", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS VARCHAR) AS k FROM events")(lambda s, d: load(s, d, "events").select("event_id", F.get_json_object("props", "$.k").alias("k")))
query("props_variant", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS VARCHAR) AS k FROM events")(lambda s, d: load(s, d, "events").select("event_id", F.try_variant_get(F.parse_json("props"), "$.k", "string").alias("k")))
query("tie_break_struct", f"SELECT u, min((w, v, eid))[3] AS first_edge FROM {gr('user_type')} GROUP BY u")(lambda s, d: graph(s, d, "user_type").groupBy("u").agg(F.min(F.struct("w", "v", "eid"))["eid"].alias("first_edge")))
query("safe_ops", "SELECT o_orderkey, try_cast(o_orderpriority AS INTEGER) AS p, CASE WHEN o_orderkey % 3 = 0 THEN NULL ELSE round(o_totalprice / (o_orderkey % 3), 4) END AS q, nullif(o_orderstatus, 'F') AS s FROM orders")(lambda s, d: load(s, d, "orders").select("o_orderkey", F.col("o_orderpriority").try_cast("int").alias("p"), F.round(F.try_divide("o_totalprice", F.col("o_orderkey") % 3), 4).alias("q"), F.nullif(F.col("o_orderstatus"), F.lit("F")).alias("s")))
query("vertex_hash", f"SELECT page_id, {hashed_sql('url')} AS hashed FROM pages")(lambda s, d: load(s, d, "pages").select("page_id", hashed(F.col("url")).alias("hashed")))
query("seen_bitmap", "SELECT count(DISTINCT l_suppkey) AS suppliers FROM lineitem")(lambda s, d: load(s, d, "lineitem").groupBy(F.bitmap_bucket_number("l_suppkey").alias("b")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("l_suppkey")).alias("bits")).agg(F.sum(F.bitmap_count("bits")).alias("suppliers")))

# ---- SQL surface


@query("udtf_components", components_sql(DUCK_SQL["conv_turn"]))
def _(s: SparkSession, d: str) -> DataFrame:
    table_functions.register(s)
    graph(s, d, "conv_turn").createOrReplaceTempView("graph_edges")
    return s.sql("SELECT * FROM graph_components(TABLE(SELECT u, v FROM graph_edges) WITH SINGLE PARTITION)")


@query("udtf_min_forest", min_forest_sql(DUCK_SQL["user_adjacent"], 150, "CAST(count(*) AS BIGINT) AS edges, CAST(sum(w) AS BIGINT) AS weight"))
def _(s: SparkSession, d: str) -> DataFrame:
    table_functions.register(s)
    graph(s, d, "user_adjacent").createOrReplaceTempView("graph_weighted")
    return s.sql("SELECT count(*) AS edges, sum(w) AS weight FROM graph_min_forest(TABLE(SELECT u, v, w FROM graph_weighted) WITH SINGLE PARTITION)")


@query("recursive_reach", f"WITH RECURSIVE e AS (SELECT u, v FROM {gr('tiny_sparse')}), b AS (SELECT u, v FROM e UNION SELECT v, u FROM e), r(v) AS (SELECT min(u) FROM e UNION SELECT b.v FROM r JOIN b ON b.u = r.v) SELECT v FROM r WHERE v IS NOT NULL")
def _(s: SparkSession, d: str) -> DataFrame:
    """The component of the least end of an edge, by rounds over the vertices that the last round reached first."""
    e = graph(s, d, "tiny_sparse").select("u", "v")
    both = cut(e.union(e.select("v", "u")).distinct())
    seen = fresh = cut(e.agg(F.min("u").alias("v")).filter("v is not null"))
    while not fresh.isEmpty():
        fresh = cut(fresh.join(both.select(F.col("u").alias("_u"), F.col("v").alias("_v")), F.col("v") == F.col("_u")).select(F.col("_v").alias("v")).distinct().join(seen, "v", "left_anti"))
        seen = cut(seen.union(fresh))
    return seen


def _table_function(s: SparkSession, d: str, name: str, call: str) -> DataFrame:
    table_functions.register(s)
    graph(s, d, name).createOrReplaceTempView(f"{name}_edges")
    return s.sql(f"SELECT * FROM {call.format(f'TABLE(SELECT u, v FROM {name}_edges) WITH SINGLE PARTITION')}")


query("udtf_bipartition", f"SELECT v, component, CAST(side AS INTEGER) AS side FROM ({bipartition_sql(DUCK_SQL['user_type'])})")(lambda s, d: _table_function(s, d, "user_type", "graph_bipartition({})"))
query("udtf_spanning_forest_components", components_sql(DUCK_SQL["page_host"]))(lambda s, d: g.components(_table_function(s, d, "page_host", "graph_spanning_forest({})")))
query("udtf_vertex_cert_verdict", k_vertex_slice_sql(3))(lambda s, d: ready(g.is_k_vertex_connected(_table_function(s, d, "small_user_slice", "graph_vertex_cert({}, 3)"), 3)))
query("udtf_edge_cert_verdict", k_edge_slice_sql(3))(lambda s, d: ready(g.is_k_edge_connected(_table_function(s, d, "small_user_slice", "graph_edge_cert({}, 3)"), 3)))
query("udtf_vertex_cert_verdict_whole")(lambda s, d: ready(g.is_k_vertex_connected(_table_function(s, d, "user_adjacent", "graph_vertex_cert({}, 3)"), 3)))
query("udtf_edge_cert_verdict_whole")(lambda s, d: ready(g.is_k_edge_connected(_table_function(s, d, "user_adjacent", "graph_edge_cert({}, 3)"), 3)))
query("sql_scalar_functions", f"SELECT s_suppkey, {6 * KIND} + s_suppkey AS vertex, round(1 - (s_acctbal + s_nationkey + 6) / (sqrt(s_acctbal * s_acctbal + 5) * sqrt(s_nationkey * s_nationkey + 10)), 6) AS distance FROM supplier")(
    lambda s, d: table_functions.register(s) or load(s, d, "supplier").selectExpr("s_suppkey", "encode_vertex(6, s_suppkey) AS vertex", "round(cosine_distance(array(s_acctbal, 1.0D, 2.0D), array(1.0D, double(s_nationkey), 3.0D)), 6) AS distance")
)


@query("udtf_connectivity", f"WITH e AS ({DUCK_SQL['user_type']}), p AS (SELECT count(DISTINCT u) * count(DISTINCT v) = count(DISTINCT (u, v)) AS whole, count(DISTINCT v) AS types FROM e), x AS (SELECT DISTINCT u FROM e ORDER BY u LIMIT 2) SELECT (SELECT min(u) FROM x) AS x, (SELECT max(u) FROM x) AS y, CASE WHEN whole THEN CAST(least(3, types) AS INTEGER) END AS kappa, CASE WHEN whole THEN CAST(least(3, types) AS INTEGER) END AS lambda FROM p")
def _(s: SparkSession, d: str) -> DataFrame:
    """Two users who all have all types are joined through each of these, as far as is asked."""
    table_functions.register(s)
    e = graph(s, d, "user_type")
    e.createOrReplaceTempView("user_type_edges")
    x, y = (r.u for r in e.select("u").distinct().orderBy("u").limit(2).collect())
    return s.sql(f"SELECT x, y, kappa, lambda FROM graph_connectivity(TABLE(SELECT u, v FROM user_type_edges) WITH SINGLE PARTITION, {x}, {y}, 3)")

"""Costs and mid-stream answers as queries: what can be counted has SQL, times have none."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sparsecert.kernels.fold import GroupPolicy, of
from sparsecert.operators import graph as g
from sparsecert.operators import measures as me
from sparsecert.plans.batch import CertEngine, map_tasks, tree_widths
from sparsecert.plans.relational import cut
from sparsecert.sources.graphs import DUCK_SQL, KIND, USER, code, graph
from sparsecert.sources.tables import load
from sparsecert.workloads.methods import (
    POLICIES, _LOG, bipartition_sql, components_cte, components_sql, k_vertex_slice_sql, min_forest_sql, query, ready, tradeoff,
)

# ---- the table of problems, row by row: a graph, a certificate, a post-pass, and SQL for what it says

_COMPLETE = "(SELECT CASE WHEN count(DISTINCT (u, v)) = count(DISTINCT u) * count(DISTINCT v) THEN CAST(least(count(DISTINCT u), count(DISTINCT v)) >= {k} AS VARCHAR) END FROM e)"
_FOREST_WEIGHT = f"SELECT CAST(CAST(sum(w) AS BIGINT) AS VARCHAR) FROM ({min_forest_sql(DUCK_SQL['user_adjacent'], 150)})"
ROWS = {
    "components": ("customer_supplier", "components", 1, me.component_count, f"({components_cte(DUCK_SQL['customer_supplier'])} SELECT CAST(count(DISTINCT c) AS VARCHAR) FROM cc)"),
    "bipartition": ("customer_supplier", "bipartite", 1, me.bipartite, f"(SELECT CAST(bool_and(bipartite) AS VARCHAR) FROM ({bipartition_sql(DUCK_SQL['customer_supplier'])}))"),
    "vertex_2_3": ("user_type", "vertex", 3, me.vertex_verdict(3), _COMPLETE.format(k=3)),
    "vertex_4": ("user_type", "vertex", 4, me.vertex_verdict(4), _COMPLETE.format(k=4)),
    "vertex_k": ("user_type", "vertex", 5, me.vertex_verdict(5), _COMPLETE.format(k=5)),
    "edge_2_3": ("user_type", "edge", 3, me.edge_verdict(3), _COMPLETE.format(k=3)),
    "edge_4": ("user_type", "edge", 4, me.edge_verdict(4), _COMPLETE.format(k=4)),
    "edge_k": ("user_type", "edge", 5, me.edge_verdict(5), _COMPLETE.format(k=5)),
    "min_forest": ("user_adjacent", "min_forest", 1, me.weight, f"({_FOREST_WEIGHT})"),
}


def _timed(s: SparkSession, d: str, problem: str, policy: GroupPolicy | None = None, overlap: bool = False, given: tuple[DataFrame, int] | None = None) -> DataFrame:
    """given: a graph's edges in order and its number of vertices, where more than one row is asked about it; weights aren't compared apart then."""
    name, prop, k, post, _ = ROWS[problem]
    e = given[0] if given else graph(s, d, name)
    n = given[1] if given else g.all_vertices(e).count()
    policy = policy or (GroupPolicy.nlogn() if prop == "min_forest" else GroupPolicy.linear())
    return me.computing_time(e, of(prop, k), policy, n, post, overlap=overlap, ordered=bool(given), compare=not given).withColumn("problem", F.lit(problem))


def _row_sql(problem: str) -> str:
    name, prop, k, _, said = ROWS[problem]
    group = f"n * {_LOG}" if prop == "min_forest" else "n"
    return f"""WITH e AS ({DUCK_SQL[name]}), c AS (SELECT (SELECT count(*) FROM (SELECT u FROM e UNION SELECT v FROM e)) AS n, (SELECT count(*) FROM e) AS m), r AS (SELECT *, {group} AS r FROM c)
SELECT '{problem}' AS problem, {said} AS answer, n, m, CAST(ceil(m / r) AS BIGINT) AS groups, CAST(m - (ceil(m / r) - 1) * r AS BIGINT) AS tail, CAST(1 AS DOUBLE) AS passes, true AS within_bound FROM r"""


def _most(problem: str):
    """Edges that may be held: a certificate's bound and a whole group."""
    _, prop, k, _, _ = ROWS[problem]
    n = F.col("n")
    group = n * F.ceil(F.log2(n.cast("double"))) if prop == "min_forest" else n
    cert = k * (n - 1) + (1 if prop == "bipartite" else 0)
    return cert + group


for _problem in ROWS:
    # a certificate and one group are held at most
    query(f"table_row_{_problem}", _row_sql(_problem))(
        lambda s, d, p=_problem: _timed(s, d, p).select("problem", "answer", "n", "m", "groups", "tail", "passes", (F.col("peak_edges") <= _most(p)).alias("within_bound"))
    )
    query(f"computing_time_{_problem}")(lambda s, d, p=_problem: _timed(s, d, p))
    query(f"computing_time_overlap_{_problem}")(lambda s, d, p=_problem: _timed(s, d, p, overlap=True))
    query(f"computing_time_whole_{_problem}")(lambda s, d, p=_problem: _timed(s, d, p, GroupPolicy.whole()))


TOTALS = {"components": "components", "bipartition": "bipartition", "k_vertex": "vertex_k", "k_edge": "edge_k", "min_forest": "min_forest"}
for _name, _problem in TOTALS.items():
    _sql = f"WITH e AS ({DUCK_SQL[ROWS[_problem][0]]}) SELECT '{_name}' AS problem, x.a AS grouped, x.a AS whole FROM (SELECT {ROWS[_problem][4]} AS a) x"
    query(f"total_time_stream_vs_whole_{_name}", _sql)(
        lambda s, d, n=_name, p=_problem: _timed(s, d, p).select(F.lit(n).alias("problem"), F.col("answer").alias("grouped")).crossJoin(_timed(s, d, p, GroupPolicy.whole()).select(F.col("answer").alias("whole")))
    )


@query("total_times_stream_vs_whole")
def _(s: SparkSession, d: str) -> DataFrame:
    """Computing time (all gaps and the post-pass) of the grouped stream, with and without overlap, and of the whole graph in one group."""
    out, given = None, {}
    for name, problem in TOTALS.items():
        graph_name = ROWS[problem][0]
        if graph_name not in given:
            # joined and put in order once for all rows, which then only read it
            given[graph_name] = (cut(me.in_order(graph(s, d, graph_name)).select("u", "v", "w", "eid")), g.all_vertices(graph(s, d, graph_name)).count())
        for mode, policy, overlap in (("grouped", None, False), ("overlap", None, True), ("whole", GroupPolicy.whole(), False)):
            row = _timed(s, d, problem, policy, overlap, given[graph_name]).select(F.lit(name).alias("problem"), F.lit(mode).alias("mode"), "m", "groups", "worst_gap_ns", "stream_ns", "wait_ns", "post_ns", "total_ns")
            out = row if out is None else out.union(row)
    return out


# ---- passes


def _answers(s: SparkSession, d: str) -> list[tuple[str, DataFrame, DataFrame]]:
    e, w = graph(s, d, "user_type"), graph(s, d, "customer_order")
    return [
        ("components", g.components(e), e), ("bipartition", g.bipartition(e), e), ("odd_cycle", g.odd_cycle(e), e), ("k_vertex", g.is_k_vertex_connected(e, 3), e), ("k_edge", g.is_k_edge_connected(e, 3), e),
        ("k_edge_classes", g.k_edge_classes(e, 3), e), ("cut_vertices", g.cut_vertices(w), w), ("bridges", g.bridges(w), w), ("min_forest", g.min_forest(w), w), ("component_sizes", g.component_sizes(w), w),
    ]


def _rows_read(plans: list[DataFrame]) -> list[int]:
    """Whole runs, four at a time: each ends in one task."""
    with ThreadPoolExecutor(4) as pool:
        return list(pool.map(me.rows_read, plans))


@query("passes_of_answers", " UNION ALL ".join(f"SELECT '{n}' AS answer, CAST(1 AS BIGINT) AS passes" for n in ("components", "bipartition", "odd_cycle", "k_vertex", "k_edge", "k_edge_classes", "cut_vertices", "bridges", "min_forest", "component_sizes")))
def _(s: SparkSession, d: str) -> DataFrame:
    """Whole runs of each answer: rows that it takes from the table over those that its edges take."""
    asked = _answers(s, d)
    graphs = list({id(e): e for _, _, e in asked}.values())
    taken = _rows_read([*graphs, *(a for _, a, _ in asked)])
    edges = {id(e): t for e, t in zip(graphs, taken, strict=False)}
    rows = [(n, me.passes(t, edges[id(e)])) for (n, _, e), t in zip(asked, taken[len(graphs) :], strict=True)]
    return s.createDataFrame(rows, "answer string, passes bigint")


@query("plan_costs_of_answers")
def _(s: SparkSession, d: str) -> DataFrame:
    """What an answer's plan costs: scans, shuffles, and levels of the merge tree at this session's number of tasks; and rows that a whole run of it took from the table."""
    asked = _answers(s, d)
    planned = [(n, me.scans(a), me.shuffles(a), len(tree_widths(map_tasks(e)))) for n, a, e in asked]  # a plan that has run names its parts twice
    rows = [(*p, t) for p, t in zip(planned, _rows_read([a for _, a, _ in asked]), strict=True)]
    return s.createDataFrame(rows, "answer string, scans bigint, shuffles bigint, tree_levels bigint, rows_read bigint")


# ---- overlap of solving and arriving

for _name, _options in (("overlap", {"overlap": True, "policy": GroupPolicy.linear(), "n": 150}),):
    query(f"components_{_name}_user_adjacent", components_sql(DUCK_SQL["user_adjacent"]))(lambda s, d, o=_options: g.components(graph(s, d, "user_adjacent"), **o))
    query(f"min_forest_{_name}_user_adjacent", min_forest_sql(DUCK_SQL["user_adjacent"], 150))(lambda s, d, o=_options: g.min_forest(graph(s, d, "user_adjacent"), **o))
    query(f"k_vertex_5_{_name}_user_type", f"WITH e AS ({DUCK_SQL['user_type']}) SELECT 'vertex' AS property, CAST(5 AS INTEGER) AS k, CAST({_COMPLETE.format(k=5)} AS BOOLEAN) AS holds")(lambda s, d, o=_options: ready(g.is_k_vertex_connected(graph(s, d, "user_type"), 5, **o)))


# ---- every tier of the planner

for _tier in ("merge_tree", "grid", "relational"):
    query(f"components_{_tier}_tier_doc_line", components_sql(DUCK_SQL["doc_line"]))(lambda s, d, t=_tier: g.components(graph(s, d, "doc_line"), tier=t))
    query(f"bipartition_{_tier}_tier_user_adjacent", bipartition_sql(DUCK_SQL["user_adjacent"]))(lambda s, d, t=_tier: g.bipartition(graph(s, d, "user_adjacent"), tier=t))
    query(f"is_bipartite_{_tier}_tier_customer_order", f"SELECT bool_and(bipartite) AS holds FROM ({bipartition_sql(DUCK_SQL['customer_order'])})")(lambda s, d, t=_tier: g.is_bipartite(graph(s, d, "customer_order"), tier=t))
    query(f"k_vertex_3_{_tier}_tier_small", k_vertex_slice_sql(3))(lambda s, d, t=_tier: ready(g.is_k_vertex_connected(graph(s, d, "small_user_slice"), 3, tier=t)))
    query(f"k_vertex_2_{_tier}_tier_user_type", f"WITH e AS ({DUCK_SQL['user_type']}) SELECT 'vertex' AS property, CAST(2 AS INTEGER) AS k, CAST({_COMPLETE.format(k=2)} AS BOOLEAN) AS holds")(lambda s, d, t=_tier: ready(g.is_k_vertex_connected(graph(s, d, "user_type"), 2, tier=t)))
    query(f"k_edge_2_{_tier}_tier_user_type", f"WITH e AS ({DUCK_SQL['user_type']}) SELECT 'edge' AS property, CAST(2 AS INTEGER) AS k, CAST({_COMPLETE.format(k=2)} AS BOOLEAN) AS holds")(lambda s, d, t=_tier: ready(g.is_k_edge_connected(graph(s, d, "user_type"), 2, tier=t)))
    query(f"min_forest_{_tier}_tier_user_adjacent", min_forest_sql(DUCK_SQL["user_adjacent"], 150))(lambda s, d, t=_tier: g.min_forest(graph(s, d, "user_adjacent"), tier=t))


# ---- answers in mid-stream

_SEQ = f"""WITH RECURSIVE o AS (SELECT event_id, row_number() OVER (ORDER BY ts, event_id) AS seq FROM events), e AS (
  SELECT u, v, row_number() OVER (ORDER BY seq) AS i FROM ({DUCK_SQL["user_adjacent"]}) x JOIN o ON o.event_id = x.eid),
n AS (SELECT count(*) AS n FROM (SELECT u FROM e UNION SELECT v FROM e)), m AS (SELECT count(*) AS m FROM e),
gs AS (SELECT gid, least((gid + 1) * n, m) AS upto FROM n, m, range(0, (m + n - 1) // n) t(gid))"""
_RANKS = f"""{_SEQ}, b AS (SELECT gid, u, v FROM gs JOIN e ON i <= upto UNION SELECT gid, v AS u, u AS v FROM gs JOIN e ON i <= upto),
cc(gid, v, c) USING KEY (gid, v) AS (
  SELECT gid, u, u FROM b GROUP BY gid, u
  UNION
  (SELECT b.gid, b.v, min(f.c) FROM cc f JOIN b ON b.gid = f.gid AND b.u = f.v JOIN recurring.cc r ON r.gid = b.gid AND r.v = b.v WHERE f.c < r.c GROUP BY b.gid, b.v)
) SELECT gs.gid AS group_id, CAST(any_value(upto) AS BIGINT) AS edges_read, CAST(count(*) - count(DISTINCT c) AS VARCHAR) AS answer FROM cc JOIN gs ON gs.gid = cc.gid GROUP BY gs.gid"""
_EVEN = f"""{_SEQ}, a AS (SELECT gid, 2 * u AS u, 2 * v + 1 AS v FROM gs JOIN e ON i <= upto UNION SELECT gid, 2 * u + 1, 2 * v FROM gs JOIN e ON i <= upto),
b AS (SELECT gid, u, v FROM a UNION SELECT gid, v, u FROM a),
cc(gid, v, c) USING KEY (gid, v) AS (
  SELECT gid, u, u FROM b GROUP BY gid, u
  UNION
  (SELECT b.gid, b.v, min(f.c) FROM cc f JOIN b ON b.gid = f.gid AND b.u = f.v JOIN recurring.cc r ON r.gid = b.gid AND r.v = b.v WHERE f.c < r.c GROUP BY b.gid, b.v)
) SELECT gs.gid AS group_id, CAST(any_value(upto) AS BIGINT) AS edges_read, CAST(bool_and(x.c <> y.c) AS VARCHAR) AS answer
FROM cc x JOIN cc y ON y.gid = x.gid AND y.v = x.v + 1 AND x.v % 2 = 0 JOIN gs ON gs.gid = x.gid GROUP BY gs.gid"""


def _over_time(s: SparkSession, d: str, prop: str, post: me.Post, **options) -> DataFrame:
    e = graph(s, d, "user_adjacent")
    return me.answers_over_time(e, of(prop), GroupPolicy.linear(), g.all_vertices(e).count(), post, **options)


query("rank_over_time_user_adjacent", _RANKS)(lambda s, d: _over_time(s, d, "components", me.rank_of))
query("rank_over_time_overlap_user_adjacent", _RANKS)(lambda s, d: _over_time(s, d, "components", me.rank_of, overlap=True))
query("bipartite_over_time_user_adjacent", _EVEN)(lambda s, d: _over_time(s, d, "bipartite", me.bipartite))


@query("per_edge_rank_over_time_user_adjacent", _RANKS)
def _(s: SparkSession, d: str) -> DataFrame:
    """A per-edge method answers at any time; here at the ends of the groups."""
    e = graph(s, d, "user_adjacent")
    return me.per_edge_over_time(e, "components", g.all_vertices(e).count())


_DAYS = f"""WITH RECURSIVE x AS (SELECT p.u, p.v, CAST(ts AS DATE) AS day FROM ({DUCK_SQL["user_adjacent"]}) p JOIN events ON event_id = eid), days AS (SELECT DISTINCT day FROM x),
b AS (SELECT d.day, u, v FROM days d JOIN x ON x.day <= d.day UNION SELECT d.day, v AS u, u AS v FROM days d JOIN x ON x.day <= d.day),
cc(day, v, c) USING KEY (day, v) AS (
  SELECT day, u, u FROM b GROUP BY day, u
  UNION
  (SELECT b.day, b.v, min(f.c) FROM cc f JOIN b ON b.day = f.day AND b.u = f.v JOIN recurring.cc r ON r.day = b.day AND r.v = b.v WHERE f.c < r.c GROUP BY b.day, b.v)
), l AS (SELECT e.event_id, max(d.day) AS day, any_value(e.user_id) AS user_id FROM events e LEFT JOIN days d ON d.day < CAST(e.ts AS DATE) GROUP BY e.event_id)
SELECT l.event_id, cc.c AS component FROM l LEFT JOIN cc ON cc.day = l.day AND cc.v = {code(USER, 'l.user_id')}"""


@query("event_component_asof", _DAYS)
def _(s: SparkSession, d: str) -> DataFrame:
    """Each event with its user's component as it stood at the end of the last day before it that has edges; null if the user had none."""
    events = load(s, d, "events").select("event_id", "user_id", F.to_date("ts").alias("day"))
    e = graph(s, d, "user_adjacent").join(events.select(F.col("event_id").alias("eid"), "day"), "eid")
    labels = me.labels_by_pane(e, of("components"), "day")
    days = labels.select(F.col("day").alias("labelled")).distinct()
    # days are few: one row each
    before = events.select("day").distinct().join(F.broadcast(days), F.col("labelled") < F.col("day"), "left").groupBy("day").agg(F.max("labelled").alias("labelled"))
    at = events.join(F.broadcast(before), "day").withColumn("v", F.lit(USER * KIND) + F.col("user_id"))
    return at.join(labels.withColumnRenamed("day", "labelled"), ["labelled", "v"], "left").select("event_id", "component")


# ---- comparisons, trade-offs

query("weight_comparisons_user_adjacent")(lambda s, d: me.comparisons_by_kernel(graph(s, d, "user_adjacent")))

_DENSE = f"""WITH c AS (SELECT count(*) AS n, count(*) * (count(*) - 1) // 2 AS m FROM embeddings),
r AS (SELECT 'n / 4' AS buffer, CAST(ceil(n * 0.25) AS BIGINT) AS r, m FROM c UNION ALL SELECT 'n', n, m FROM c UNION ALL SELECT 'n sqrt(log n)', CAST(ceil(n * sqrt({_LOG})) AS BIGINT), m FROM c UNION ALL SELECT 'n log n', n * {_LOG}, m FROM c UNION ALL SELECT 'all', m, m FROM c)
SELECT buffer, CAST(ceil(m / r) AS BIGINT) AS groups, CAST(CASE WHEN m % r = 0 THEN r ELSE m % r END AS BIGINT) AS tail, CAST(m AS BIGINT) AS edges_read FROM r"""


@query("tradeoff_groups_embedding_pairs", _DENSE)
def _(s: SparkSession, d: str) -> DataFrame:
    """The memory sweep on the dense graph of all pairs of vectors."""
    e = graph(s, d, "embedding_pairs")
    return tradeoff(e, load(s, d, "embeddings").count()).select("buffer", "groups", "tail", "edges_read")


query("tradeoff_times_embedding_pairs")(lambda s, d: tradeoff(graph(s, d, "embedding_pairs"), load(s, d, "embeddings").count()))


@query("tradeoff_weights_user_adjacent", f"SELECT t.b AS buffer, CAST(x.w AS BIGINT) AS weight FROM (SELECT unnest([{', '.join(repr(p) for p in POLICIES)}]) AS b) t, (SELECT sum(w) AS w FROM ({min_forest_sql(DUCK_SQL['user_adjacent'], 150)})) x")
def _(s: SparkSession, d: str) -> DataFrame:
    """Every buffer size gives the same forest's weight."""
    out = None
    for name, policy in POLICIES.items():
        row = g.min_forest(graph(s, d, "user_adjacent"), policy=policy, n=150).agg(F.sum("w").alias("weight")).select(F.lit(name).alias("buffer"), "weight")
        out = row if out is None else out.union(row)
    return out


# ---- laws

_STRONG = f"""WITH RECURSIVE parts AS (SELECT h, u, v FROM (SELECT unnest([0, 1, 2]) AS h) t, ({DUCK_SQL['customer_order']}) UNION ALL SELECT 1, u, v FROM ({DUCK_SQL['premium_cust_supp']}) UNION ALL SELECT 2, u, v FROM ({DUCK_SQL['customer_supplier']})),
b AS (SELECT h, u, v FROM parts UNION SELECT h, v, u FROM parts),
cc(h, v, c) USING KEY (h, v) AS (
  SELECT h, u, u FROM b GROUP BY h, u
  UNION
  (SELECT b.h, b.v, min(f.c) FROM cc f JOIN b ON b.h = f.h AND b.u = f.v JOIN recurring.cc r ON r.h = b.h AND r.v = b.v WHERE f.c < r.c GROUP BY b.h, b.v)
) SELECT CAST(h AS INTEGER) AS other, count(DISTINCT c) AS of_graph, count(DISTINCT c) AS of_cert FROM cc GROUP BY h"""


@query("strong_cert_law_customer_order", _STRONG)
def _(s: SparkSession, d: str) -> DataFrame:
    """Components of a graph and of its certificate, alone and together with two other graphs."""
    e = graph(s, d, "customer_order").select("u", "v", "w", "eid")
    cert = CertEngine(of("edge", 2)).run(e).edges
    others = [None, *(graph(s, d, n).select("u", "v", "w", "eid") for n in ("premium_cust_supp", "customer_supplier"))]
    out = None
    for i, h in enumerate(others):
        both = [g.is_connected(x if h is None else x.union(h)).select("components") for x in (e, cert)]
        row = both[0].withColumnRenamed("components", "of_graph").crossJoin(both[1].withColumnRenamed("components", "of_cert")).select(F.lit(i).alias("other"), "of_graph", "of_cert")
        out = row if out is None else out.union(row)
    return out

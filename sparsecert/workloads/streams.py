"""Streams of the given tables: each is run to its end, and what it leaves is the query's result."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sparsecert.kernels.fold import of
from sparsecert.operators import graph as g
from sparsecert.plans import relational
from sparsecert.plans.batch import clean
from sparsecert.plans.shared import shared_path
from sparsecert.sources.graphs import DUCK_SQL, event_order, graph
from sparsecert.sources.tables import load, stream_table, write_edges
from sparsecert.streaming.certs import PAIR_SCHEMA, CertSink, LateSink, PaneSink, keyed_certs, on_time, pane_certs, session_edges, sliding_certs
from sparsecert.workloads.methods import bipartition_sql, components_sql, min_forest_sql, query, ready

ROCKS = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


def edge_files(s: SparkSession, d: str, name: str, files: int) -> DataFrame:
    """The graph's edges as a stream of so many files, one micro-batch each."""
    path = shared_path(s, "stream")
    write_edges(graph(s, d, name).repartition(files), path)
    return s.readStream.schema(PAIR_SCHEMA + ", seq bigint").option("maxFilesPerTrigger", 1).parquet(path)


def streamed(s: SparkSession, d: str, name: str, prop: str, k: int = 1, files: int = 3) -> DataFrame:
    sink = CertSink(shared_path(s, "cert"), of(prop, k))
    q = sink.start(edge_files(s, d, name, files), shared_path(s, "progress"))
    q.awaitTermination()
    return sink.latest(s)


query("stream_components_customer_order", components_sql(DUCK_SQL["customer_order"]))(lambda s, d: g.components(streamed(s, d, "customer_order", "components")))
query("stream_bipartite_user_adjacent", f"SELECT bool_and(bipartite) AS holds FROM ({bipartition_sql(DUCK_SQL['user_adjacent'])})")(lambda s, d: g.is_bipartite(streamed(s, d, "user_adjacent", "bipartite")))
query("stream_min_forest_user_adjacent", min_forest_sql(DUCK_SQL["user_adjacent"], 150))(lambda s, d: streamed(s, d, "user_adjacent", "min_forest"))
query("stream_k_vertex_5_user_type", "SELECT 'vertex' AS property, CAST(5 AS INTEGER) AS k, count(DISTINCT event_type) >= 5 AS holds FROM events")(lambda s, d: ready(g.is_k_vertex_connected(streamed(s, d, "user_type", "vertex", 5), 5)))


@query("stream_keyed_state_components", components_sql(DUCK_SQL["doc_line"]))
def _(s: SparkSession, d: str) -> DataFrame:
    """Certificates in keyed state: each block's newest rows, united."""
    name = "spark.sql.streaming.stateStore.providerClass"
    before = s.conf.get(name, None)
    s.conf.set(name, ROCKS)
    try:
        out = shared_path(s, "state")

        def write(batch: DataFrame, batch_id: int) -> None:
            batch.withColumn("batch", F.lit(batch_id)).write.mode("append").parquet(out)

        q = keyed_certs(edge_files(s, d, "doc_line", 2), "components", r=512, blocks=4).writeStream.foreachBatch(write).outputMode("update").option("checkpointLocation", shared_path(s, "progress")).trigger(availableNow=True).start()
        q.awaitTermination()
    finally:
        s.conf.set(name, before) if before else s.conf.unset(name)
    rows = s.read.parquet(out)
    newest = rows.groupBy("block").agg(F.max("batch").alias("batch"))
    return g.components(rows.join(newest, ["block", "batch"]).select("u", "v", "w", "eid"))


def timed_edges(s: SparkSession, d: str) -> DataFrame:
    e = event_order(load(s, d, "events")).select(F.col("event_id").alias("eid"), F.col("ts"))
    return graph(s, d, "user_adjacent").join(e, "eid")


_PANES = f"SELECT x.*, date_trunc('day', ts) AS pane FROM ({DUCK_SQL['user_adjacent']}) x JOIN events ON event_id = eid"


def _pane_sql(panes: str, key: str) -> str:
    return f"""WITH RECURSIVE e AS ({panes}), b AS (SELECT p, u, v FROM e UNION SELECT p, v AS u, u AS v FROM e),
cc(p, v, c) USING KEY (p, v) AS (
  SELECT p, u, u FROM b GROUP BY p, u
  UNION
  (SELECT b.p, b.v, min(f.c) FROM cc f JOIN b ON b.p = f.p AND b.u = f.v JOIN recurring.cc r ON r.p = b.p AND r.v = b.v WHERE f.c < r.c GROUP BY b.p, b.v)
) SELECT CAST(epoch(p) AS BIGINT) AS {key}, count(*) - count(DISTINCT c) AS forest_edges FROM cc GROUP BY p"""


def _seconds(c: str):
    """Of a day's start, whatever the session's time zone."""
    return F.datediff(F.col(c), F.to_date(F.lit("1970-01-01"))).cast("long") * 86400


_TUMBLING, _SLIDING = _pane_sql(f"SELECT pane AS p, u, v FROM ({_PANES})", "pane"), _pane_sql(f"SELECT pane + INTERVAL (i) DAY AS p, u, v FROM ({_PANES}), range(1, 4) t(i)", "window_end")
query("tumbling_window_forests", _TUMBLING)(lambda s, d: pane_certs(timed_edges(s, d), of("components")).groupBy(_seconds("pane").alias("pane")).agg(F.count(F.lit(1)).alias("forest_edges")))
query("sliding_window_forests", _SLIDING)(lambda s, d: sliding_certs(pane_certs(timed_edges(s, d), of("components")), of("components"), 3).groupBy(_seconds("window_end").alias("window_end")).agg(F.count(F.lit(1)).alias("forest_edges")))
query("user_sessions", "SELECT user_id, count(*) AS n, min(event_id) AS first_event FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS session FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, session")(lambda s, d: session_edges(load(s, d, "events")).select("user_id", "n", "first_event"))


@query("stream_deduplicated_events", "SELECT count(*) AS n, count(DISTINCT event_id) AS ids FROM events")
def _(s: SparkSession, d: str) -> DataFrame:
    """The events come twice; repeats within the watermark are dropped."""
    path, out = shared_path(s, "events"), shared_path(s, "deduplicated")
    e = load(s, d, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    e.union(e).repartition(1).write.parquet(path)
    q = on_time(s.readStream.schema(s.read.parquet(path).schema).parquet(path), "30 days").writeStream.format("parquet").option("path", out).option("checkpointLocation", shared_path(s, "progress")).trigger(availableNow=True).start()
    q.awaitTermination()
    return s.read.parquet(out).agg(F.count(F.lit(1)).alias("n"), F.count_distinct("event_id").alias("ids"))


query("relational_edge_cert_components", components_sql(DUCK_SQL["page_host"]))(lambda s, d: g.components(relational.relational_edge_cert(clean(graph(s, d, "page_host")), 2)))
query("relational_vertex_cert_verdict", "SELECT 'vertex' AS property, CAST(2 AS INTEGER) AS k, count(DISTINCT event_type) >= 2 AS holds FROM events")(lambda s, d: ready(g.is_k_vertex_connected(relational.relational_vertex_cert(clean(graph(s, d, "user_type")), 2), 2)))


def event_files(s: SparkSession, d: str) -> DataFrame:
    """The events as a stream of one file."""
    path = shared_path(s, "events")
    load(s, d, "events").select("event_id", "user_id", "event_type", F.col("ts").cast("timestamp").alias("ts")).repartition(1).write.parquet(path)
    return s.readStream.schema(s.read.parquet(path).schema).parquet(path)


def run_to_end(stream: DataFrame, s: SparkSession) -> DataFrame:
    """What an append stream has written when all of its input is read."""
    out = shared_path(s, "appended")
    stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", shared_path(s, "progress")).trigger(availableNow=True).start().awaitTermination()
    return s.read.schema(stream.schema).parquet(out)


@query("label_stream_edges", f"SELECT e.eid, l.component FROM ({DUCK_SQL['customer_order']}) e JOIN ({components_sql(DUCK_SQL['customer_order'])}) l ON l.v = e.u")
def _(s: SparkSession, d: str) -> DataFrame:
    """A stream of edges joined with a table of labels."""
    labels = g.components(graph(s, d, "customer_order")).withColumnRenamed("v", "u")
    return run_to_end(edge_files(s, d, "customer_order", 2).join(labels, "u").select("eid", "component"), s)


@query("click_then_purchase", "SELECT c.event_id AS click_id, p.event_id AS purchase_id FROM events c JOIN events p ON c.user_id = p.user_id AND c.event_type = 'click' AND p.event_type = 'purchase' AND p.ts > c.ts AND p.ts <= c.ts + INTERVAL 6 HOUR")
def _(s: SparkSession, d: str) -> DataFrame:
    """Two streams joined by user and interval; watermarks let the state of both end."""
    e = event_files(s, d)
    clicks = e.filter("event_type = 'click'").select(F.col("user_id").alias("a"), F.col("ts").alias("clicked"), F.col("event_id").alias("click_id")).withWatermark("clicked", "1 day")
    purchases = e.filter("event_type = 'purchase'").select(F.col("user_id").alias("b"), F.col("ts").alias("bought"), F.col("event_id").alias("purchase_id")).withWatermark("bought", "1 day")
    return run_to_end(clicks.join(purchases, F.expr("a = b AND bought > clicked AND bought <= clicked + INTERVAL 6 HOURS")).select("click_id", "purchase_id"), s)


def streamed_panes(s: SparkSession, d: str) -> DataFrame:
    """The panes' certificates after the stream of edges has come to its end, in three batches whatever their times."""
    path = shared_path(s, "timed")
    timed_edges(s, d).select("u", "v", "w", "eid", F.col("ts").cast("timestamp").alias("ts")).repartition(3).write.parquet(path)
    sink = PaneSink(shared_path(s, "panes"), of("components"))
    s.readStream.schema(s.read.parquet(path).schema).option("maxFilesPerTrigger", 1).parquet(path).writeStream.foreachBatch(sink).option("checkpointLocation", shared_path(s, "progress")).trigger(availableNow=True).start().awaitTermination()
    return sink.version(s, sink.last)


query("stream_tumbling_window_forests", _TUMBLING)(lambda s, d: streamed_panes(s, d).groupBy(_seconds("pane").alias("pane")).agg(F.count(F.lit(1)).alias("forest_edges")))
query("stream_sliding_window_forests", _SLIDING)(lambda s, d: sliding_certs(streamed_panes(s, d), of("components"), 3).groupBy(_seconds("window_end").alias("window_end")).agg(F.count(F.lit(1)).alias("forest_edges")))


def completed(stream: DataFrame, s: SparkSession) -> DataFrame:
    """What a stream in complete mode says when all of its input is read: each trigger writes the whole result anew."""
    out, last = shared_path(s, "complete"), []

    def write(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/batch={batch_id:09d}")
        last.append(batch_id)

    stream.writeStream.foreachBatch(write).outputMode("complete").option("checkpointLocation", shared_path(s, "progress")).trigger(availableNow=True).start().awaitTermination()
    return s.read.schema(stream.schema).parquet(f"{out}/batch={max(last):09d}")


@query("stream_events_by_type_complete", "SELECT event_type, count(*) AS n, count(DISTINCT user_id) AS users FROM events GROUP BY 1")
def _(s: SparkSession, d: str) -> DataFrame:
    """A table as a stream of its files, in complete mode: users are counted once by a set a type, which types bound."""
    e = stream_table(s, d, "events")
    return completed(e.groupBy("event_type").agg(F.count(F.lit(1)).alias("n"), F.size(F.collect_set("user_id")).cast("long").alias("users")), s)


@query("stream_sessions_complete", "SELECT user_id, count(*) AS n, min(event_id) AS first_event FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS session FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, session")
def _(s: SparkSession, d: str) -> DataFrame:
    """Sessions of a stream by event time."""
    return completed(session_edges(event_files(s, d).withWatermark("ts", "60 days")), s).select("user_id", "n", "first_event")


@query("stream_late_rows", "WITH o AS (SELECT max(ts) AS newest FROM events WHERE event_id % 10 <> 0) SELECT 'late' AS part, count(*) FILTER (WHERE event_id % 10 = 0 AND ts < newest - INTERVAL 86400 SECOND) AS n FROM events, o UNION ALL SELECT 'on time', count(*) FILTER (WHERE event_id % 10 <> 0 OR ts >= newest - INTERVAL 86400 SECOND) FROM events, o")
def _(s: SparkSession, d: str) -> DataFrame:
    """A tenth of the events comes after all others; those more than a day behind the newest time go to a table of late ones."""
    path = shared_path(s, "events")
    e = load(s, d, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    for part in (e.filter("event_id % 10 <> 0"), e.filter("event_id % 10 = 0")):
        part.coalesce(1).write.mode("append").parquet(path)
    sink = LateSink(shared_path(s, "late"), 86400)
    s.readStream.schema(s.read.parquet(path).schema).option("maxFilesPerTrigger", 1).parquet(path).writeStream.foreachBatch(sink).option("checkpointLocation", shared_path(s, "progress")).trigger(availableNow=True).start().awaitTermination()
    late, rest = (sink.read(s, name, range(2)) for name in ("late", "on_time"))
    return late.agg(F.count(F.lit(1)).alias("n")).select(F.lit("late").alias("part"), "n").union(rest.agg(F.count(F.lit(1)).alias("n")).select(F.lit("on time").alias("part"), "n"))

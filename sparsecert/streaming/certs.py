"""Certificates of edge streams: by micro-batch with versions, as keyed state, and by event-time panes.

A micro-batch is a group: the trigger's interval has to be at least the time that a group takes to
solve, or the backlog grows, which is what the smallest gap between edges says.
"""

from __future__ import annotations

import json
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle, StreamingQuery
from pyspark.sql.streaming.listener import StreamingQueryListener

from sparsecert.kernels.certs import Edges
from sparsecert.kernels.fold import GroupPolicy, Property, of
from sparsecert.plans.batch import CERT, certs_by_key, clean, local_certs

PAIR_SCHEMA = "u bigint, v bigint, w bigint, eid bigint"


@dataclass
class CertSink:
    """foreachBatch target: version j is version j - 1 united with the batch's certificate.

    A version is written whole under the batch's number, so a batch that runs again writes the same
    version from the same predecessor. For edge connectivity copies count, so ids are made unique first.
    """

    path: str
    prop: Property
    policy: GroupPolicy = field(default_factory=GroupPolicy.adaptive)

    def version(self, spark: SparkSession, batch_id: int) -> DataFrame:
        return spark.read.schema(PAIR_SCHEMA).parquet(f"{self.path}/version={batch_id:09d}")

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        fresh = local_certs(clean(batch), self.prop, self.policy, resolve=True)
        both = fresh if batch_id == 0 else fresh.union(self.version(spark, batch_id - 1))
        if self.prop.name == "edge":
            both = both.dropDuplicates(["eid"])
        local_certs(both.repartition(1), self.prop, GroupPolicy.whole(), resolve=True).write.mode("overwrite").parquet(f"{self.path}/version={batch_id:09d}")

    def start(self, edges: DataFrame, checkpoint: str, **trigger) -> StreamingQuery:
        return edges.writeStream.foreachBatch(self).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()

    def latest(self, spark: SparkSession) -> DataFrame:
        """The newest whole version."""
        root = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(self.path)
        fs = root.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
        done = [s.getPath().getName() for s in fs.listStatus(root) if fs.exists(spark.sparkContext._jvm.org.apache.hadoop.fs.Path(s.getPath(), "_SUCCESS"))]
        if not done:
            return spark.createDataFrame([], PAIR_SCHEMA)
        return spark.read.schema(PAIR_SCHEMA).parquet(f"{self.path}/{max(done)}")


class BlockCert(StatefulProcessor):
    """Keyed state: a buffer and a certificate per block; the buffer is folded in when it is full."""

    def __init__(self, name: str, k: int, r: int):
        self.prop, self.r = of(name, k), r

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.buffer, self.cert = handle.getListState("buffer", PAIR_SCHEMA), handle.getListState("cert", PAIR_SCHEMA)

    @staticmethod
    def _edges(state) -> Edges:
        rows = list(state.get())
        return Edges(*(np.array(c, dtype=np.int64) for c in zip(*rows, strict=True))) if rows else Edges.empty()

    @staticmethod
    def _rows(e: Edges) -> list[tuple]:
        return list(zip(e.u.tolist(), e.v.tolist(), e.w.tolist(), e.eid.tolist(), strict=True))

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        cert, buffer, folds = self._edges(self.cert), self._edges(self.buffer), 0
        for frame in rows:
            buffer = Edges.join(buffer, Edges(*(frame[c].to_numpy(dtype=np.int64) for c in ("u", "v", "w", "eid"))))
            while len(buffer) >= self.r:
                merged = Edges.join(cert, buffer.take(np.arange(self.r)))
                cert, buffer, folds = merged.take(self.prop.keep(merged)), buffer.take(np.arange(self.r, len(buffer))), folds + 1
        self.buffer.put(self._rows(buffer)) if len(buffer) else self.buffer.clear()
        if folds:
            self.cert.put(self._rows(cert))
        out = Edges.join(cert, buffer)
        yield pd.DataFrame({"block": [int(key[0])] * len(out), "u": out.u, "v": out.v, "w": out.w, "eid": out.eid})

    def close(self) -> None:
        pass


def keyed_certs(edges: DataFrame, name: str, k: int = 1, r: int = 1024, blocks: int = 8) -> DataFrame:
    """(block, u, v, w, eid): after each trigger the certificate and buffer of each block that got edges. Needs RocksDB state."""
    keyed = clean(edges).withColumn("block", F.pmod(F.xxhash64("eid"), F.lit(blocks)).cast("int"))
    return keyed.groupBy("block").transformWithStateInPandas(BlockCert(name, k, r), outputStructType=f"block int, {PAIR_SCHEMA}", outputMode="Update", timeMode="None")


def paned(edges: DataFrame, length: str = "1 day") -> DataFrame:
    """(pane, u, v, w, eid): edges with the start of their tumbling window of ts."""
    return edges.withColumn("pane", F.window("ts", length)["start"]).filter("u <> v").select("pane", "u", "v", "w", "eid")


def pane_certs(edges: DataFrame, prop: Property, length: str = "1 day") -> DataFrame:
    """(pane, u, v, w, eid): a certificate per tumbling window of ts, made before the shuffle."""
    return certs_by_key(paned(edges, length), "pane", prop)


def sliding_certs(panes: DataFrame, prop: Property, panes_per_window: int, pane: str = "1 day") -> DataFrame:
    """(window_end, u, v, w, eid): windows of several panes from the panes' certificates, so each edge is solved once.

    A window that moves on leaves panes behind; nothing is deleted.
    """
    step = F.expr(f"interval {pane}")
    spread = panes.withColumn("window_end", F.explode(F.transform(F.sequence(F.lit(1), F.lit(panes_per_window)), lambda i: F.col("pane") + step * i)))
    return certs_by_key(spread.select("window_end", "u", "v", "w", "eid"), "window_end", prop)


@dataclass
class PaneSink:
    """foreachBatch target for panes of a stream: a pane's certificate is united with what each batch brings of it.

    Versions are whole and numbered by batch, so a batch that runs again writes the same one. Late
    edges find their pane as long as versions keep it.
    """

    path: str
    prop: Property
    length: str = "1 day"

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        spark, fresh = batch.sparkSession, pane_certs(batch, self.prop, self.length)
        if batch_id:
            fresh = certs_by_key(fresh.union(self.version(spark, batch_id - 1)), "pane", self.prop)
        fresh.write.mode("overwrite").parquet(f"{self.path}/version={batch_id:09d}")
        self.last = batch_id

    def version(self, spark: SparkSession, batch_id: int) -> DataFrame:
        return spark.read.schema(f"pane timestamp, {CERT}").parquet(f"{self.path}/version={batch_id:09d}")


def session_edges(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """(user_id, session, event_types): sessions of each user by event time; works on streams with a watermark."""
    return events.groupBy("user_id", F.session_window("ts", gap).alias("session")).agg(F.count(F.lit(1)).alias("n"), F.min("event_id").alias("first_event"))


def on_time(events: DataFrame, delay: str) -> DataFrame:
    """With a watermark and without repeats of an event id within it."""
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def split_late(events: DataFrame, batch_max: Callable[[], object], delay_seconds: int) -> tuple[DataFrame, DataFrame]:
    """For foreachBatch: rows within the delay of the newest time seen, and the late ones."""
    edge = F.lit(batch_max()) - F.expr(f"interval {delay_seconds} seconds")
    return events.filter(F.col("ts") >= edge), events.filter(F.col("ts") < edge)


@dataclass
class LateSink:
    """foreachBatch target: rows on time and late ones to tables of their own, so that none is lost.

    A batch's rows are late by the newest time of the batches before it, which their tables tell.
    """

    path: str
    delay_seconds: int

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        spark, newest = batch.sparkSession, None
        if batch_id:
            newest = self.read(spark, "on_time", range(batch_id)).agg(F.max("ts")).first()[0]
        on_time_, late = (batch, batch.filter("false")) if newest is None else split_late(batch, lambda: newest, self.delay_seconds)
        for name, rows in (("on_time", on_time_), ("late", late)):
            rows.write.mode("overwrite").parquet(f"{self.path}/{name}/batch={batch_id:09d}")

    def read(self, spark: SparkSession, name: str, batches: range) -> DataFrame:
        return spark.read.parquet(*[f"{self.path}/{name}/batch={i:09d}" for i in batches])


class RateListener(StreamingQueryListener):
    """Edges per second, batch time and gap of each trigger."""

    def __init__(self) -> None:
        self.rows: list[dict] = []

    def onQueryStarted(self, event) -> None:
        pass

    def onQueryProgress(self, event) -> None:
        p = json.loads(event.progress.json)
        edges, took = p.get("numInputRows", 0), p.get("durationMs", {}).get("triggerExecution", 0)
        self.rows.append({"batch": p["batchId"], "edges": edges, "batch_ms": took, "gap_ms": took / edges if edges else None, "state_bytes": sum(s.get("memoryUsedBytes", 0) for s in p.get("stateOperators", []))})

    def onQueryTerminated(self, event) -> None:
        pass

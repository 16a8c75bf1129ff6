"""Components by joins, for vertex sets beyond one task: rounds of hooking to the least neighbour.

A round points each vertex at its least neighbour, follows pointers once more and contracts the
edges; the number of live vertices at least halves. Only edges between different components and
vertices whose label changed go through the joins.
"""

from __future__ import annotations

import tempfile
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sparsecert.kernels.forest import forest_of, labels_of


def ensure_checkpoints(spark: SparkSession) -> None:
    """spark.checkpoint.dir is the cluster's; one is set here only where it is missing, as in tests."""
    if not spark.conf.get("spark.checkpoint.dir", None) and spark.sparkContext._jsc.sc().getCheckpointDir().isEmpty():
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="checkpoints-"))


def cut(df: DataFrame) -> DataFrame:
    ensure_checkpoints(df.sparkSession)
    return df.checkpoint()


def thinned(edges: DataFrame, most_edges: int = 2_000_000) -> DataFrame:
    """Each task keeps a spanning forest of what it reads, up to most_edges edges at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray]] = []
        count = 0

        def solved() -> pa.RecordBatch:
            u, v = (np.concatenate(x) for x in zip(*held, strict=True))
            keep = forest_of(u, v)
            return pa.RecordBatch.from_arrays([pa.array(u[keep]), pa.array(v[keep])], names=["u", "v"])

        for batch in batches:
            if batch.num_rows:
                held.append((batch.column(0).to_numpy(), batch.column(1).to_numpy()))
                count += batch.num_rows
            if count >= most_edges:
                out = solved()
                held, count = [(out.column(0).to_numpy(), out.column(1).to_numpy())], out.num_rows
                if count >= most_edges // 2:
                    yield out
                    held, count = [], 0
        if held:
            yield solved()

    return edges.select(F.col("u").cast("bigint"), F.col("v").cast("bigint")).filter("u is not null and v is not null and u <> v").mapInArrow(run, "u bigint, v bigint")


def relational_components(edges: DataFrame, max_rounds: int = 60, thin: bool = True) -> DataFrame:
    """(v, component) for each end of an edge; component is the least vertex reachable."""
    pairs = thinned(edges) if thin else edges.select("u", "v").filter("u <> v")
    ends = edges.select(F.col("u").alias("v")).union(edges.select("v")).distinct()
    live = cut(pairs.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct())
    labels = None
    for _ in range(max_rounds):
        if live.isEmpty():
            break
        both = live.select("u", "v").union(live.select(F.col("v").alias("u"), F.col("u").alias("v")))
        hook = both.groupBy(F.col("u").alias("x")).agg(F.min("v").alias("y")).select("x", F.least("x", "y").alias("y"))
        hook = cut(hook)
        up = hook.select(F.col("x").alias("y"), F.col("y").alias("z"))
        jump = cut(hook.join(up, "y", "left").select("x", F.coalesce("z", "y").alias("y")))
        labels = jump if labels is None else labels.join(jump.select(F.col("x").alias("y"), F.col("y").alias("z")), "y", "left").select("x", F.coalesce("z", "y").alias("y"))
        labels = cut(labels)
        a = jump.select(F.col("x").alias("u"), F.col("y").alias("a"))
        b = jump.select(F.col("x").alias("v"), F.col("y").alias("b"))
        live = live.join(a, "u").join(b, "v").filter("a <> b").select(F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v")).distinct()
        live = cut(live)
    else:
        raise RuntimeError(f"edges are left after {max_rounds} rounds")
    if labels is None:
        return ends.select("v", F.col("v").alias("component"))
    found = labels.select(F.col("x").alias("v"), F.col("y").alias("component"))
    return ends.join(found, "v", "left").select("v", F.coalesce("component", "v").alias("component"))


def linked_components(edges: DataFrame, most_edges: int = 4_000_000) -> DataFrame:
    """(v, component) for the ends of edges between unlike ends, each in a component of two or more.

    Tasks keep forests of what they read; if these are most_edges at most they meet in one task, which
    needs no rounds, else they are joined by rounds.
    """
    thin = cut(thinned(edges))
    if thin.count() > most_edges:
        return relational_components(thin, thin=False)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        u, v = np.empty(0, np.int64), np.empty(0, np.int64)
        for batch in batches:
            u, v = np.concatenate([u, batch.column(0).to_numpy()]), np.concatenate([v, batch.column(1).to_numpy()])
            if len(u) >= 1 << 20:
                keep = forest_of(u, v)
                u, v = u[keep], v[keep]
        ids, label = labels_of(u, v)
        for i in range(0, len(ids), 1 << 16):
            yield pa.RecordBatch.from_arrays([pa.array(ids[i : i + (1 << 16)]), pa.array(label[i : i + (1 << 16)])], names=["v", "component"])

    return thin.repartition(1).mapInArrow(run, "v bigint, component bigint")


def relational_sides(edges: DataFrame) -> DataFrame:
    """(v, component, odd, side) for each end of an edge, from the components of the double cover; side 0 holds a component's least vertex."""
    arms = edges.select(F.explode(F.array(F.struct((2 * F.col("u")).alias("u"), (2 * F.col("v") + 1).alias("v")), F.struct((2 * F.col("u") + 1).alias("u"), (2 * F.col("v")).alias("v")))).alias("e")).select("e.u", "e.v")
    pair = relational_components(arms).groupBy(F.shiftright("v", 1).alias("v")).agg(F.min("component").alias("low"), F.min_by("component", "v").alias("first"), F.count_distinct("component").alias("parts"))
    return pair.select("v", F.shiftright("low", 1).alias("component"), (F.col("parts") < 2).alias("odd"), (F.col("first") % 2).cast("tinyint").alias("side"))


def relational_bipartite(edges: DataFrame) -> DataFrame:
    """One row (holds): no vertex meets its own copy in the double cover."""
    return relational_sides(edges).agg(F.coalesce(~F.bool_or("odd"), F.lit(True)).alias("holds"))


def relational_bipartite_cert(edges: DataFrame, per_component: bool = False) -> DataFrame:
    """A spanning forest, and the edge of least number that closes an odd cycle with it (or one in each component)."""
    forest = cut(relational_edge_cert(edges, 1).select("u", "v", "w", "eid"))
    sides = cut(relational_sides(forest))
    of = lambda x: sides.select(F.col("v").alias(x), F.col("component").alias(f"c{x}"), F.col("side").alias(f"s{x}"))
    same = edges.filter("u <> v").join(of("u"), "u").join(of("v"), "v").filter("su = sv")
    least = F.min(F.struct("eid", "u", "v", "w")).alias("e")
    odd = (same.groupBy("cu").agg(least) if per_component else same.agg(least)).filter("e is not null").select("e.u", "e.v", "e.w", "e.eid")
    return forest.union(odd)


def relational_min_forest(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """Minimum forest by rounds: each component takes its least edge out, then what these join is contracted.

    (u, v, w, eid) under the order (w, u, v, eid).
    """
    order = F.struct("w", F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"), "eid")
    live = cut(edges.filter("u <> v").select(F.col("u").alias("a"), F.col("v").alias("b"), order.alias("e")))
    taken = None
    for _ in range(max_rounds):
        if live.isEmpty():
            break
        out = live.select(F.col("a").alias("x"), "e").union(live.select(F.col("b").alias("x"), "e"))
        least = out.groupBy("x").agg(F.min("e").alias("e"))
        ends = live.select("e", "a", "b").join(least.select("e").distinct(), "e", "left_semi")
        picked = cut(ends)
        taken = picked.select("e") if taken is None else taken.union(picked.select("e"))
        joined = linked_components(picked.select(F.col("a").alias("u"), F.col("b").alias("v")))
        joined = cut(joined)
        ca, cb = joined.select(F.col("v").alias("a"), F.col("component").alias("na")), joined.select(F.col("v").alias("b"), F.col("component").alias("nb"))
        # of parallel edges between two components only the least can ever be taken
        live = live.join(ca, "a").join(cb, "b").filter("na <> nb").groupBy(F.least("na", "nb").alias("a"), F.greatest("na", "nb").alias("b")).agg(F.min("e").alias("e"))
        live = cut(live)
    else:
        raise RuntimeError(f"edges are left after {max_rounds} rounds")
    if taken is None:
        return edges.filter("false").select("u", "v", "w", "eid")
    return taken.select("e.u", "e.v", "e.w", "e.eid")


def relational_edge_cert(edges: DataFrame, k: int) -> DataFrame:
    """k times a spanning forest of what the ones before left: keeps min(edge connectivity, k) of all pairs.

    A forest is a minimum forest by edge number, so that it is the same whatever the partitioning.
    """
    left, kept = edges.select("u", "v", "w", "eid").filter("u <> v"), None
    for i in range(k):
        by_id = left.select("u", "v", F.col("eid").alias("w"), "eid")
        ids = cut(relational_min_forest(by_id).select("eid"))
        forest = left.join(ids, "eid", "left_semi").withColumn("forest_ix", F.lit(i + 1))
        kept = forest if kept is None else kept.unionByName(forest)
        if i + 1 < k:
            left = cut(left.join(ids, "eid", "left_anti").select("u", "v", "w", "eid"))
    return kept


def relational_vertex_cert(edges: DataFrame, k: int, max_depth: int = 10_000) -> DataFrame:
    """k times a breadth-first forest of what the ones before left, on distinct pairs: keeps min(vertex connectivity, k).

    A layer is one join; a component's least vertex is its root.
    """
    pairs = edges.filter("u <> v").groupBy(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).agg(F.min(F.struct("eid", "w")).alias("m"))
    left, kept = cut(pairs.select("u", "v", "m.w", "m.eid")), None
    for i in range(k):
        if left.isEmpty():
            break
        both = left.select("u", "v", "eid").union(left.select(F.col("v").alias("u"), F.col("u").alias("v"), "eid"))
        front = cut(relational_components(left).select("component").distinct().select(F.col("component").alias("u")))
        seen, tree = front, None
        for _ in range(max_depth):
            reached = both.join(front, "u").join(seen.select(F.col("u").alias("v")), "v", "left_anti")
            layer = cut(reached.groupBy("v").agg(F.min(F.struct("u", "eid")).alias("by")).select(F.col("v").alias("u"), "by.eid"))
            if layer.isEmpty():
                break
            tree = layer.select("eid") if tree is None else tree.union(layer.select("eid"))
            front = layer.select("u")
            seen = seen.union(front)
        ids = cut(tree)
        forest = left.join(ids, "eid", "left_semi").withColumn("forest_ix", F.lit(i + 1))
        kept = forest if kept is None else kept.unionByName(forest)
        left = cut(left.join(ids, "eid", "left_anti").select("u", "v", "w", "eid"))
    return kept if kept is not None else left.withColumn("forest_ix", F.lit(0))

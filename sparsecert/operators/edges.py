"""Operators on edge lists: what a graph's rows go through before and after a certificate."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from sparsecert.plans.relational import cut


def project_edges(df: DataFrame, u: Column, v: Column, w: Column | None = None) -> DataFrame:
    return df.select(u.cast("long").alias("u"), v.cast("long").alias("v"), (F.lit(1) if w is None else w).cast("long").alias("w"))


def drop_loops(edges: DataFrame) -> DataFrame:
    return edges.filter("u <> v")


def canonical(edges: DataFrame) -> DataFrame:
    """The lesser end first."""
    return edges.withColumns({"u": F.least("u", "v"), "v": F.greatest("u", "v")})


def dedupe_pairs(edges: DataFrame) -> DataFrame:
    """(u, v), once for each pair; partial before the shuffle."""
    return canonical(edges).select("u", "v").distinct()


def cap_multiplicity(edges: DataFrame, k: int) -> DataFrame:
    """At most k edges of each pair, least eid first."""
    pair = Window.partitionBy("u", "v").orderBy("eid")
    return canonical(edges).withColumn("_n", F.row_number().over(pair)).filter(F.col("_n") <= k).drop("_n")


def induced_subgraph(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    keep = vertices.select(F.col("v").alias("_k"))
    return edges.join(keep, F.col("u") == F.col("_k"), "left_semi").join(keep, F.col("v") == F.col("_k"), "left_semi")


def union_graph(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.unionByName(b, allowMissingColumns=True)


def prefix_graph(edges: DataFrame, i: int) -> DataFrame:
    """The edges that have arrived by i."""
    return edges.filter(F.col("seq") <= i)


def degrees(edges: DataFrame) -> DataFrame:
    """(v, degree, weight): both ends of each edge count."""
    return edges.select(F.explode(F.array("u", "v")).alias("v"), "w").groupBy("v").agg(F.count(F.lit(1)).alias("degree"), F.sum("w").alias("weight"))


def degree_filter(edges: DataFrame, least: int) -> DataFrame:
    """Edges between vertices of at least that degree."""
    return induced_subgraph(edges, degrees(edges).filter(F.col("degree") >= least).select("v"))


def multiplicity(edges: DataFrame) -> DataFrame:
    return canonical(edges).groupBy("u", "v").agg(F.count(F.lit(1)).alias("copies"))


def sample_edges(edges: DataFrame, fraction: float, seed: int) -> DataFrame:
    return edges.sample(fraction=fraction, seed=seed)


def neighbours(edges: DataFrame) -> DataFrame:
    """(v, near): sorted distinct neighbours; for graphs whose vertices have bounded degree."""
    both = edges.select(F.col("u").alias("v"), F.col("v").alias("x")).union(edges.select("v", F.col("u").alias("x")))
    return both.groupBy("v").agg(F.array_sort(F.collect_set("x")).alias("near"))


def distinct_neighbours(edges: DataFrame) -> DataFrame:
    both = edges.select(F.col("u").alias("v"), F.col("v").alias("x")).union(edges.select("v", F.col("u").alias("x")))
    return both.groupBy("v").agg(F.count_distinct("x").alias("near"))


def group_schedule(edges: DataFrame, r: int) -> DataFrame:
    """(group_id, edges_in, is_tail) for groups of r edges in their order: counts alone tell it."""
    m = edges.agg(F.count(F.lit(1)).alias("m"))
    groups = m.select("m", F.explode(F.when(F.col("m") > 0, F.sequence(F.lit(0).cast("long"), F.floor((F.col("m") - 1) / r)))).alias("group_id"))
    size = F.least(F.lit(r).cast("long"), F.col("m") - F.col("group_id") * r)
    return groups.select("group_id", size.alias("edges_in"), (size < r).alias("is_tail"))


def top_k_per_vertex(edges: DataFrame, k: int) -> DataFrame:
    """The k heaviest edges at each first end."""
    heaviest = Window.partitionBy("u").orderBy(F.col("w").desc(), "v", "eid")
    return edges.withColumn("rank", F.row_number().over(heaviest)).filter(F.col("rank") <= k)


def salted_join(edges: DataFrame, labels: DataFrame, key: str, salts: int = 8) -> DataFrame:
    """A join on a key of which few values hold most rows: each value is dealt to `salts` tasks."""
    left = edges.withColumn("_salt", F.pmod(F.xxhash64("eid"), F.lit(salts)).cast("int"))
    right = labels.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return left.join(right, [key, "_salt"]).drop("_salt")


def asof_join(left: DataFrame, right: DataFrame, by: str, at: str, value: str, tie: str) -> DataFrame:
    """Adds to each left row the newest right value at or before it; one union and one window per key."""
    a = left.select("*", F.lit(1).alias("_side"), F.lit(None).cast(right.schema[value].dataType).alias(f"_{value}"))
    b = right.select(F.col(by), F.col(at), F.col(value).alias(f"_{value}"), F.col(tie).alias(tie)).withColumn("_side", F.lit(0))
    both = a.unionByName(b, allowMissingColumns=True)
    upto = Window.partitionBy(by).orderBy(at, "_side", tie).rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn(value, F.last(f"_{value}", ignorenulls=True).over(upto)).filter("_side = 1").drop("_side", f"_{value}")


def band_join(left: DataFrame, right: DataFrame, a: str, b: str, width: float) -> DataFrame:
    """Pairs with |a - b| <= width: equal buckets of that width, next ones added, then the exact condition."""
    x = left.withColumn("_bucket", F.explode(F.transform(F.array(F.lit(-1), F.lit(0), F.lit(1)), lambda d: F.floor(F.col(a) / width) + d)))
    y = right.withColumn("_bucket", F.floor(F.col(b) / width))
    return x.join(y, "_bucket").filter(F.abs(F.col(a) - F.col(b)) <= width).drop("_bucket")


def interval_join(left: DataFrame, right: DataFrame, by: str, a: str, b: str, seconds: int) -> DataFrame:
    """Pairs of a key with 0 < b - a <= seconds: bins of that length, and the next one."""
    micros = lambda c: F.unix_micros(F.col(c).cast("timestamp"))
    width = seconds * 1_000_000
    x = left.withColumn("_bin", F.explode(F.array(F.floor(micros(a) / width), F.floor(micros(a) / width) + 1)))
    y = right.withColumn("_bin", F.floor(micros(b) / width))
    return x.join(y, [by, "_bin"]).filter((micros(b) > micros(a)) & (micros(b) - micros(a) <= width)).drop("_bin")


def dictionary(df: DataFrame, column: str, parts: int | None = None) -> DataFrame:
    """(column, id): the distinct values numbered from 0 in their order, without gaps; no two values share a number.

    Values are range-sorted; a table of the ranges, one row each, gives the first number of each.
    """
    parts = parts or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = cut(df.select(column).filter(F.col(column).isNotNull()).distinct().repartitionByRange(parts, column).withColumn("_p", F.spark_partition_id()))
    ahead = Window.orderBy("_q").rowsBetween(Window.unboundedPreceding, -1)
    first = dealt.groupBy(F.col("_p").alias("_q")).agg(F.count(F.lit(1)).alias("_c")).select("_q", F.coalesce(F.sum("_c").over(ahead), F.lit(0)).alias("_first"))
    local = dealt.withColumn("_n", F.row_number().over(Window.partitionBy("_p").orderBy(column)))
    return local.join(first, F.col("_p") == F.col("_q")).select(column, (F.col("_first") + F.col("_n") - 1).alias("id"))

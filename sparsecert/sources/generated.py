"""Small graphs of known answers, made from spark.range."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def _edges(df: DataFrame, u, v, w=None) -> DataFrame:
    out = df.select(u.cast("long").alias("u"), v.cast("long").alias("v"), (F.lit(1) if w is None else w).cast("long").alias("w"))
    return out.withColumn("eid", F.xxhash64("u", "v")).withColumn("seq", F.col("eid"))


def path(spark: SparkSession, n: int) -> DataFrame:
    return _edges(spark.range(n - 1), F.col("id"), F.col("id") + 1)


def cycle(spark: SparkSession, n: int) -> DataFrame:
    return _edges(spark.range(n), F.col("id"), (F.col("id") + 1) % n)


def star(spark: SparkSession, n: int) -> DataFrame:
    return _edges(spark.range(1, n), F.lit(0), F.col("id"))


def clique(spark: SparkSession, n: int) -> DataFrame:
    pairs = spark.range(n * n).select((F.col("id") / n).cast("long").alias("a"), (F.col("id") % n).alias("b")).filter("a < b")
    return _edges(pairs, F.col("a"), F.col("b"))


def complete_bipartite(spark: SparkSession, a: int, b: int) -> DataFrame:
    return _edges(spark.range(a * b), (F.col("id") / b).cast("long"), a + F.col("id") % b)


def grid(spark: SparkSession, rows: int, columns: int) -> DataFrame:
    cell = spark.range(rows * columns).withColumn("c", F.col("id") % columns)
    return _edges(cell.filter(F.col("c") < columns - 1), F.col("id"), F.col("id") + 1).union(_edges(cell.filter(F.col("id") < (rows - 1) * columns), F.col("id"), F.col("id") + columns))


def random_graph(spark: SparkSession, n: int, m: int, seed: int = 0) -> DataFrame:
    """m edges between hashed ends, copies and all but loops included; the same for a seed on any cluster."""
    end = lambda salt: F.pmod(F.xxhash64(F.col("id"), F.lit(seed), F.lit(salt)), F.lit(n))
    df = spark.range(m).select(end(1).alias("a"), end(2).alias("b"), F.pmod(F.xxhash64(F.col("id"), F.lit(seed), F.lit(3)), F.lit(1000)).alias("w"), "id")
    return df.filter("a <> b").select(F.col("a").alias("u"), F.col("b").alias("v"), "w", F.col("id").alias("eid"), F.col("id").alias("seq"))


def rate_edges(spark: SparkSession, vertices: int, per_batch: int) -> DataFrame:
    """An endless stream of random edges, so many a trigger."""
    rate = spark.readStream.format("rate-micro-batch").option("rowsPerBatch", per_batch).option("numPartitions", 2).load()
    end = lambda salt: F.pmod(F.xxhash64("value", F.lit(salt)), F.lit(vertices))
    return rate.select(end(1).alias("u"), end(2).alias("v"), F.lit(1).cast("long").alias("w"), F.col("value").alias("eid"), F.col("value").alias("seq"))

"""Reading tables and edge lists, and writing certificates and edge lists."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")

EDGE_SCHEMA = T.StructType(
    [
        T.StructField("u", T.LongType(), False),
        T.StructField("v", T.LongType(), False),
        T.StructField("w", T.LongType(), True),
        T.StructField("eid", T.LongType(), False),
        T.StructField("seq", T.LongType(), True),
    ]
)


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table; filters and columns chosen later reach the Parquet scan."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = TABLES) -> None:
    """The tables as temporary views, for SQL."""
    for name in names:
        load(spark, sf_dir, name).createOrReplaceTempView(name)


def spread(df: DataFrame, parts: int, seed: int | None = None) -> DataFrame:
    """Deals rows to so many tasks: files of one row group would all go to one. A seed gives another order."""
    return df.repartition(parts) if seed is None else df.repartition(parts, F.xxhash64(F.lit(seed), *df.columns))


def stream_table(spark: SparkSession, sf_dir: str, name: str, per_trigger: int = 1) -> DataFrame:
    """A table as a stream of its files; the schema is that of the table."""
    schema = load(spark, sf_dir, name).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).option("pathGlobFilter", f"{name}*.parquet").parquet(sf_dir)


FORMATS = ("parquet", "csv", "json", "orc")


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    """An edge list with columns u, v and, if there, w, eid and seq; Avro needs Spark's own package."""
    reader = spark.read.schema(EDGE_SCHEMA)
    return reader.option("header", True).csv(path) if fmt == "csv" else reader.format(fmt).load(path)


def write_edges(edges: DataFrame, path: str, fmt: str = "parquet", mode: str = "errorifexists") -> None:
    out = edges.select(*[c for c in EDGE_SCHEMA.names if c in edges.columns]).write.mode(mode)
    out.option("header", True).csv(path) if fmt == "csv" else out.format(fmt).save(path)


def save_bucketed(edges: DataFrame, table: str, buckets: int) -> None:
    """A certificate as a table bucketed by one end, so that joins on it need no shuffle."""
    edges.write.mode("overwrite").bucketBy(buckets, "u").sortBy("u").saveAsTable(table)

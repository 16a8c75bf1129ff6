"""Distributed prefix sums and ranks, with DataFrame operations only.

Rows are range-sorted by group and order into stretches of equal size, whatever groups and keys they
hold: the order ends with a column that tells all rows apart, so that a key or source with a third
of all rows is spread over as many stretches as it needs.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from sparsecert.llm.common import staged


def prefix_before(df: DataFrame, group: str, order: list[str], value: Column, out: str, rows: int, rows_per_stretch: int = 16_384, most_stretches: int = 20_000) -> DataFrame:
    """Adds `out`: the sum of value over the rows of the same group that come before in the order.

    df: a written table, as it is read more than once. rows: its rows. The last column of the order
    must differ in all rows. Beyond most_stretches the stretches grow; a group has at most one
    offset a stretch.
    """
    stretches = max(1, min(most_stretches, -(-rows // rows_per_stretch)))
    dealt = df.withColumn("_value", value.cast("long")).repartitionByRange(stretches, group, *order).withColumn("_bucket", F.spark_partition_id())
    dealt = staged(dealt, "stretches")
    sums = dealt.groupBy(F.col(group).alias("_g"), F.col("_bucket").alias("_b")).agg(F.sum("_value").alias("_s"))
    ahead = Window.partitionBy("_g").orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)
    offsets = sums.select("_g", "_b", F.coalesce(F.sum("_s").over(ahead), F.lit(0)).alias("_offset"))
    within = Window.partitionBy(group, "_bucket").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    local = dealt.withColumn("_local", F.coalesce(F.sum("_value").over(within), F.lit(0)))
    joined = local.join(offsets, (F.col(group) == F.col("_g")) & (F.col("_bucket") == F.col("_b")))
    return joined.withColumn(out, F.col("_offset") + F.col("_local")).drop("_g", "_b", "_bucket", "_value", "_offset", "_local")

"""A filter of fixed size: which rows may have a partner, told without a shuffle of their texts."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

FILTER_BITS = 1 << 25


def bitmap(keys: DataFrame, key: str) -> DataFrame:
    """At most FILTER_BITS / 32768 rows of 4 KB, whatever the input: 4 MB. Fuller with more keys, never wrong."""
    folded = F.pmod(F.col(key), F.lit(FILTER_BITS))
    return keys.groupBy(F.bitmap_bucket_number(folded).alias("_bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(folded)).alias("_bits"))


def flagged(df: DataFrame, key: str, bits: DataFrame) -> DataFrame:
    """Adds _maybe: false only where no row that the bitmap was made from has this key."""
    folded = F.pmod(F.col(key), F.lit(FILTER_BITS))
    placed = df.withColumn("_b", F.bitmap_bucket_number(folded)).withColumn("_place", F.bitmap_bit_position(folded))
    joined = placed.join(F.broadcast(bits), F.col("_b") == F.col("_bucket"), "left")
    byte = F.conv(F.hex(F.substring("_bits", (F.col("_place") / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
    hit = F.getbit(byte, (F.col("_place") % 8).cast("int")) == 1
    return joined.withColumn("_maybe", F.coalesce(hit, F.lit(False))).drop("_b", "_place", "_bucket", "_bits")


def without(df: DataFrame, gone: DataFrame, key: str) -> DataFrame:
    """df without the rows whose key is in gone; only rows that the filter can't clear are shuffled."""
    marked = flagged(df, key, bitmap(gone, key))
    clear = marked.filter("not _maybe").drop("_maybe")
    return clear.unionByName(marked.filter("_maybe").drop("_maybe").join(gone.select(key).distinct(), key, "left_anti").select(*clear.columns))

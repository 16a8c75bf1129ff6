"""Exact deduplication by composable polynomial fingerprints.

A text without its white space is hashed in chunks; the hash of a whole follows from the hashes of
its parts, each shifted by the length of what follows. The pieces of a huge text are hashed by many
tasks, and their hashes combined. Texts with equal fingerprints are compared
with one of their group, chunk by chunk; those that differ go through another round with other bases.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sparsecert.llm.bitfilter import bitmap, flagged, without
from sparsecert.llm.common import load, slices, staged

#: The characters that equality ignores, and the prime that hashes are taken modulo.
BLANKS = b" \t\n\x0b\x0c\r"
PRIME = (1 << 31) - 1
#: A chunk of so many bytes keeps sums of products below 2^53, where doubles are exact.
CHUNK = 8192
HASHES = 4
COMPARE_BYTES = 1 << 16
LONG = 4 << 20  # bytes of a text whose pieces are dealt to many tasks
PIECE = 1 << 20


class Fingerprint:
    """Four polynomial hashes modulo a prime; `seed` picks their bases."""

    def __init__(self, seed: int = 0):
        draw = np.random.default_rng(1000 + seed)
        self.bases = [int(b) for b in draw.integers(1 << 20, PRIME - 1, HASHES)]
        powers = np.ones((HASHES, CHUNK), dtype=np.int64)
        for j, b in enumerate(self.bases):
            for i in range(1, CHUNK):
                powers[j, i] = int(powers[j, i - 1]) * b % PRIME
        self.falling = np.ascontiguousarray(powers[:, ::-1].astype(np.float64))

    def chunk(self, data: bytes) -> tuple[int, ...]:
        """Of at most CHUNK bytes."""
        values = np.frombuffer(data, dtype=np.uint8).astype(np.float64) + 1.0
        return tuple(int(x) % PRIME for x in self.falling[:, CHUNK - len(data) :] @ values)

    def join(self, left: tuple[int, ...], right: tuple[int, ...], right_length: int) -> tuple[int, ...]:
        """The hashes of a text whose first part has `left` and whose last right_length bytes have `right`."""
        return tuple((a * pow(b, right_length, PRIME) + c) % PRIME for a, c, b in zip(left, right, self.bases, strict=True))

    def of(self, data: bytes) -> tuple[int, ...]:
        view, out = memoryview(data), (0,) * HASHES
        for i in range(0, len(view), CHUNK):
            part = view[i : i + CHUNK]
            out = self.join(out, self.chunk(part), len(part)) if i else self.chunk(part)
        return out


def normalised(data: bytes) -> bytes:
    return data.translate(None, BLANKS)


def _fingerprints(seed: int, longest: int, text: str):
    """Adds _f1, _f2, _len, _sha; they are null for texts of more bytes than longest."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hasher = Fingerprint(seed)
        for batch in slices(batches, text):
            low, high, length, sha = [], [], [], []
            for value in batch.column(text).cast(pa.binary()):  # one copy at a time
                data = value.as_py() or b""
                if len(data) > longest:
                    for column in (low, high, length, sha):
                        column.append(None)
                    continue
                data = normalised(data)
                a, b, c, d = hasher.of(data)
                low.append(a << 31 | b)
                high.append(c << 31 | d)
                length.append(len(data))
                sha.append(hashlib.sha256(data).hexdigest())
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(low, pa.int64()), pa.array(high, pa.int64()), pa.array(length, pa.int64()), pa.array(sha, pa.string())], names=[*batch.schema.names, "_f1", "_f2", "_len", "_sha"])

    return run


def _piece_hashes(seed: int):
    """The hashes of pieces as four longs, and their lengths."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hasher = Fingerprint(seed)
        for batch in batches:
            pieces = batch.column("_piece").to_pylist()
            yield pa.RecordBatch.from_arrays([batch.column("_row"), batch.column("_at"), pa.array([len(p) for p in pieces], pa.int64()), pa.array([list(hasher.of(p)) for p in pieces], pa.list_(pa.int64()))], names=["_row", "_at", "_bytes", "_hashes"])

    return run


def _combined(seed: int):
    """Joins the hashes of a text's pieces, in order, each shifted by the length of what follows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hasher = Fingerprint(seed)
        for batch in batches:
            low, high, length = [], [], []
            for parts in batch.column("_parts").to_pylist():
                whole, size = (0,) * HASHES, 0
                for part in parts:
                    whole = hasher.join(whole, tuple(part["_hashes"]), part["_bytes"])
                    size += part["_bytes"]
                a, b, c, d = whole
                low.append(a << 31 | b)
                high.append(c << 31 | d)
                length.append(size)
            yield pa.RecordBatch.from_arrays([batch.column("_row"), *[pa.array(x, pa.int64()) for x in (low, high, length)]], names=["_row", "_f1", "_f2", "_len"])

    return run


KEY = ["_f1", "_f2", "_len"]


def with_fingerprints(df: DataFrame, text: str, seed: int, longest: int = LONG, piece: int = PIECE) -> DataFrame:
    """df (with _row) as a written table with the fingerprint columns, _sha among them.

    Texts of more than longest bytes are cut into pieces without their white space, which tasks hash
    apart; a text's fingerprint is the same either way.
    """
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema.fields) + ", _f1 bigint, _f2 bigint, _len bigint, _sha string"
    work = staged(df.mapInArrow(_fingerprints(seed, longest, text), schema), "prints")
    long = work.filter("_sha is null")
    if long.isEmpty():
        return work
    norm = F.translate(F.col(text), BLANKS.decode(), "").cast("binary")
    solid = long.select("_row", norm.alias("_norm")).withColumn("_sha", F.sha2("_norm", 256))
    last = F.greatest(F.floor((F.octet_length("_norm") - 1) / piece).cast("int"), F.lit(0))
    pieces = solid.select("_row", "_sha", "_norm", F.explode(F.sequence(F.lit(0), last)).alias("_at")).select("_row", "_at", F.expr(f"substring(_norm, _at * {piece} + 1, {piece})").alias("_piece"))
    hashed = pieces.repartition("_row", "_at").mapInArrow(_piece_hashes(seed), "_row bigint, _at int, _bytes bigint, _hashes array<bigint>")
    parts = hashed.groupBy("_row").agg(F.array_sort(F.collect_list(F.struct("_at", "_bytes", "_hashes"))).alias("_parts"))
    prints = parts.mapInArrow(_combined(seed), "_row bigint, _f1 bigint, _f2 bigint, _len bigint").join(solid.select("_row", "_sha"), "_row")
    prints = staged(prints, "longprints")
    return work.filter("_sha is not null").unionByName(long.drop(*KEY, "_sha").join(prints, "_row"))


def _round(work: DataFrame, seed: int, text: str) -> tuple[DataFrame, DataFrame]:
    """work: _row, text and fingerprint. Returns the groups of two or more, and their rows with _same."""
    groups = work.groupBy(*KEY).agg(F.count(F.lit(1)).alias("_n"), F.min("_row").alias("_head")).filter("_n > 1")
    groups = staged(groups, "groups")
    rows = flagged(work.select("_row", *KEY, "_sha", F.col(text).alias("_text")), "_f1", bitmap(groups, "_f1")).filter("_maybe").drop("_maybe")
    rows = rows.withColumn("_norm", F.translate(F.coalesce(F.col("_text"), F.lit("")), BLANKS.decode(), "").cast("binary"))
    heads = rows.join(groups.select(F.col("_head").alias("_row"), F.lit(1).alias("_is_head")), "_row").select(*KEY, F.col("_norm").alias("_head_norm"))
    heads = staged(heads, "heads")
    steps = F.sequence(F.lit(0), F.greatest(F.floor((F.col("_len") - 1) / COMPARE_BYTES).cast("int"), F.lit(0)))
    part = lambda c, i: F.substring(F.col(c), i * COMPARE_BYTES + 1, F.lit(COMPARE_BYTES))
    same = F.forall(steps, lambda i: part("_norm", i) == part("_head_norm", i))
    compared = rows.join(heads, KEY).withColumn("_same", same)
    compared = compared.select("_row", *KEY, "_sha", "_same", F.length(F.coalesce(F.col("_text"), F.lit(""))).alias("_points"), F.when(~F.col("_same"), F.col("_text")).alias("_text"))
    return groups, staged(compared.withColumn("_round", F.lit(seed)), "compared")


def equal_classes(work: DataFrame, text: str = "text", first_seed: int = 0, hasher=with_fingerprints) -> DataFrame:
    """The rows of work (with _row and fingerprint) that have an equal: _row, _points, and the key of their class."""
    settled, seed = None, first_seed
    while True:
        _, compared = _round(work, seed, text)
        good = compared.filter("_same").select("_row", "_points", "_round", *KEY)
        settled = good if settled is None else settled.unionByName(good)
        rest = compared.filter("not _same")
        if rest.isEmpty():
            return settled
        seed += 1
        work, text = hasher(rest.select("_row", "_text"), "_text", seed), "_text"


def prepared(docs: DataFrame, text: str = "text", hasher=with_fingerprints) -> DataFrame:
    """docs as a written table with a row number and fingerprints."""
    return hasher(docs.withColumn("_row", F.monotonically_increasing_id()), text, 0)


def decisions(work: DataFrame, text: str = "text", key: str = "doc_id", hasher=with_fingerprints) -> DataFrame:
    """For rows of work that have an equal: _row, keep_id, group_size, kept."""
    ids = work.select(F.col("_row").alias("_r"), F.col(key).alias("_id"))
    rows = equal_classes(work, text, hasher=hasher).join(ids, F.col("_row") == F.col("_r")).drop("_r")
    rows = staged(rows, "classes")
    best = F.min(F.struct((-F.col("_points")).alias("p"), F.col("_id").isNull().alias("z"), F.col("_id").alias("id"), F.col("_row").alias("row")))
    classes = rows.groupBy("_round", *KEY).agg(best.alias("_best"), F.count(F.lit(1)).alias("group_size"))
    # a table of its own, so that the join's sides are plain shuffles, whose large partitions Spark splits
    joined = rows.join(staged(classes, "best"), ["_round", *KEY])
    return joined.select("_row", F.col("_best.id").alias("keep_id"), "group_size", (F.col("_row") == F.col("_best.row")).alias("kept"))


def exact_classes(docs: DataFrame, text: str = "text", key: str = "doc_id", hasher=with_fingerprints) -> DataFrame:
    """One row per row of docs: doc_id, keep_id, group_size, kept, text_sha256.

    Null texts count as empty, and all texts without a letter are equal. Exactly one row of a class
    is kept, even if rows repeat an id: longest original, then least id (null last), then first read.
    An empty table gives an empty result; further columns of docs are ignored.
    """
    work = prepared(docs.select(F.col(key).alias("_key"), F.col(text).alias("_source_text")), "_source_text", hasher)
    found = decisions(work, "_source_text", "_key", hasher).withColumnRenamed("_row", "_r")
    joined = work.select("_row", "_key", "_sha").join(found, F.col("_row") == F.col("_r"), "left")
    return joined.select(
        F.col("_key").alias("doc_id"), F.when(F.col("kept").isNull(), F.col("_key")).otherwise(F.col("keep_id")).alias("keep_id"), F.coalesce(F.col("group_size"), F.lit(1)).cast("long").alias("group_size"),
        F.coalesce(F.col("kept"), F.lit(True)).alias("kept"), F.col("_sha").alias("text_sha256"),
    )


def without_copies(docs: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """docs without the rows that exact_classes doesn't keep, all columns as they were."""
    work = prepared(docs, text)
    dropped = staged(decisions(work, text, key).filter("not kept").select("_row"), "dropped")
    return without(work.drop(*KEY, "_sha"), dropped, "_row").select(*docs.columns)


def op10_polynomial_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_classes(load(spark, sf_dir, "documents"))


OP10_SQL = r"""
WITH d AS (
  SELECT doc_id, length(coalesce(text, '')) AS points, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]', '', 'g') AS norm FROM documents
), g AS (
  SELECT norm, count(*) AS group_size, arg_min(doc_id, (-points, doc_id)) AS keep_id FROM d GROUP BY norm
)
SELECT d.doc_id, g.keep_id, CAST(g.group_size AS BIGINT) AS group_size, d.doc_id = g.keep_id AS kept, sha256(d.norm) AS text_sha256
FROM d JOIN g USING (norm)
"""

"""Near-duplicate texts: consistent weighted sampling over weighted word shingles, banded and verified.

A shingle is five words. Its weight is its count in the text times a damped inverse document
frequency, taken from a table of fixed size that counts all documents by hashed shingle. Weights
stand on a geometric grid, so that a sample's draw is a table entry: for each of K hashes the entry
with the least draw, and the shingle that it belongs to, is the text's signature. Texts that agree on
a band are candidates; a candidate pair is a link if the weighted Jaccard similarity of the two whole
texts reaches the threshold.

Texts joined by bands form groups. A small group is compared in one task. In a larger one each text
meets hubs; what then still stands outside the group's main component meets every text of the group,
so that no link between candidates is lost, and no group emits all its pairs.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sparsecert.llm.bitfilter import bitmap, flagged, without
from sparsecert.llm.common import load, slices, staged
from sparsecert.plans.relational import linked_components

WORDS = 5
THRESHOLD = 0.8
BANDS, ROWS = 12, 4
FREQUENCY_BITS = 18
GRID = 2.0**0.25
DAMPING = 0.5
SLOTS = 4096
HUBS = 16
CHUNK = 128
MEET_BYTES = 4 << 20  # of texts on each side of a later comparison's task
SLICE_BYTES = 1 << 20

BLANK = np.zeros(256, dtype=bool)
BLANK[[32, 9, 10, 11, 12, 13]] = True
_MIX = np.uint64(0x9E3779B97F4A7C15)


def _mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(31))) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> np.uint64(29))) * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(32))


PRIME = 0x100000001B3
STRETCH = 1 << 18  # bytes whose signs are hashed at a time: some 70 bytes of arrays a sign


class Shingler:
    """Distinct shingles of a list of texts, by whole-array steps over stretches of bounded size."""

    def __init__(self, words: int = WORDS):
        self.words = words
        self.powers = np.multiply.accumulate(np.full(STRETCH, PRIME, dtype=np.uint64))
        self.steps = _mixed(np.arange(1, words + 1, dtype=np.uint64) * _MIX) | np.uint64(1)

    def word_hashes(self, data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Hash and first place of each word. A word that a stretch's end cuts is hashed in parts, each shifted by the length before it."""
        hashes, places, open_ = [np.empty(0, np.uint64)], [np.empty(0, np.int64)], 0
        for low in range(0, len(data), STRETCH):
            part = data[low : low + STRETCH]
            solid = ~BLANK[part]
            edge = np.diff(np.concatenate([[False], solid, [False]]).view(np.int8))
            starts, ends = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
            if not len(starts):
                open_ = 0
                continue
            at = np.flatnonzero(solid)
            lengths = ends - starts
            first = np.concatenate([[0], np.cumsum(lengths)[:-1]])
            place = np.arange(len(at)) - np.repeat(first, lengths)
            h = np.add.reduceat((part[at].astype(np.uint64) + np.uint64(1)) * self.powers[place], first)
            goes_on = int(bool(open_) and starts[0] == 0)
            if goes_on:
                begun = next(x for x in reversed(hashes) if len(x))
                begun[-1] = np.uint64((int(begun[-1]) + int(h[0]) * pow(PRIME, open_, 1 << 64)) & ((1 << 64) - 1))
            open_ = (int(lengths[-1]) + (open_ if goes_on and len(starts) == 1 else 0)) if ends[-1] == len(part) else 0
            hashes.append(h[goes_on:])
            places.append(starts[goes_on:] + low)
        return _mixed(np.concatenate(hashes)), np.concatenate(places)

    def of(self, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(text's place, shingle, count), by text, then shingle. Texts of fewer words have one shingle, blank ones none."""
        data = np.frombuffer(b" ".join([*texts, b""]), dtype=np.uint8)
        none = np.empty(0, dtype=np.int64), np.empty(0, dtype=np.uint64), np.empty(0, dtype=np.int64)
        word, starts = self.word_hashes(data)
        if not len(starts):
            return none
        borders = np.cumsum([len(t) + 1 for t in texts])
        owner = np.searchsorted(borders, starts, side="right")
        n = self.words
        per = np.bincount(owner, minlength=len(texts))
        parts, owners = [], []
        if len(word) >= n:
            full = np.flatnonzero(owner[: len(word) - n + 1] == owner[n - 1 :])
            parts.append(sum(word[full + j] * self.steps[j] for j in range(n)))
            owners.append(owner[full])
        short = np.flatnonzero((per > 0) & (per < n))
        if len(short):
            begin = np.concatenate([[0], np.cumsum(per)[:-1]])
            parts.append(np.array([np.sum(word[begin[d] : begin[d] + per[d]] * self.steps[: per[d]], dtype=np.uint64) + np.uint64(per[d]) for d in short], dtype=np.uint64))
            owners.append(short)
        bits = max(1, int(len(texts)).bit_length())
        key = np.sort((np.concatenate(owners).astype(np.uint64) << np.uint64(64 - bits)) | (_mixed(np.concatenate(parts)) >> np.uint64(24)))
        new = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
        distinct = key[new]
        return (distinct >> np.uint64(64 - bits)).astype(np.int64), distinct & np.uint64((1 << 40) - 1), np.diff(np.concatenate([new, [len(key)]]))


def buckets_of(shingles: np.ndarray) -> np.ndarray:
    return (shingles & np.uint64((1 << FREQUENCY_BITS) - 1)).astype(np.int64)


def levels(shingles: np.ndarray, counts: np.ndarray, weights: np.ndarray) -> np.ndarray:
    """Places on the grid of count times weight."""
    w = counts * weights[buckets_of(shingles)]
    return np.rint(np.log(w) / math.log(GRID)).astype(np.int64)


class Sampler:
    """Tables of improved consistent weighted sampling: draws by hash, slot and grid level."""

    def __init__(self, hashes: int = BANDS * ROWS, seed: int = 5):
        draw = np.random.default_rng(seed)
        self.scale, self.cost, self.shift = draw.gamma(2.0, 1.0, (hashes, SLOTS)), draw.gamma(2.0, 1.0, (hashes, SLOTS)), draw.random((hashes, SLOTS))
        self.odd = draw.integers(0, 1 << 62, hashes, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
        self.tables: dict[tuple[int, int], np.ndarray] = {}

    def table(self, k: int, level: int) -> np.ndarray:
        """Order of the draws at a weight of GRID ** level, as the upper half of 64 bits."""
        if (k, level) not in self.tables:
            r = self.scale[k]
            t = np.floor(level * math.log(GRID) / r + self.shift[k])
            draw = (np.log(self.cost[k]) - r * (t - self.shift[k]) - r).astype(np.float32).view(np.int32).astype(np.int64)
            order = np.where(draw < 0, -(draw & 0x7FFFFFFF), draw) + (1 << 31)
            self.tables[k, level] = order.astype(np.uint64) << np.uint64(32)
        return self.tables[k, level]

    def signatures(self, starts: np.ndarray, shingles: np.ndarray, level: np.ndarray) -> np.ndarray:
        """(texts, hashes): the least draw with its shingle, for texts whose shingles begin at starts."""
        low = shingles & np.uint64(0xFFFFFFFF)
        slot_bits = np.uint64(64 - SLOTS.bit_length() + 1)
        groups = [(int(q), np.flatnonzero(level == q)) for q in np.unique(level)]
        out = np.empty((len(starts), len(self.odd)), dtype=np.uint64)
        wide = shingles << np.uint64(24) | shingles
        for k, odd in enumerate(self.odd):
            slots = ((wide * odd) >> slot_bits).astype(np.int64)
            drawn = np.empty(len(shingles), dtype=np.uint64)
            for q, at in groups:
                if len(groups) == 1:
                    drawn = self.table(k, q)[slots]
                else:
                    drawn[at] = self.table(k, q)[slots[at]]
            out[:, k] = np.minimum.reduceat(drawn | low, starts)
        return out


def band_keys(signatures: np.ndarray) -> np.ndarray:
    """(texts, bands) of 64-bit keys, the band's number mixed in."""
    out = np.empty((len(signatures), BANDS), dtype=np.uint64)
    for b in range(BANDS):
        key = np.full(len(signatures), (b + 1) * 0x9E3779B1, dtype=np.uint64)
        for r in range(ROWS):
            key = _mixed((key ^ signatures[:, b * ROWS + r]) * _MIX)
        out[:, b] = key
    return out.view(np.int64)


CHUNKS = 64


def _frequencies(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    shingler, counts, documents = Shingler(), np.zeros(1 << FREQUENCY_BITS, dtype=np.int64), 0
    for batch in slices(batches, "_bytes", most_bytes=SLICE_BYTES):
        texts = batch.column("_bytes").to_pylist()
        counts += np.bincount(buckets_of(shingler.of(texts)[1]), minlength=1 << FREQUENCY_BITS)
        documents += len(texts)
    if documents:
        part = counts.reshape(CHUNKS, -1)
        yield pa.RecordBatch.from_arrays([pa.array(range(CHUNKS), pa.int32()), pa.array([x.tobytes() for x in part], pa.binary()), pa.array([documents if i == 0 else 0 for i in range(CHUNKS)], pa.int64())], names=["chunk", "counts", "documents"])


def _added(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Sums the tables of a task by chunk as they stream by."""
    held: dict[int, np.ndarray] = {}
    documents: dict[int, int] = {}
    for batch in batches:
        for c, x, n in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True):
            held[c] = held[c] + np.frombuffer(x, np.int64) if c in held else np.frombuffer(x, np.int64)
            documents[c] = documents.get(c, 0) + n
    if held:
        yield pa.RecordBatch.from_arrays([pa.array(list(held), pa.int32()), pa.array([x.tobytes() for x in held.values()], pa.binary()), pa.array(list(documents.values()), pa.int64())], names=["chunk", "counts", "documents"])


def shingle_weights(texts: DataFrame) -> np.ndarray:
    """Damped inverse document frequencies by hashed shingle, counted over all rows of _bytes.

    The table has 2^18 entries whatever the input; tasks' tables are added in a tree.
    """
    schema = "chunk int, counts binary, documents bigint"
    counts = texts.mapInArrow(_frequencies, schema)
    for width in (16, 1):
        dealt = counts.withColumn("_d", F.spark_partition_id() % width).repartition(CHUNKS, "chunk", "_d").drop("_d")
        counts = dealt.mapInArrow(_added, schema)
    rows = {r["chunk"]: r for r in counts.collect()}  # CHUNKS rows of 32 KB
    if not rows:
        return np.ones(1 << FREQUENCY_BITS)
    n = sum(r["documents"] for r in rows.values())
    df = np.concatenate([np.frombuffer(rows[c]["counts"], np.int64) for c in range(CHUNKS)])
    return 1.0 + DAMPING * np.log((1.0 + n) / (1.0 + np.minimum(df, n))) / math.log(1.0 + n)


def _signed(weights, text: str):
    """Adds _bands: the keys of a text's bands, null for blank texts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingler, sampler, idf = Shingler(), Sampler(), weights.value
        for batch in slices(batches, text, most_bytes=SLICE_BYTES):
            owner, shingles, counts = shingler.of([t or b"" for t in batch.column(text).cast(pa.binary()).to_pylist()])
            keys: list[list[int] | None] = [None] * batch.num_rows
            if len(owner):
                starts = np.flatnonzero(np.concatenate([[True], owner[1:] != owner[:-1]]))
                for i, row in zip(owner[starts].tolist(), band_keys(sampler.signatures(starts, shingles, levels(shingles, counts, idf))).tolist(), strict=True):
                    keys[i] = row
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(keys, pa.list_(pa.int64()))], names=[*batch.schema.names, "_bands"])

    return run


def similarity(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray]) -> float:
    """Weighted Jaccard of two texts' (sorted shingles, weights)."""
    if not len(a[0]) or not len(b[0]):
        return 0.0
    at = np.minimum(np.searchsorted(b[0], a[0]), len(b[0]) - 1)
    hit = b[0][at] == a[0]
    both = np.minimum(a[1][hit], b[1][at[hit]]).sum()
    return float(both / (a[1].sum() + b[1].sum() - both))


class Compared:
    """Texts of one task with their shingles, compared pair by pair; what is already joined isn't compared again."""

    def __init__(self, table: pa.Table, idf: np.ndarray, threshold: float):
        table = table.combine_chunks()
        self.ids = table.column("rep").to_numpy()
        self.keys = np.array(table.column("keys").to_pylist(), dtype=np.int64).reshape(len(self.ids), BANDS)
        self.hub = table.column("hub").to_numpy(zero_copy_only=False).astype(bool)
        self.comp = table.column("component").to_numpy()
        texts = table.column("_bytes").to_pylist()
        shingler, self.sets = Shingler(), []
        lo = 0
        while lo < len(texts):  # slices of bounded size
            hi, held = lo, 0
            while hi < len(texts) and (hi == lo or held + len(texts[hi]) <= SLICE_BYTES):
                held += len(texts[hi])
                hi += 1
            owner, shingles, counts = shingler.of(texts[lo:hi])
            weight = GRID ** levels(shingles, counts, idf).astype(np.float64)
            cut = np.searchsorted(owner, np.arange(hi - lo + 1))
            self.sets += [(shingles[cut[i] : cut[i + 1]], weight[cut[i] : cut[i + 1]]) for i in range(hi - lo)]
            lo = hi
        self.threshold, self.top = threshold, {int(c): int(c) for c in self.comp}

    def _root(self, c: int) -> int:
        while self.top[c] != c:
            self.top[c] = self.top[self.top[c]]
            c = self.top[c]
        return c

    def links(self) -> tuple[list[int], list[int]]:
        """Hubs against all texts that share a band with them."""
        us, vs = [], []
        for a in np.flatnonzero(self.hub).tolist():
            for b in np.flatnonzero((self.keys == self.keys[a]).any(axis=1)).tolist():
                if b == a or self.hub[b] and b < a:
                    continue
                x, y = self._root(int(self.comp[a])), self._root(int(self.comp[b]))
                if x != y and similarity(self.sets[a], self.sets[b]) >= self.threshold:
                    self.top[max(x, y)] = min(x, y)
                    us.append(int(self.ids[a]))
                    vs.append(int(self.ids[b]))
        return us, vs


def _compare(rows: DataFrame, by: list[str], weights, threshold: float) -> DataFrame:
    """rows: the columns of by, rep, keys, hub, component, _bytes. Links found in each group, as u, v."""

    def run(table: pa.Table) -> pa.Table:
        us, vs = Compared(table, weights.value, threshold).links()
        return pa.table({"u": pa.array(us, pa.int64()), "v": pa.array(vs, pa.int64())})

    return rows.select(*by, "rep", "keys", "hub", "component", "_bytes").groupBy(*by).applyInArrow(run, "u bigint, v bigint")


def candidate_groups(firsts: DataFrame) -> DataFrame:
    """firsts: rep, keys. (rep, sg, members): texts joined by bands, directly or not; sg is the least of a group."""
    bands = staged(firsts.select("rep", F.posexplode("keys").alias("band", "key")), "bands")
    buckets = bands.groupBy("band", "key").agg(F.min("rep").alias("head"), F.count(F.lit(1)).alias("n")).filter("n > 1").select("band", "key", "head")
    edges = bands.join(buckets, ["band", "key"]).filter("rep <> head").select(F.col("rep").alias("u"), F.col("head").alias("v"))
    groups = staged(linked_components(edges).select(F.col("v").alias("rep"), F.col("component").alias("sg")), "groups")
    return staged(groups.join(groups.groupBy("sg").agg(F.count(F.lit(1)).alias("members")), "sg"), "sized")


def text_links(texts: DataFrame, weights, threshold: float) -> DataFrame:
    """texts: rep, sg, members, keys, _bytes. Links that give the same components as all links of candidates.

    A group that fits a task is compared whole. In a larger one HUBS texts meet all; then each text
    outside the group's main component meets all texts of the group: a pair that was never compared
    is then a pair of the main component, which is joined already.
    """
    alone = texts.withColumn("component", F.col("rep"))
    small = _compare(alone.filter(F.col("members") <= CHUNK).withColumn("hub", F.lit(True)), ["sg"], weights, threshold)

    large = alone.filter(F.col("members") > CHUNK).withColumn("chunks", F.ceil(F.col("members") / CHUNK).cast("int"))
    large = large.withColumn("chunk", F.pmod(F.xxhash64("rep"), F.col("chunks")).cast("int"))
    # the least text of each hashed slot is a hub: HUBS at most, found without gathering the group
    hubs = large.groupBy("sg", F.pmod(F.xxhash64("rep", F.lit(7)), F.lit(HUBS)).alias("slot")).agg(F.min("rep").alias("rep"))
    hubs = staged(hubs.select("rep"), "hubs")
    met = large.join(hubs.withColumn("hub", F.lit(True)), "rep", "left").withColumn("hub", F.coalesce("hub", F.lit(False)))
    met = met.withColumn("chunk", F.explode(F.when(F.col("hub"), F.sequence(F.lit(0), F.col("chunks") - 1)).otherwise(F.array("chunk"))))
    first = staged(small.union(_compare(met, ["sg", "chunk"], weights, threshold)), "links")

    joined = linked_components(first).select(F.col("v").alias("_v"), F.col("component").alias("_c"))
    placed = staged(large.select("rep", "sg", F.octet_length("_bytes").cast("long").alias("size")).join(joined, F.col("rep") == F.col("_v"), "left").select("rep", "sg", "size", F.coalesce("_c", "rep").alias("_c")), "placed")
    parts = placed.groupBy("sg", "_c").agg(F.count(F.lit(1)).alias("n"), F.sum("size").alias("bytes"))
    main = parts.groupBy("sg").agg(F.max(F.struct("n", "_c", "bytes")).alias("_main"), F.sum("n").alias("_all"), F.sum("bytes").alias("_bytes")).filter("_all > _main.n")
    split = staged(main.select("sg", F.col("_main._c").alias("_main"), F.ceil((F.col("_bytes") - F.col("_main.bytes")) / MEET_BYTES).cast("int").alias("blocks")), "split")
    if split.isEmpty():
        return first
    state = staged(placed.join(split, "sg").select("rep", "_c", "_main", F.greatest("blocks", F.lit(1)).alias("blocks"), "size"), "state")
    rows = large.drop("component", "chunk", "chunks").join(state, "rep").withColumn("component", F.col("_c"))
    # texts that share no band with one outside can't meet it, so they aren't dealt again
    touched = rows.filter("_c <> _main").select("sg", F.posexplode("keys").alias("band", "key")).distinct()
    near = rows.select("sg", "rep", "size", F.posexplode("keys").alias("band", "key")).join(touched, ["sg", "band", "key"], "left_semi")
    near = staged(near.select("sg", "rep", "size").distinct(), "near")
    dealt = near.join(near.groupBy("sg").agg(F.greatest(F.ceil(F.sum("size") / MEET_BYTES), F.lit(1)).cast("int").alias("chunks")), "sg").select("rep", "chunks")
    rows = rows.drop("size").join(dealt, "rep").withColumn("chunk", F.pmod(F.xxhash64("rep"), F.col("chunks")).cast("int"))
    outside = rows.filter("_c <> _main").withColumn("block", F.pmod(F.xxhash64("rep", F.lit(3)), F.col("blocks")).cast("int")).withColumn("hub", F.lit(True))
    outside = outside.withColumn("chunk", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)))
    every = rows.withColumn("hub", F.lit(False)).withColumn("block", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    columns = ["sg", "block", "chunk", "rep", "keys", "hub", "component", "_bytes"]
    return first.union(_compare(outside.select(*columns).unionByName(every.select(*columns)), ["sg", "block", "chunk"], weights, threshold))


def near_classes(docs: DataFrame, text: str, threshold: float = THRESHOLD) -> tuple[DataFrame, DataFrame]:
    """A written copy of docs with _row, and (_row, component): texts that are equal or linked, by least row."""
    spark = docs.sparkSession
    body = F.coalesce(F.col(text), F.lit("")).cast("binary")
    weights = spark.sparkContext.broadcast(shingle_weights(docs.select(body.alias("_bytes"))))
    keyed = docs.withColumn("_row", F.monotonically_increasing_id()).withColumn("_sha", F.unhex(F.sha2(body, 256)))
    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in keyed.schema.fields), "_bands array<bigint>"])
    work = staged(keyed.mapInArrow(_signed(weights, text), schema), "signed")

    # equal texts are one class: its least row stands for it; blank texts have no shingle and no class
    solid = work.select("_row", "_sha", F.col("_bands").isNotNull().alias("solid")).filter("solid")
    reps = solid.groupBy("_sha").agg(F.min("_row").alias("rep"), F.count(F.lit(1)).alias("n"))
    shared = staged(reps.filter("n > 1").select("_sha", "rep"), "copies")
    copies = staged(solid.join(shared, "_sha").select("_row", "rep"), "copied")
    firsts = without(work.filter("_bands is not null").select("_row", "_bands"), copies.filter("_row <> rep").select("_row"), "_row")
    firsts = firsts.select(F.col("_row").alias("rep"), F.col("_bands").alias("keys"))
    groups = candidate_groups(firsts)
    texts = flagged(work.select(F.col("_row").alias("rep"), F.col("_bands").alias("keys"), body.alias("_bytes")), "rep", bitmap(groups, "rep")).filter("_maybe").drop("_maybe")
    texts = staged(texts.join(groups, "rep"), "texts")
    found = linked_components(staged(text_links(texts, weights, threshold), "found"))
    whole = staged(found.select("v", "component").union(copies.select(F.col("_row").alias("v"), F.col("rep").alias("component"))), "joined")
    final = linked_components(whole.select(F.col("v").alias("u"), F.col("component").alias("v")))
    return work, staged(final.select(F.col("v").alias("_row"), "component"), "classes")


def near_duplicates(docs: DataFrame, text: str = "text", key: str = "doc_id", threshold: float = THRESHOLD) -> DataFrame:
    """One row per row of docs: doc_id, class_id (the class's least doc_id), class_size, kept.

    Null, empty and blank texts have no shingle and stand alone; texts of fewer than five words are
    one shingle; equal texts are one class. Exactly one row of a class is kept: least id, then first
    read. An empty table gives an empty result; further columns of docs are ignored.
    """
    work, classes = near_classes(docs.select(F.col(key).alias("_key"), F.col(text).alias("_text")), "_text", threshold)
    rows = work.select("_row", "_key").join(classes, "_row", "left").select("_key", "_row", F.coalesce("component", "_row").alias("_class"))
    rows = staged(rows, "rows")
    best = rows.groupBy("_class").agg(F.min(F.struct(F.col("_key").isNull().alias("z"), F.col("_key").alias("id"), F.col("_row").alias("row"))).alias("_best"), F.count(F.lit(1)).alias("class_size"))
    # a table of its own, so that the join's sides are plain shuffles, whose large partitions Spark splits
    return rows.join(staged(best, "best"), "_class").select(F.col("_key").alias("doc_id"), F.col("_best.id").alias("class_id"), "class_size", (F.col("_row") == F.col("_best.row")).alias("kept"))


def one_of_each(docs: DataFrame, text: str = "text", key: str = "doc_id", threshold: float = THRESHOLD) -> DataFrame:
    """docs with one row of each class, all columns as they were."""
    work, classes = near_classes(docs, text, threshold)
    ids = classes.join(work.select("_row", F.col(key).alias("_key")), "_row")
    ids = staged(ids, "ids")
    best = ids.groupBy("component").agg(F.min(F.struct(F.col("_key").isNull().alias("z"), F.col("_key").alias("id"), F.col("_row").alias("row"))).alias("_best"))
    gone = staged(ids.join(staged(best, "best"), "component").filter(F.col("_row") != F.col("_best.row")).select("_row"), "gone")
    return without(work.drop("_sha", "_bands"), gone, "_row").select(*docs.columns)


def op3_weighted_minhash_neardup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(load(spark, sf_dir, "documents"))

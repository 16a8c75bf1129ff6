"""Near-duplicate vectors by sorted projection passes.

In each pass vectors stand in the lexicographic order of their signs on random planes; each is
compared, in double precision, with a bounded window of those before it. How many leading signs a
vector shares with those a window away is measured in each pass, which gives the chance that a pair
at the threshold was missed; vectors in crowds, where it is too large, go through further passes, or
meet all of the crowd in blocks where that costs less. Verified pairs of all passes are united into
components. Within a component links are then counted exactly: at once where
all members lie in a ball so narrow that each pair is linked, else block by block, where blocks are
stretches of the component in the order of a pass, and pairs of blocks too far apart for any link
are left out.

Vectors are carried as the bytes of their components.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sparsecert.kernels.forest import forest_of
from sparsecert.llm.common import load, staged
from sparsecert.plans.relational import linked_components

THRESHOLD = 0.95
BITS = 62
BLOCK = 2048
MISSED = 0.01  # the chance of a miss that a pair right at the threshold may have
CROWD = 2048


def passes_for(rows: int, window: int, threshold: float, missed: float = 0.01) -> int:
    """Passes to begin with: enough where sign prefixes split the table evenly.

    A window then holds the vectors that share about log2(rows / window) leading signs; the angle of
    a pair gives the chance that it does. What the passes reached is measured by _depths.
    """
    agree = 1.0 - math.acos(threshold) / math.pi
    shared = agree ** max(0.0, math.log2(max(rows, 1) / window) + 1)
    return max(4, math.ceil(math.log(missed) / math.log(1.0 - min(shared, 0.999))))


def unit_rows(column: pa.Array, dim: int, single: bool) -> np.ndarray:
    """Vectors of equal length as unit rows of doubles. column: their bytes, of single or double components."""
    flat = np.frombuffer(b"".join(column.to_pylist()), dtype=np.float32 if single else np.float64).astype(np.float64)
    x = flat.reshape(len(column), dim)
    if not single:  # squares of singles fit doubles
        x = x / np.abs(x).max(axis=1, keepdims=True)
    return x / np.sqrt(np.einsum("nd,nd->n", x, x))[:, None]


def _packed(single: bool):
    """row, vec_id, and the bytes of vectors that can link: none that is null, empty, zero or holds what isn't finite."""
    kind = np.float32 if single else np.float64

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            column = batch.column("vector")
            offsets, held = column.offsets.to_numpy().astype(np.int64), column.values
            flat = np.ascontiguousarray(held.fill_null(0).to_numpy(zero_copy_only=False), dtype=kind)
            bad = ~np.isfinite(flat)
            if held.null_count:
                bad |= held.is_null().to_numpy(zero_copy_only=False)
            among = lambda mark, at=offsets: np.diff(np.concatenate([[0], np.cumsum(mark)])[at])
            fine = column.is_valid().to_numpy(zero_copy_only=False) & (among(bad) == 0) & (among(flat != 0) > 0)
            mask = pa.py_buffer(np.packbits(fine, bitorder="little").tobytes())
            out = pa.Array.from_buffers(pa.large_binary(), len(column), [mask, pa.py_buffer(offsets * flat.itemsize), pa.py_buffer(flat)])
            yield pa.RecordBatch.from_arrays([batch.column("row"), batch.column("vec_id"), out.cast(pa.binary())], names=["row", "vec_id", "bytes"])

    return run


def _planes(seed: int, number: int, dim: int) -> np.ndarray:
    return np.random.default_rng([seed, number, dim]).standard_normal((dim, BITS))


_WEIGHTS = 1 << np.arange(BITS - 1, -1, -1, dtype=np.int64)


def _keys(passes: range, seed: int, single: bool):
    """Adds to each vector its place in each pass: a row per pass. Planes are drawn once a task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        drawn: dict[tuple[int, int], np.ndarray] = {}
        for batch in batches:
            dims = batch.column("dim").to_numpy()
            for dim in np.unique(dims).tolist():
                part = batch.filter(pa.array(dims == dim))
                for lo in range(0, part.num_rows, 4096):
                    chunk = part.slice(lo, 4096)
                    x = unit_rows(chunk.column("bytes"), dim, single)
                    for p in passes:
                        if (p, dim) not in drawn:
                            if len(drawn) >= 256:
                                drawn.clear()
                            drawn[p, dim] = _planes(seed, p, dim)
                        key = ((x @ drawn[p, dim]) > 0) @ _WEIGHTS
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(x), p, dtype=np.int32)), pa.array(key), chunk.column("rep"), chunk.column("bytes"), chunk.column("dim")], names=["pass", "key", "rep", "bytes", "dim"])

    return run


def _linked(x: np.ndarray, y: np.ndarray, threshold: float, rough: tuple[np.ndarray, np.ndarray] | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Pairs that reach the threshold in double precision; products of single precision (of `rough`) leave out those far below it."""
    a, b = rough or (x.astype(np.float32), y.astype(np.float32))
    i, j = np.divmod(np.flatnonzero((a @ b.T).ravel() >= np.float32(threshold - 1e-3)), len(y))
    sure = np.concatenate([np.einsum("nd,nd->n", x[i[k : k + 65536]], y[j[k : k + 65536]]) for k in range(0, len(i), 65536)]) >= threshold if len(i) else np.empty(0, bool)
    return i[sure], j[sure]


def _depths(passes: np.ndarray, keys: np.ndarray, here: np.ndarray, window: int, first: bool, last: bool) -> np.ndarray:
    """Leading signs by which rows at these places are sure to meet: more than are shared with the rows a window away on both sides.

    Near an end of the arrays the row there stands for one further away, which can only add signs;
    first and last say that nothing lies beyond the end.
    """
    shared = np.full(len(here), -1, dtype=np.int64)
    for far, known in ((here - window, first), (here + window, last)):
        there = np.clip(far, 0, len(keys) - 1)
        counts = (passes[here] == passes[there]) & (here != there) & ((far == there) | (not known))
        x = keys[here] ^ keys[there]
        high = x >> 31
        length = np.where(high > 0, 31 + np.frexp(high.astype(np.float64))[1], np.frexp((x & 0x7FFFFFFF).astype(np.float64))[1])
        shared = np.maximum(shared, np.where(counts, BITS - length, -1))
    return shared + 1


EDGES = "side int, a bigint, b bigint, bytes binary, dim int"


def _windows(threshold: float, window: int, single: bool, parts: int):
    """Over a sorted partition: side 0 links as a forest; sides 1 and 2 are its last and first rows, for the seams; side 3 each row's depth (_depths)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        at = TaskContext.get().partitionId()
        names = ["side", "a", "b", "bytes", "dim"]
        held: pa.RecordBatch | None = None
        head_left = window
        keys, passes, reps = (np.empty(0, np.int64) for _ in range(3))
        done, start = 0, at == 0  # rows of these arrays whose depth is known; whether they begin where all rows do

        def depths(upto: int, end: bool = False) -> Iterator[pa.RecordBatch]:
            here = np.arange(done, upto)
            if len(here):
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(here), 3, dtype=np.int32)), pa.array(reps[here]), pa.array(_depths(passes, keys, here, window, start, end)), pa.nulls(len(here), pa.binary()), pa.array(np.zeros(len(here), dtype=np.int32))], names=names)

        def rows(side: int, part: pa.RecordBatch, seam: int) -> pa.RecordBatch:
            n = part.num_rows
            return pa.RecordBatch.from_arrays([pa.array(np.full(n, side, dtype=np.int32)), pa.array(np.full(n, seam)), part.column("rep"), part.column("bytes"), part.column("dim")], names=names)

        for batch in batches:
            if not batch.num_rows:
                continue
            if head_left and at:
                yield rows(2, batch.slice(0, head_left), at - 1)
            head_left = max(0, head_left - batch.num_rows)
            both = batch if held is None else pa.Table.from_batches([held, batch]).combine_chunks().to_batches()[0]
            old = both.num_rows - batch.num_rows
            u, v = pairs_within(both, old, window, threshold, single)
            keep = forest_of(u, v) if len(u) else []
            none = pa.nulls(len(keep), pa.binary())
            if len(keep):
                yield pa.RecordBatch.from_arrays([pa.array(np.zeros(len(keep), dtype=np.int32)), pa.array(u[keep]), pa.array(v[keep]), none, pa.array(np.zeros(len(keep), dtype=np.int32))], names=names)
            held = both.slice(max(0, both.num_rows - window))
            keys, passes, reps = (np.concatenate([x, batch.column(c).to_numpy()]) for x, c in ((keys, "key"), (passes, "pass"), (reps, "rep")))
            if (upto := len(keys) - window) > done:
                yield from depths(upto)
                cut = max(0, upto - window)
                keys, passes, reps, done, start = keys[cut:], passes[cut:], reps[cut:], upto - cut, start and not cut
        yield from depths(len(keys), at == parts - 1)
        if held is not None:
            yield rows(1, held, at)

    return run


def pairs_within(rows: pa.RecordBatch, fresh: int, window: int, threshold: float, single: bool) -> tuple[np.ndarray, np.ndarray]:
    """Linked pairs of ids: each row from place `fresh` on against up to `window` rows before it."""
    ids, dims = rows.column("rep").to_numpy(), rows.column("dim").to_numpy()
    us, vs = [], []
    for dim in np.unique(dims):
        at = np.flatnonzero(dims == dim)
        x = unit_rows(rows.column("bytes").take(pa.array(at)), int(dim), single)
        first, rough = int(np.searchsorted(at, fresh)), x.astype(np.float32)
        for lo in range(first, len(at), 128):
            hi, back = min(lo + 128, len(at)), max(0, lo - window)
            i, j = _linked(x[lo:hi], x[back:hi], threshold, (rough[lo:hi], rough[back:hi]))
            i, j = i + lo, j + back
            keep = j < i
            us.append(ids[at[i[keep]]])
            vs.append(ids[at[j[keep]]])
    return (np.concatenate(us), np.concatenate(vs)) if us else (np.empty(0, np.int64), np.empty(0, np.int64))


def _seam(threshold: float, window: int, single: bool):
    """Rows on both sides of a partition's end, at most a window each."""

    def run(table: pa.Table) -> pa.Table:
        batch = table.sort_by("side").combine_chunks().rename_columns(["side", "a", "rep", "bytes", "dim"]).to_batches()[0]
        sides = batch.column("side").to_numpy()
        u, v = pairs_within(batch, int((sides == 1).sum()), 2 * window, threshold, single)
        keep = forest_of(u, v) if len(u) else np.empty(0, np.int64)
        return pa.table({"u": pa.array(u[keep], pa.int64()), "v": pa.array(v[keep], pa.int64())})

    return run


def _met(threshold: float, single: bool):
    """Links between a block of a crowd's rows outside its main component and a block of all its rows, as a forest."""

    def run(table: pa.Table) -> pa.Table:
        batch = table.combine_chunks().to_batches()[0]
        ids, dims, few = batch.column("rep").to_numpy(), batch.column("dim").to_numpy(), batch.column("few").to_numpy(zero_copy_only=False)
        us, vs = [np.empty(0, np.int64)], [np.empty(0, np.int64)]
        for dim in np.unique(dims):
            at = np.flatnonzero(dims == dim)
            x = unit_rows(batch.column("bytes").take(pa.array(at)), int(dim), single)
            a, b = np.flatnonzero(few[at]), np.flatnonzero(~few[at])
            for lo in range(0, len(a), 256):
                i, j = _linked(x[a[lo : lo + 256]], x[b], threshold)
                u, v = ids[at[a[lo + i]]], ids[at[b[j]]]
                us.append(u[u != v])
                vs.append(v[u != v])
            u, v = np.concatenate(us), np.concatenate(vs)
            keep = forest_of(u, v) if len(u) else np.empty(0, np.int64)
            us, vs = [u[keep]], [v[keep]]
        return pa.table({"u": us[0], "v": vs[0]})

    return run


def _sums(single: bool):
    """Sums of unit vectors by group over what a task reads, and how many there are."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple[int, int], np.ndarray] = {}

        def out() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([c for c, _ in held], pa.int64()), pa.array([b for _, b in held], pa.int64()), pa.array([x.tobytes() for x in held.values()], pa.binary())], names=["component", "own", "total"])

        for batch in batches:
            dims, comps, own = (batch.column(c).to_numpy() for c in ("dim", "component", "own"))
            for dim in np.unique(dims).tolist():
                at = np.flatnonzero(dims == dim)
                x = unit_rows(batch.column("bytes").take(pa.array(at)), dim, single)
                order = np.lexsort((own[at], comps[at]))
                names = np.stack([comps[at][order], own[at][order]])
                starts = np.flatnonzero(np.concatenate([[True], (names[:, 1:] != names[:, :-1]).any(axis=0)]))
                for c, o, total in zip(*names[:, starts].tolist(), np.add.reduceat(x[order], starts), strict=True):
                    held[c, o] = held[c, o] + total if (c, o) in held else total
            if len(held) > 4096:
                yield out()
                held.clear()
        if held:
            yield out()

    return run


def whole_groups(batches: Iterator[pa.RecordBatch], keys: list[str]) -> Iterator[pa.RecordBatch]:
    """Batches of a partition sorted by keys, cut so that no group is parted."""
    held: pa.RecordBatch | None = None
    for batch in batches:
        if not batch.num_rows:
            continue
        both = batch if held is None else pa.Table.from_batches([held, batch]).combine_chunks().to_batches()[0]
        last = np.logical_and.reduce([(x := both.column(k).to_numpy()) == x[-1] for k in keys])
        start = int(last.argmax())
        if start:
            yield both.slice(0, start)
        held = both.slice(start)
    if held is not None:
        yield held


def starts_of(batch: pa.RecordBatch, keys: list[str]) -> np.ndarray:
    """Where groups begin, and the end."""
    new = np.logical_or.reduce([(x := batch.column(k).to_numpy())[1:] != x[:-1] for k in keys])
    return np.concatenate([[0], np.flatnonzero(new) + 1, [batch.num_rows]])


def sorted_by(df: DataFrame, *keys: str) -> DataFrame:
    return df.repartition(*keys).sortWithinPartitions(*keys)


def _added(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """One sum a group."""
    keys = ["component", "own"]
    for batch in whole_groups(batches, keys):
        cut = starts_of(batch, keys)
        totals = batch.column("total").to_pylist()
        out = [np.sum([np.frombuffer(x) for x in totals[i:j]], axis=0).tobytes() if j - i > 1 else totals[i] for i, j in zip(cut, cut[1:], strict=False)]
        first = pa.array(cut[:-1])
        yield pa.RecordBatch.from_arrays([batch.column("component").take(first), batch.column("own").take(first), pa.array(out, pa.binary())], names=["component", "own", "centre"])


def _angles(single: bool):
    """The angle between each vector and its group's centre."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            dims = batch.column("dim").to_numpy()
            angle = np.zeros(batch.num_rows)
            for dim in np.unique(dims).tolist():
                at = pa.array(np.flatnonzero(dims == dim))
                x, c = unit_rows(batch.column("bytes").take(at), dim, single), unit_rows(batch.column("centre").take(at), dim, False)
                angle[at.to_numpy()] = np.arccos(np.clip((x * c).sum(axis=1), -1, 1))
            yield pa.RecordBatch.from_arrays([batch.column("component"), batch.column("own"), pa.array(angle)], names=["component", "own", "angle"])

    return run


def _balls(groups: DataFrame, single: bool) -> DataFrame:
    """groups: component, own, bytes, dim. (component, own, centre, radius): the least ball around the mean that holds a group."""
    sums = groups.select("component", "own", "bytes", "dim").mapInArrow(_sums(single), "component bigint, own bigint, total binary")
    centres = staged(sorted_by(sums, "component", "own").mapInArrow(_added, "component bigint, own bigint, centre binary"), "centres")
    angles = groups.select("component", "own", "bytes", "dim").join(centres, ["component", "own"]).mapInArrow(_angles(single), "component bigint, own bigint, angle double")
    return centres.join(angles.groupBy("component", "own").agg(F.max("angle").alias("radius")), ["component", "own"])


def _near_blocks(threshold: float):
    """Pairs of a component's blocks, low <= high, that may hold a link: the gap between their balls is no wider than the threshold's angle."""
    widest = math.acos(threshold) + 1e-6

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        a, b = (np.stack([np.frombuffer(c) for c in t.column("centre").to_pylist()]) for t in (left, right))
        a, b = (x / np.linalg.norm(x, axis=1, keepdims=True) for x in (a, b))
        gap = np.arccos(np.clip(a @ b.T, -1, 1)) - left.column("radius").to_numpy()[:, None] - right.column("radius").to_numpy()[None]
        low, high = left.column("own").to_numpy(), right.column("own").to_numpy()
        # a mean near zero has no direction worth the name: such blocks meet all
        far = (gap > widest) & np.isfinite(gap)
        i, j = np.nonzero(~far & (low[:, None] <= high[None]))
        return pa.table({"component": pa.array(np.full(len(i), left.column("component")[0].as_py())), "low": pa.array(low[i]), "high": pa.array(high[j])})

    return run


def _inside(threshold: float, single: bool):
    """Links inside small components, counted by the product of all of a component's vectors."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in whole_groups(batches, ["component"]):
            cut, dims, n, data = starts_of(batch, ["component"]), batch.column("dim").to_numpy(), batch.column("n").to_numpy(), batch.column("bytes")
            out = np.zeros(batch.num_rows, dtype=np.int64)
            for i, j in zip(cut.tolist(), cut[1:].tolist(), strict=False):
                x = unit_rows(data.slice(i, j - i), int(dims[i]), single)
                hit = x @ x.T >= threshold
                np.fill_diagonal(hit, False)
                out[i:j] = hit @ n[i:j]
            yield pa.RecordBatch.from_arrays([batch.column("rep"), pa.array(out)], names=["rep", "links"])

    return run


def _counted(threshold: float, single: bool):
    """Links between two blocks of a component (or within one), by vector."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys = ["component", "low", "high"]
        for many in whole_groups(batches, keys):
            cut = starts_of(many, keys)
            for i, j in zip(cut.tolist(), cut[1:].tolist(), strict=False):
                batch = many.slice(i, j - i)
                x, n, mine = unit_rows(batch.column("bytes"), int(batch.column("dim")[0].as_py()), single), batch.column("n").to_numpy(), batch.column("own").to_numpy()
                low, high = batch.column("low")[0].as_py(), batch.column("high")[0].as_py()
                out = np.zeros(len(x), dtype=np.int64)
                a, b = np.flatnonzero(mine == low), np.flatnonzero(mine == high)
                for lo in range(0, len(a), 512):
                    part = a[lo : lo + 512]
                    hit = x[part] @ x[b].T >= threshold
                    if low == high:
                        hit[np.arange(len(part)), np.arange(lo, lo + len(part))] = False
                    out[part] += hit @ n[b]
                    if low != high:
                        out[b] += n[part] @ hit
                yield pa.RecordBatch.from_arrays([batch.column("rep"), pa.array(out)], names=["rep", "links"])

    return run


def _crowd_links(crowd: DataFrame, main: int, members: int, few: int, threshold: float, single: bool) -> DataFrame:
    """Exact links of a crowd's rows outside its main component with all of the crowd, by pairs of blocks."""
    here, there = max(1, -(-few // CROWD)), max(1, -(-members // CROWD))
    block = lambda n: F.pmod(F.xxhash64("rep"), F.lit(n)).cast("int")
    columns = ("rep", "bytes", "dim")
    a = crowd.filter(F.col("component") != main).select(*columns, F.lit(True).alias("few"), block(here).alias("i"), F.explode(F.sequence(F.lit(0), F.lit(there - 1))).alias("j"))
    b = crowd.select(*columns, F.lit(False).alias("few"), F.explode(F.sequence(F.lit(0), F.lit(here - 1))).alias("i"), block(there).alias("j"))
    return a.union(b).groupBy("i", "j").applyInArrow(_met(threshold, single), "u bigint, v bigint")


def _loose_links(loose: DataFrame, threshold: float, single: bool) -> DataFrame:
    """loose: component, members, key, rep, n, bytes, dim. (rep, links): links inside components, counted exactly.

    A component's blocks are stretches of its vectors in the order of a pass's key, so that a block's
    vectors lie near each other; of a component's pairs of blocks only those meet whose balls do.
    """
    # stretches of equal size by range, whatever the components; a component has at most members / BLOCK + 2 of them
    parts = max(1, -(-loose.count() // BLOCK))
    placed = loose.repartitionByRange(parts, "component", "key", "rep").withColumn("own", F.spark_partition_id().cast("long"))
    placed = staged(placed, "blocks")
    balls = staged(_balls(placed, single), "balls")
    # rows of balls are few: a component of M vectors has M / BLOCK of them; they meet in strips of 256
    strips = balls.withColumn("strip", F.floor(F.col("own") / 256))
    spans = strips.groupBy("component").agg(F.min("strip").alias("from"), F.max("strip").alias("to"))
    left = strips.join(spans, "component").withColumn("other", F.explode(F.sequence("strip", "to"))).select("component", "strip", "other", "own", "centre", "radius")
    right = strips.join(spans, "component").withColumn("other", F.col("strip")).withColumn("strip", F.explode(F.sequence("from", "other")))
    right = right.select(*[F.col(c).alias(c) for c in left.columns])  # columns of its own: both sides come of one table
    by = ["component", "strip", "other"]
    met = staged(left.groupBy(*by).cogroup(right.groupBy(*by)).applyInArrow(_near_blocks(threshold), "component bigint, low bigint, high bigint"), "met")
    both = met.select("component", "low", "high", F.explode(F.array_distinct(F.array("low", "high"))).alias("own"))
    dealt = placed.select("component", "own", "rep", "n", "bytes", "dim").join(both, ["component", "own"])
    return sorted_by(dealt, "component", "low", "high").mapInArrow(_counted(threshold, single), "rep bigint, links bigint").groupBy("rep").agg(F.sum("links").alias("links"))


def link_vectors(rows: DataFrame, key: str = "vec_id", column: str = "embedding", threshold: float = THRESHOLD, window: int = 512, passes: int | None = None, seed: int = 11) -> DataFrame:
    """One row per row: vec_id, n_links, component_id, kept.

    Vectors that are null, empty, zero, or hold null or non-finite components link with nothing;
    vectors of different length link with none of another length; equal vectors are one class and
    compared once. Passes go on until each row's measured depths leave a chance of MISSED at most. Rows with a null id take part; a component's id is its least id that isn't null.
    An empty table gives an empty result; further columns are ignored.
    """
    single = rows.schema[column].dataType.elementType.simpleString() == "float"
    kind = rows.schema[key].dataType.simpleString()
    named = rows.select(F.col(key).alias("vec_id"), F.col(column).alias("vector")).withColumn("row", F.monotonically_increasing_id())
    work = staged(named.select("row", "vec_id", "vector").mapInArrow(_packed(single), f"row bigint, vec_id {kind}, bytes binary").withColumn("sha", F.unhex(F.sha2("bytes", 256))), "vectors")
    fine = work.filter("bytes is not null")
    # rows of equal vectors, told by their digest; the least row stands for them
    shared = staged(fine.groupBy("sha").agg(F.min("row").alias("rep"), F.count(F.lit(1)).alias("n")).filter("n > 1"), "shared")
    copies = staged(fine.select("row", "sha").join(shared, "sha").select("row", "rep", "n"), "copies")
    dim = (F.octet_length("bytes") / (4 if single else 8)).cast("int").alias("dim")
    classes = fine.select(F.col("row").alias("rep"), "bytes", dim).join(copies.filter("row <> rep").select(F.col("row").alias("rep")), "rep", "left_anti")
    sizes = copies.filter("row = rep").select("rep", "n")
    count = classes.count()
    agree = 1.0 - math.acos(threshold) / math.pi
    enough = -math.log(MISSED)

    def passed(some: DataFrame, rows_: int, which: range) -> tuple[DataFrame, DataFrame]:
        """Links that passes find, and by row what they add to -log of the chance that a pair at the threshold is missed."""
        parts = max(1, -(-rows_ * len(which) // 16384))
        dealt = some.select("rep", "bytes", "dim").mapInArrow(_keys(which, seed, single), "pass int, key bigint, rep bigint, bytes binary, dim int")
        sorted_ = dealt.repartitionByRange(parts, "pass", "key", "rep").sortWithinPartitions("pass", "key", "rep")
        found = staged(sorted_.mapInArrow(_windows(threshold, window, single, parts), EDGES), "windows")
        seams = found.filter("side in (1, 2)").groupBy("a").applyInArrow(_seam(threshold, window, single), "u bigint, v bigint")
        edges = staged(found.filter("side = 0").select(F.col("a").alias("u"), F.col("b").alias("v")).union(seams), "links")
        gain = -F.log1p(-F.least(F.pow(F.lit(agree), F.col("b")), F.lit(0.999)))
        return edges, found.filter("side = 3").groupBy(F.col("a").alias("rep")).agg(F.sum(gain).alias("gain"), F.count(F.lit(1)).alias("tried"))

    upto = passes or passes_for(count, window, threshold, MISSED)
    edges, gains = passed(classes, count, range(upto))
    gains = staged(gains, "gains")
    while True:
        comps = staged(linked_components(edges).select(F.col("v").alias("rep"), "component"), "components")
        # rows whose pairs may have been missed, with where they stand now
        crowd = staged(gains.filter(F.col("gain") < enough).join(comps, "rep", "left").withColumn("component", F.coalesce("component", "rep")), "crowd")
        main = crowd.groupBy("component").agg(F.count(F.lit(1)).alias("members")).agg(F.max_by("component", F.struct("members", "component")).alias("component"), F.sum("members").alias("members"), F.max("members").alias("most")).first()
        if main.members is None or main.members == main.most:
            break  # pairs that may be missed lie inside one component, where all links are counted
        few = main.members - main.most
        whole = classes.join(crowd, "rep")
        more = int(crowd.agg(F.percentile_approx(F.ceil((F.lit(enough) - F.col("gain")) / (F.col("gain") / F.col("tried"))), 0.5)).first()[0])
        if few <= 2 * window * more:
            edges = staged(edges.union(_crowd_links(whole, main.component, main.members, few, threshold, single)), "links")
            comps = staged(linked_components(edges).select(F.col("v").alias("rep"), "component"), "components")
            break
        found, added = passed(whole, main.members, range(upto, upto + more))
        upto += more
        edges = edges.union(found)
        added = added.withColumnRenamed("gain", "more").withColumnRenamed("tried", "again")
        gains = staged(crowd.select("rep", "gain", "tried").join(added, "rep").select("rep", (F.col("gain") + F.col("more")).alias("gain"), (F.col("tried") + F.col("again")).alias("tried")), "gains")

    sized = staged(comps.join(sizes, "rep", "left").withColumn("n", F.coalesce("n", F.lit(1).cast("long"))), "sized")
    grouped = classes.join(sized, "rep")
    size = sized.groupBy("component").agg(F.count(F.lit(1)).alias("members"), F.sum("n").alias("weight"))
    size = staged(size, "sizes")
    small = sorted_by(grouped.join(size.filter(F.col("members") <= BLOCK).select("component"), "component").select("component", "rep", "n", "bytes", "dim"), "component")
    counted = small.mapInArrow(_inside(threshold, single), "rep bigint, links bigint")
    if (wide := size.filter(F.col("members") > BLOCK)).isEmpty():
        size = size.withColumn("tight", F.lit(False))
    else:
        # all within half the threshold's angle of one point: each pair is linked; a margin keeps rounding out
        half = math.acos(threshold) / 2 - 1e-9
        large = staged(grouped.join(wide.select("component", "members"), "component"), "large")
        tight = staged(_balls(large.withColumn("own", F.lit(0).cast("long")), single).select("component", (F.col("radius") <= half).alias("tight")), "tight")
        keyed = large.join(tight.filter("not tight").select("component"), "component")
        keyed = keyed.join(keyed.select("rep", "bytes", "dim").mapInArrow(_keys(range(1), seed, single), "pass int, key bigint, rep bigint, bytes binary, dim int").select("rep", "key"), "rep")
        counted = counted.unionByName(_loose_links(staged(keyed, "loose"), threshold, single))
        size = size.join(tight, "component", "left").withColumn("tight", F.coalesce("tight", F.lit(False)))

    by_class = sized.join(size.select("component", "weight", "tight"), "component").join(counted, "rep", "left")
    by_class = by_class.select(F.col("rep").alias("_rep"), "component", F.when(F.col("tight"), F.col("weight") - F.col("n")).otherwise(F.coalesce("links", F.lit(0))).alias("others"))
    placed = work.select("row", "vec_id").join(copies, "row", "left").withColumn("rep", F.coalesce("rep", "row")).join(by_class, F.col("rep") == F.col("_rep"), "left")
    placed = staged(placed.select("vec_id", (F.coalesce("others", F.lit(0)) + F.coalesce(F.col("n") - 1, F.lit(0))).cast("long").alias("n_links"), F.coalesce("component", "rep").alias("group")), "placed")
    least = placed.groupBy("group").agg(F.min("vec_id").alias("component_id"))
    out = placed.join(least, "group")
    return out.select("vec_id", "n_links", "component_id", F.col("vec_id").eqNullSafe(F.col("component_id")).alias("kept"))


def op4_sorted_projection_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return link_vectors(load(spark, sf_dir, "embeddings"))


#: All pairs by brute force, then components by keyed recursion.
OP4_SQL = """
WITH RECURSIVE f AS MATERIALIZED (
  SELECT vec_id, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS x FROM embeddings
  WHERE len(embedding) > 0 AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND len(list_filter(embedding, lambda x: x <> 0)) > 0
), e AS MATERIALIZED (
  SELECT a.vec_id AS u, b.vec_id AS v FROM f a JOIN f b ON a.vec_id <> b.vec_id AND len(a.x) = len(b.x) WHERE list_cosine_similarity(a.x, b.x) >= 0.95
), cc(v, c) USING KEY (v) AS (
  SELECT vec_id, vec_id FROM embeddings
  UNION
  (SELECT e.v, min(f.c) FROM cc f JOIN e ON e.u = f.v JOIN recurring.cc r ON r.v = e.v WHERE f.c < r.c GROUP BY e.v)
), n AS (
  SELECT u, count(*) AS links FROM e GROUP BY u
)
SELECT cc.v AS vec_id, CAST(coalesce(n.links, 0) AS BIGINT) AS n_links, cc.c AS component_id, cc.v = cc.c AS kept FROM cc LEFT JOIN n ON n.u = cc.v
"""

"""Certificates in batch: each task folds what it reads, and small certificates meet in a tree.

A task's result is no larger than its certificate, so what is shuffled doesn't grow with the edges
but with the vertices a task has seen. Where a task sees nearly as many vertices as edges nothing
shrinks; `grid_sparsify` then deals edges by blocks of vertex pairs first.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsecert.kernels.certs import Edges
from sparsecert.kernels.fold import Fold, GroupPolicy, Property, of
from sparsecert.plans.relational import cut, relational_bipartite_cert, relational_edge_cert, relational_min_forest, relational_vertex_cert

CERT = "u bigint, v bigint, w bigint, eid bigint"
MEASURES = "part bigint, group_id bigint, edges_in bigint, cert_before bigint, merged bigint, cert_after bigint, update_ns bigint, peak_edges bigint, edges_read bigint"
FAN_IN = 8


def clean(edges: DataFrame, on_loop: str = "drop") -> DataFrame:
    """u, v, w, eid of rows that a kernel may see. Loops are dropped, refused ("fail"), or kept as marks
    of their vertex ("mark", where an edge with one end missing marks the other); negative weights,
    flagged deletions and missing ends are errors or left to `rejected`."""
    out = edges
    if "op" in out.columns:
        out = out.filter(F.when(F.col("op") == "I", F.lit(True)).otherwise(F.raise_error(F.lit("only insertions are allowed in an edge stream"))))
    weight = F.coalesce(F.col("w").cast("long"), F.lit(0)) if "w" in out.columns else F.lit(0).cast("long")
    weight = F.when(weight < 0, F.raise_error(F.lit("a weight is negative"))).otherwise(weight).cast("long")
    eid = F.col("eid").cast("long") if "eid" in out.columns else F.xxhash64(*out.columns)
    out = out.select(F.col("u").cast("long").alias("u"), F.col("v").cast("long").alias("v"), weight.alias("w"), F.coalesce(eid, F.lit(0)).alias("eid"))
    if on_loop == "mark":
        return out.filter("u is not null or v is not null").select(F.coalesce("u", "v").alias("u"), F.coalesce("v", "u").alias("v"), "w", "eid")
    out = out.filter("u is not null and v is not null")
    if on_loop == "fail":
        return out.filter(F.when(F.col("u") == F.col("v"), F.raise_error(F.lit("an edge is a loop"))).otherwise(F.lit(True)))
    return out.filter("u <> v")


def rejected(edges: DataFrame) -> DataFrame:
    """Rows that clean leaves out, with the reason."""
    reason = F.when(F.col("u").isNull() | F.col("v").isNull(), F.lit("an end is missing")).when(F.col("u") == F.col("v"), F.lit("loop"))
    return edges.withColumn("reason", reason).filter("reason is not null")


def as_edges(batch: pa.RecordBatch) -> Edges:
    return Edges(*(batch.column(c).to_numpy(zero_copy_only=False) for c in ("u", "v", "w", "eid")))


def as_batch(e: Edges) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(getattr(e, c), pa.int64()) for c in ("u", "v", "w", "eid")], names=["u", "v", "w", "eid"])


class Marks:
    """Vertices that loops mark: those that no edge of the certificate ends in are told as loops again."""

    def __init__(self) -> None:
        self.parts: list[np.ndarray] = []
        self.count = self.limit = 0

    def taken(self, e: Edges) -> Edges:
        """The edges without the loops."""
        loop = e.u == e.v
        if not loop.any():
            return e
        self.parts.append(e.u[loop])
        self.count += len(self.parts[-1])
        if self.count > max(1 << 16, 2 * self.limit):
            self.parts = [np.unique(np.concatenate(self.parts))]
            self.count = self.limit = len(self.parts[0])
        return e.take(~loop)

    def beside(self, cert: Edges) -> Edges:
        if not self.parts:
            return cert
        alone = np.setdiff1d(np.concatenate(self.parts), np.concatenate([cert.u, cert.v]))
        return Edges.join(cert, Edges(alone, alone, np.zeros(len(alone), np.int64), np.full(len(alone), -1)))


def local_certs(edges: DataFrame, prop: Property, policy: GroupPolicy, n: int | None = None, resolve: bool | None = None, overlap: bool = False) -> DataFrame:
    """One certificate per task, by groups in the order of arrival; no shuffle.

    A vertex that only loops end in goes on as one loop, so that all vertices arrive with the certificate.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fold, marks = Fold(prop, policy, n, overlap), Marks()
        for batch in batches:
            fold.add(marks.taken(as_edges(batch)))
        cert = marks.beside(fold.finish(resolve))
        if len(cert):
            yield as_batch(cert)

    return edges.select("u", "v", "w", "eid").mapInArrow(run, CERT)


def measured(edges: DataFrame, prop: Property, policy: GroupPolicy, n: int | None = None, order: str | None = "seq") -> DataFrame:
    """The counters of each group. With an order, one task reads all edges in it: a stream as it arrives."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        fold = Fold(prop, policy, n)
        for batch in batches:
            fold.add(as_edges(batch))
        fold.finish()
        rows = [{"part": TaskContext.get().partitionId(), "group_id": i, **g, "peak_edges": fold.peak, "edges_read": fold.edges_read} for i, g in enumerate(fold.groups)]
        if rows:
            yield pa.RecordBatch.from_pylist(rows, schema=pa.schema([(c.split()[0], pa.int64()) for c in MEASURES.split(", ")]))

    whole = edges.repartition(1).sortWithinPartitions(order) if order else edges
    return whole.select("u", "v", "w", "eid").mapInArrow(run, MEASURES)


UNKNOWN = 1 << 60  # Spark's word for a size it doesn't know is beyond this


def leaf_sizes(df: DataFrame) -> list[tuple[int, int]]:
    """(bytes, tasks) of the plan's leaves, as Spark knows them before running: a table's files and
    their splits, or the partitions of a checkpoint, whose bytes are unknown."""
    session = df.sparkSession
    split = int(session._jsparkSession.sessionState().conf().filesMaxPartitionBytes())
    leaves, out = df._jdf.queryExecution().optimizedPlan().collectLeaves(), []
    for i in range(leaves.size()):
        leaf = leaves.apply(i)
        size = int(leaf.stats().sizeInBytes())
        if leaf.getClass().getSimpleName() == "LogicalRDD":
            out.append((UNKNOWN, int(leaf.rdd().getNumPartitions())))
        else:
            out.append((size, 1 if size >= UNKNOWN else -(-size // split)))
    return out


def map_tasks(df: DataFrame) -> int:
    """At most so many tasks bring certificates: splits of what is read, or the shuffle's partitions."""
    session = df.sparkSession
    return max(int(session.conf.get("spark.sql.shuffle.partitions")), session.sparkContext.defaultParallelism, sum(tasks for _, tasks in leaf_sizes(df)))


def tree_widths(tasks: int, fan_in: int = FAN_IN) -> list[int]:
    """How many tasks each level of a merge tree has; none merges more than fan_in of the level before."""
    out = [-(-tasks // fan_in)]
    while out[-1] > 1:
        out.append(-(-out[-1] // fan_in))
    return out


def merge_tree(certs: DataFrame, prop: Property, tasks: int, fan_in: int = FAN_IN) -> DataFrame:
    """Unites the certificates of so many tasks, fan_in at a time, until one is left."""
    for width in tree_widths(tasks, fan_in):
        certs = certs.withColumn("_p", F.spark_partition_id() % width).repartition(width, "_p").drop("_p") if width > 1 else certs.repartition(1)
        certs = local_certs(certs, prop, GroupPolicy.whole(), resolve=True)
    return certs


def certs_by_key(edges: DataFrame, key: str, prop: Property, most_held: int = 4_000_000) -> DataFrame:
    """(key, u, v, w, eid): a certificate for each key. Tasks certify what they read before anything is
    shuffled, so a key with most of the edges sends certificates and not edges; these meet in a tree."""
    kind = edges.schema[key].dataType.simpleString()
    schema = f"`{key}` {kind}, {CERT}"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[object, list[Edges]] = {}
        count = 0

        def solved() -> int:
            for name, parts in held.items():
                e = Edges.join(*parts)
                held[name] = [e.take(prop.keep(e))]
            return sum(len(x[0]) for x in held.values())

        def out() -> Iterator[pa.RecordBatch]:
            for name, (e,) in held.items():
                yield pa.RecordBatch.from_arrays([pa.array([name] * len(e), typed), *as_batch(e).columns], names=[key, "u", "v", "w", "eid"])

        for batch in batches:
            typed = batch.schema.field(key).type
            coded = batch.column(key).dictionary_encode()
            codes = coded.indices.fill_null(len(coded.dictionary)).to_numpy(zero_copy_only=False)
            names, e = [*coded.dictionary.to_pylist(), None], as_edges(batch)
            order = np.argsort(codes, kind="stable")
            cuts = np.flatnonzero(np.diff(codes[order])) + 1
            for at in np.split(order, cuts) if len(order) else ():
                held.setdefault(names[codes[at[0]]], []).append(e.take(at))
            count += len(e)
            if count > most_held:
                count = solved()
                if count > most_held // 2:
                    yield from out()
                    held, count = {}, 0
        if held:
            solved()
            yield from out()

    def met(table: pa.Table) -> pa.Table:
        e = Edges.join(*[as_edges(b) for b in table.combine_chunks().to_batches()])
        kept = e.take(prop.keep(e))
        return pa.Table.from_arrays([pa.array([table.column(key)[0].as_py()] * len(kept), table.schema.field(key).type), *as_batch(kept).columns], names=[key, "u", "v", "w", "eid"])

    certs = edges.select(key, "u", "v", "w", "eid").mapInArrow(run, schema)
    for width in tree_widths(map_tasks(edges)):
        by = [key, "_p"] if width > 1 else [key]
        certs = certs.withColumn("_p", F.spark_partition_id() % width).groupBy(*by).applyInArrow(lambda table: met(table), schema)
    return certs


@dataclass(frozen=True)
class Cert:
    """A certificate: its edges, and what it certifies."""

    edges: DataFrame
    prop: Property

    def resparsify(self) -> Cert:
        """A certificate of the certificate, which stands for the same graph."""
        return replace(self, edges=local_certs(self.edges.repartition(1), self.prop, GroupPolicy.whole(), resolve=True))

    def union(self, other: Cert) -> Cert:
        return replace(self, edges=local_certs(self.edges.union(other.edges).repartition(1), self.prop, GroupPolicy.whole(), resolve=True))

    def size_bound_ok(self, n: int) -> bool:
        return self.edges.count() <= max(0, self.prop.bound(n))

    def save(self, path: str, block: str | None = None) -> None:
        (self.edges.write.partitionBy(block) if block else self.edges.write).parquet(path)


@dataclass(frozen=True)
class CertEngine:
    """Group-wise certificates of a graph in any number of tasks."""

    prop: Property
    policy: GroupPolicy | None = None
    fan_in: int = FAN_IN

    def run(self, edges: DataFrame, n: int | None = None, parts: int | None = None, tier: str | None = None, marks: bool = False, overlap: bool = False) -> Cert:
        """tier: merge_tree, grid or relational; what the planner says if None. marks: vertices that no edge
        of the certificate ends in come with it, as loops, so that no second pass has to find them."""
        policy = self.policy or (GroupPolicy.nlogn() if self.prop.name in ("min_forest", "max_forest") else GroupPolicy.adaptive())
        ready = clean(edges, "mark" if marks else "drop")
        plan = Plan(tier, 4, "as asked") if tier else planned(ready, self.prop.k)
        if plan.tier == "relational":
            return Cert(_by_joins(ready, self.prop), self.prop)
        if plan.tier == "grid":
            return Cert(grid_sparsify(ready, self.prop, plan.grid, policy, is_clean=True), self.prop)
        if parts:
            ready = ready.repartition(parts)
        local = local_certs(ready, self.prop, policy, n, resolve=True, overlap=overlap)
        return Cert(merge_tree(local, self.prop, parts or map_tasks(edges), self.fan_in), self.prop)


def _by_joins(ready: DataFrame, prop: Property) -> DataFrame:
    """A certificate found by joins, with the marks of ready as loops beside it."""
    edges = cut(ready.filter("u <> v"))
    if prop.name == "vertex":
        found = relational_vertex_cert(edges, prop.k)
    elif prop.name in ("bipartite", "bipartite_each"):
        found = relational_bipartite_cert(edges, prop.name == "bipartite_each")
    elif prop.name == "min_forest":
        found = relational_min_forest(edges)
    elif prop.name == "max_forest":
        found = relational_min_forest(edges.withColumn("w", -F.col("w"))).withColumn("w", -F.col("w"))
    else:
        found = relational_edge_cert(edges, prop.k)
    marks = ready.filter("u = v").select("u", "v", F.lit(0).cast("long").alias("w"), F.lit(-1).cast("long").alias("eid")).distinct()
    return found.select("u", "v", "w", "eid").union(marks)


def merge_certs(a: Cert, b: Cert) -> Cert:
    return a.union(b)


def grid_sparsify(edges: DataFrame, prop: Property, p: int, policy: GroupPolicy | None = None, is_clean: bool = False) -> DataFrame:
    """Deals edges to blocks (hash of u, hash of v) of p x p, certifies each, then coarsens p until one block is left.

    A block sees about 2n / p vertices but m / p^2 edges, so it shrinks where a random split wouldn't.
    """
    certs = edges if is_clean else clean(edges)
    policy = policy or GroupPolicy.adaptive()
    while p >= 1:
        side = lambda c: F.pmod(F.xxhash64(F.col(c)), F.lit(p))  # noqa: B023, E731
        block = F.least(side("u"), side("v")) * p + F.greatest(side("u"), side("v"))
        certs = cut(local_certs(certs.repartition(min(p * (p + 1) // 2, 4096), block), prop, policy, resolve=True))
        if p == 1:
            break
        p = max(1, p // 10)
    return certs


@dataclass(frozen=True)
class Plan:
    """What the planner chose, and why."""

    tier: str
    grid: int
    reason: str


def choose(n: int, m: int, k: int = 1, edge_bytes: int = 24, task_bytes: int = 2 << 30, split_edges: int = 33_000_000) -> Plan:
    """One task holds a certificate of up to task_bytes; a grid is needed where a split hardly repeats vertices."""
    size = edge_bytes * k * max(n, 1)
    tasks = max(1, m // split_edges)
    dense = m / max(1, tasks) > 4 * k * min(n, 2 * split_edges)
    if size <= task_bytes:
        return Plan("merge_tree", 1, f"a certificate of at most {size} bytes fits one task") if dense or tasks == 1 else Plan("grid", max(2, int((size / task_bytes * 16) ** 0.5) + 1), "a random split has nearly as many vertices as edges")
    return Plan("relational", 10 if m > 100 * n else 1, f"a certificate of up to {size} bytes is beyond one task")


def planned(edges: DataFrame, k: int = 1, task_bytes: int = 2 << 30, edge_bytes: int = 24) -> Plan:
    """The planner on a graph as it stands.

    A vertex takes 4 bytes of the input at least; where a certificate on so many vertices fits one
    task, nothing is read to decide. Else a sketch of the ends counts vertices in one more pass.
    """
    if edge_bytes * k * (sum(size for size, _ in leaf_sizes(edges)) // 4) <= task_bytes:
        return Plan("merge_tree", 1, "a certificate on as many vertices as the input can hold fits one task")
    row = edges.select(F.explode(F.array("u", "v")).alias("v")).agg(F.approx_count_distinct("v", 0.02).alias("n"), (F.count(F.lit(1)) / 2).cast("long").alias("m")).first()
    return choose(row.n, row.m, k, edge_bytes, task_bytes)


def cert_of(edges: DataFrame, name: str, k: int = 1, policy: GroupPolicy | None = None, n: int | None = None, parts: int | None = None, tier: str | None = None, marks: bool = False, overlap: bool = False, **options) -> Cert:
    return CertEngine(of(name, k, **options), policy).run(edges, n, parts, tier, marks, overlap)


def one_task(df: DataFrame, kernel, schema: str) -> DataFrame:
    """Runs kernel(Edges) -> RecordBatch over a whole certificate in one task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = [as_edges(b) for b in batches]
        yield kernel(Edges.join(*parts) if parts else Edges.empty())

    return df.select("u", "v", "w", "eid").repartition(1).mapInArrow(run, schema)


def column(values, kind=np.int64) -> pa.Array:
    return pa.array(np.asarray(values, dtype=kind))

"""The methods on graphs as DataFrames: components, sides, connectivity, minimum forests.

Each takes edges (u, v, and w and eid where weights matter) and optionally all vertices (v). A
certificate is built by groups in all tasks, united in a tree, and asked in one task.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsecert.kernels import answers, cores
from sparsecert.kernels.certs import Edges, sides
from sparsecert.kernels.fold import Fold, GroupPolicy, of
from sparsecert.kernels.forest import compact, forest, labels_of
from sparsecert.plans.batch import Cert, as_batch, as_edges, cert_of, certs_by_key, clean, column, one_task, planned
from sparsecert.plans.relational import cut, relational_components, relational_sides

VERDICT = "property string, k int, holds boolean, witness array<bigint>"


def all_vertices(edges: DataFrame, vertices: DataFrame | None = None) -> DataFrame:
    """Ends of edges (loops and all), and the given vertices."""
    ends = edges.select(F.explode(F.array("u", "v")).alias("v")).filter("v is not null")
    return (ends.union(vertices.select("v")) if vertices is not None else ends).distinct()


def spanning_forest(edges: DataFrame, policy: GroupPolicy | None = None, **options) -> Cert:
    return cert_of(edges, "components", policy=policy, **options)


def _with_given(found: DataFrame, vertices: DataFrame | None) -> DataFrame:
    """found (v, ...) with rows for the given vertices it lacks; what is known of these is null."""
    if vertices is None:
        return found
    return found.join(vertices.select("v").filter("v is not null").distinct(), "v", "full")


def components(edges: DataFrame, vertices: DataFrame | None = None, tier: str | None = None, **options) -> DataFrame:
    """(v, component): the least vertex reachable; isolated vertices are their own.

    One pass: vertices that only loops or half-edges name come with the certificate. tier: see
    CertEngine.run; the relational one labels by joins, and no task holds all vertices.
    """
    tier = tier or planned(edges).tier
    if tier == "relational":
        ready = clean(edges, "mark")
        found = relational_components(ready.filter("u <> v"))
        found = found.join(ready.filter("u = v").select(F.col("u").alias("v")).distinct(), "v", "full")
    else:

        def kernel(e: Edges) -> pa.RecordBatch:
            ids, label = labels_of(e.u, e.v)
            return pa.RecordBatch.from_arrays([column(ids), column(label)], names=["v", "component"])

        found = one_task(spanning_forest(edges, tier=tier, marks=True, **options).edges, kernel, "v bigint, component bigint")
    return _with_given(found, vertices).select("v", F.coalesce("component", "v").alias("component"))


def component_sizes(edges: DataFrame, vertices: DataFrame | None = None, **options) -> DataFrame:
    return components(edges, vertices, **options).groupBy("component").agg(F.count(F.lit(1)).alias("members"))


def is_connected(edges: DataFrame, vertices: DataFrame | None = None, **options) -> DataFrame:
    """One row: connected, and how many components and vertices there are."""
    sizes = component_sizes(edges, vertices, **options)
    return sizes.agg(F.count(F.lit(1)).alias("components"), F.coalesce(F.sum("members"), F.lit(0)).alias("vertices")).select((F.col("components") <= 1).alias("connected"), "components", "vertices")


def same_component(edges: DataFrame, pairs: DataFrame, vertices: DataFrame | None = None, **options) -> DataFrame:
    """pairs: x, y. Adds same."""
    labels = components(edges, vertices, **options)
    x, y = labels.select(F.col("v").alias("x"), F.col("component").alias("_cx")), labels.select(F.col("v").alias("y"), F.col("component").alias("_cy"))
    return pairs.join(x, "x", "left").join(y, "y", "left").select("x", "y", F.coalesce(F.col("_cx") == F.col("_cy"), F.col("x") == F.col("y")).alias("same"))


def bipartite_cert(edges: DataFrame, policy: GroupPolicy | None = None, per_component: bool = False, **options) -> Cert:
    return cert_of(edges, "bipartite_each" if per_component else "bipartite", policy=policy, **options)


def bipartition(edges: DataFrame, vertices: DataFrame | None = None, per_component: bool = True, tier: str | None = None, **options) -> DataFrame:
    """(v, component, side, bipartite): side 0 holds the component's least vertex.

    per_component: a component with an odd cycle has null sides; else any such component makes all
    sides null. One pass; tier as in components.
    """
    tier = tier or planned(edges).tier
    if tier == "relational":
        ready = clean(edges, "mark")
        found = relational_sides(ready.filter("u <> v"))
        if not per_component:  # one row goes to all
            found = found.crossJoin(F.broadcast(found.agg(F.bool_or("odd").alias("any")))).withColumn("odd", F.col("any"))
        odd = F.col("odd")
        found = found.select("v", "component", F.when(~odd, F.col("side")).alias("side"), (~odd).alias("bipartite"))
        found = found.join(ready.filter("u = v").select(F.col("u").alias("v")).distinct(), "v", "full")
    else:

        def kernel(e: Edges) -> pa.RecordBatch:
            ids, a, b = compact(e.u, e.v)
            comp, side = sides(len(ids), a[a != b], b[a != b])  # a loop only marks its vertex
            odd = side == 2
            bad = odd if per_component else np.full(len(ids), bool(odd.any()))
            return pa.RecordBatch.from_arrays([column(ids), column(ids[comp]), pa.array(side.astype(np.int8), mask=bad), pa.array(~bad)], names=["v", "component", "side", "bipartite"])

        found = one_task(bipartite_cert(edges, per_component=per_component, tier=tier, marks=True, **options).edges, kernel, "v bigint, component bigint, side tinyint, bipartite boolean")
    out, alone = _with_given(found, vertices), F.col("component").isNull()
    return out.select("v", F.coalesce("component", "v").alias("component"), F.when(alone, F.lit(0)).otherwise(F.col("side")).cast("tinyint").alias("side"), F.coalesce("bipartite", F.lit(True)).alias("bipartite"))


def odd_cycle(edges: DataFrame, **options) -> DataFrame:
    """One row (property, k, holds, witness): holds if there is no odd cycle, else an odd cycle's vertices in order."""

    def kernel(e: Edges) -> pa.RecordBatch:
        cycle = answers.odd_cycle(e)
        return _verdict("bipartite", 0, not cycle, cycle)

    return one_task(bipartite_cert(edges, **options).edges, kernel, VERDICT)


def is_bipartite(edges: DataFrame, **options) -> DataFrame:
    return odd_cycle(edges, **options).select("holds")


def stop_when_odd(edges: DataFrame, policy: GroupPolicy | None = None) -> DataFrame:
    """The verdict alone: each task stops solving once a group has shown an odd cycle, which no later edge can undo."""
    policy = policy or GroupPolicy.adaptive()

    def is_odd(cert: Edges) -> bool:
        ids, a, b = compact(cert.u, cert.v)
        return bool((sides(len(ids), a, b)[1] == 2).any())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fold, told, odd = Fold(of("bipartite"), policy), 0, False
        for batch in batches:
            if odd:
                continue
            fold.add(as_edges(batch))
            if len(fold.groups) > told:
                told, odd = len(fold.groups), is_odd(fold.cert)
        cert = fold.cert if odd else fold.finish(resolve=True)
        if len(cert):
            yield as_batch(cert)

    local = clean(edges).mapInArrow(run, "u bigint, v bigint, w bigint, eid bigint")
    return one_task(local, lambda e: _verdict("bipartite", 0, not answers.odd_cycle(e), []), VERDICT).select("holds")


def _verdict(name: str, k: int, holds: bool, witness) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([name]), pa.array([k], pa.int32()), pa.array([bool(holds)]), pa.array([None if holds else [int(x) for x in witness]], pa.list_(pa.int64()))], names=["property", "k", "holds", "witness"])


def vertex_cert(edges: DataFrame, k: int, cert_kernel: str = "auto", **options) -> Cert:
    """At most k(n - 1) edges that keep min(vertex connectivity, k) of all pairs; copies of a pair are dropped in each merge."""
    return cert_of(edges, "vertex", k, kernel=cert_kernel, **options)


def edge_cert(edges: DataFrame, k: int, cert_kernel: str = "auto", **options) -> Cert:
    """At most k(n - 1) edges that keep min(edge connectivity, k) of all pairs, up to k copies of a pair among them."""
    return cert_of(edges, "edge", k, kernel=cert_kernel, **options)


def _marked(cert: DataFrame, vertices: DataFrame | None) -> DataFrame:
    """The certificate with vertices added as loops, so that isolated ones reach the one task."""
    if vertices is None:
        return cert
    return cert.unionByName(vertices.select(F.col("v").alias("u"), F.col("v"), F.lit(0).cast("long").alias("w"), F.lit(-1).cast("long").alias("eid")))


def is_k_vertex_connected(edges: DataFrame, k: int, vertices: DataFrame | None = None, strict: bool = False, **options) -> DataFrame:
    """One row (property, k, holds, witness); the witness is a separator of fewer than k vertices.

    Cost after the certificate: at most k^2 / 2 + n flows of k augmentations over kn edges.
    """
    cert = vertex_cert(edges, k, marks=True, **options).edges

    def kernel(e: Edges) -> pa.RecordBatch:
        ids = np.unique(np.concatenate([e.u, e.v])) if len(e) else np.empty(0, np.int64)
        return _verdict("vertex", k, *answers.k_vertex_connected(e, ids, k, strict))

    return one_task(_marked(cert, vertices), kernel, VERDICT)


def is_k_edge_connected(edges: DataFrame, k: int, vertices: DataFrame | None = None, **options) -> DataFrame:
    """One row (property, k, holds, witness); the witness is one side of a cut of fewer than k edges."""
    cert = edge_cert(edges, k, marks=True, **options).edges

    def kernel(e: Edges) -> pa.RecordBatch:
        ids = np.unique(np.concatenate([e.u, e.v])) if len(e) else np.empty(0, np.int64)
        return _verdict("edge", k, *answers.k_edge_connected(e, ids, k))

    return one_task(_marked(cert, vertices), kernel, VERDICT)


def cut_vertices(edges: DataFrame, **options) -> DataFrame:
    """(v): vertices whose removal parts a component, from the 2-vertex certificate."""
    return one_task(vertex_cert(edges, 2, **options).edges, lambda e: pa.RecordBatch.from_arrays([column(answers.low_points(e)[0])], names=["v"]), "v bigint")


def bridges(edges: DataFrame, **options) -> DataFrame:
    """(u, v, eid): edges whose removal parts a component, from the 2-edge certificate."""
    return one_task(edge_cert(edges, 2, **options).edges, lambda e: as_batch(e.take(np.array(answers.low_points(e)[1], dtype=np.int64))), "u bigint, v bigint, w bigint, eid bigint").select("u", "v", "eid")


def _by_pair(cert: DataFrame, pairs: DataFrame, k: int, asked: type) -> DataFrame:
    """Asks a certificate about pairs: each of the shuffle's tasks gets a share of the pairs and the
    certificate, which has at most k(n - 1) edges, and lays it out once. Nothing goes to the driver."""
    blocks = int(cert.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = pairs.select(F.col("x").cast("long").alias("x"), F.col("y").cast("long").alias("y")).withColumn("block", F.pmod(F.xxhash64("x", "y"), F.lit(blocks)))
    sent = cert.select("u", "v", "w", "eid").withColumn("block", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long"))))

    def run(some: pa.Table, whole: pa.Table) -> pa.Table:
        batches = whole.combine_chunks().to_batches()
        graph = asked(as_edges(batches[0]) if batches else Edges.empty())
        got = [graph.value(x, y, k)[0] for x, y in zip(some.column("x").to_pylist(), some.column("y").to_pylist(), strict=True)]
        return pa.table({"x": some.column("x"), "y": some.column("y"), "value": pa.array(got, pa.int32())})

    return dealt.groupBy("block").cogroup(sent.groupBy("block")).applyInArrow(run, "x bigint, y bigint, value int")


def local_vertex_connectivity(edges: DataFrame, pairs: DataFrame, k: int, **options) -> DataFrame:
    """(x, y, value): vertex-disjoint paths, at most k; an edge between the two is one of them."""
    return _by_pair(vertex_cert(edges, k, **options).edges, pairs, k, answers.VertexAsked)


def edge_levels(edges: DataFrame, k: int, **options) -> DataFrame:
    """(v, class_1, ..., class_k): the classes that j edge-disjoint paths join pairwise, each named by its least vertex.

    All pairs' edge connectivities up to k in a row per vertex: x and y have as many edge-disjoint
    paths, at most k, as there are levels on which they share a class.
    """
    names = [f"class_{j}" for j in range(1, k + 1)]

    def kernel(e: Edges) -> pa.RecordBatch:
        ids = np.unique(np.concatenate([e.u, e.v]))
        return pa.RecordBatch.from_arrays([column(ids), *(column(answers.edge_classes(e, None, j)[1]) for j in range(1, k + 1))], names=["v", *names])

    return one_task(edge_cert(edges, k, **options).edges, kernel, ", ".join(f"{c} bigint" for c in ("v", *names)))


def vertex_levels(cert: DataFrame, k: int) -> DataFrame:
    """(v, level, known) of a graph that fits a task, as a certificate does; see kernels.cores.vertex_levels."""

    def kernel(e: Edges) -> pa.RecordBatch:
        ids, level, known = cores.vertex_levels(e, k)
        return pa.RecordBatch.from_arrays([column(ids), pa.array(level.astype(np.int32), pa.int32()), pa.array(known)], names=["v", "level", "known"])

    return one_task(cert, kernel, "v bigint, level int, known boolean")


def pairs_with(ids: DataFrame, some: DataFrame) -> DataFrame:
    """(x, y), x < y: the pairs of vertices of ids of which at least one is in some."""
    met = some.select(F.col("v").alias("_a")).crossJoin(ids.select(F.col("v").alias("_b"))).filter("_a <> _b")
    return met.select(F.least("_a", "_b").alias("x"), F.greatest("_a", "_b").alias("y")).distinct()


def vertex_blocks(cert: DataFrame, k: int) -> DataFrame:
    """(v, component, block, level, known) of a graph that fits a task; see kernels.cores.vertex_blocks."""

    def kernel(e: Edges) -> pa.RecordBatch:
        v, component, block, level, known = cores.vertex_blocks(e, k)
        return pa.RecordBatch.from_arrays([column(v), column(component), pa.array(block, pa.int64(), mask=block < 0), pa.array(level.astype(np.int32), pa.int32()), pa.array(known)], names=["v", "component", "block", "level", "known"])

    return one_task(cert, kernel, "v bigint, component bigint, block bigint, level int, known boolean")


def vertex_connectivities(edges: DataFrame, k: int, apart: bool = False, **options) -> DataFrame:
    """(x, y, value, component, block): vertex-disjoint paths of all pairs, at most k, in rows that don't grow with the square.

    A row without y puts a vertex in a component and one of its blocks, if it is in any, with its level
    there. Two vertices of no common block have one path in the same component and none else; two of a
    block (no pair shares two) have the lesser of their levels. Where a level is null, every pair of
    that vertex with one of that block is a row of its own. apart: for pairs without an edge between
    them; rows of others are left out.
    """
    cert = cut(vertex_cert(edges, k, **options).edges)
    told = cut(vertex_blocks(cert, k))
    some, all_of = told.filter("not known").select(F.col("v").alias("_a"), "block"), told.select(F.col("v").alias("_b"), "block")
    pairs = some.join(all_of, "block").filter("_a <> _b").select(F.least("_a", "_b").alias("x"), F.greatest("_a", "_b").alias("y")).distinct()
    if apart:
        pairs = pairs.join(edges.select(F.least("u", "v").alias("x"), F.greatest("u", "v").alias("y")), ["x", "y"], "left_anti")
    none = F.lit(None).cast("bigint")
    asked = _by_pair(cert, pairs, k, cores.Capped).select("x", "y", "value", none.alias("component"), none.alias("block"))
    placed = all_vertices(edges).join(told, "v", "left")
    level = F.when(F.coalesce("known", F.lit(True)), F.coalesce("level", F.lit(0))).cast("int")
    return placed.select(F.col("v").alias("x"), none.alias("y"), level.alias("value"), F.coalesce("component", "v").alias("component"), "block").union(asked)


def local_edge_connectivity(edges: DataFrame, pairs: DataFrame, k: int, **options) -> DataFrame:
    """(x, y, value): edge-disjoint paths, at most k.

    j such paths are what classes of vertices share, and the classes of j + 1 part those of j. So
    any number of pairs is answered by joins on the labels.
    """
    labels = edge_levels(edges, k, **options)
    labels = labels.select("v", F.array(*labels.columns[1:]).alias("classes"))
    ends = [labels.select(F.col("v").alias(n), F.col("classes").alias(f"_{n}")) for n in ("x", "y")]
    asked = pairs.select(F.col("x").cast("long").alias("x"), F.col("y").cast("long").alias("y"))
    shared = F.aggregate(F.zip_with("_x", "_y", lambda a, b: (a == b).cast("int")), F.lit(0), lambda s, c: s + c)
    return asked.join(ends[0], "x", "left").join(ends[1], "y", "left").select("x", "y", F.coalesce(shared, F.lit(0)).cast("int").alias("value"))


def k_edge_classes(edges: DataFrame, k: int, vertices: DataFrame | None = None, **options) -> DataFrame:
    """(v, class): vertices that are pairwise joined by k edge-disjoint paths; the class is its least vertex."""
    cert = _marked(edge_cert(edges, k, marks=True, **options).edges, vertices)

    def kernel(e: Edges) -> pa.RecordBatch:
        ids, label = answers.edge_classes(e, None, k)
        return pa.RecordBatch.from_arrays([column(ids), column(label)], names=["v", "class"])

    return one_task(cert, kernel, "v bigint, class bigint")


def remove_vertices(edges: DataFrame, gone: DataFrame) -> DataFrame:
    g = gone.select(F.col("v").alias("_g"))
    return edges.join(g, F.col("u") == F.col("_g"), "left_anti").join(g, F.col("v") == F.col("_g"), "left_anti")


def remove_edges(edges: DataFrame, gone: DataFrame) -> DataFrame:
    return edges.join(gone.select("eid"), "eid", "left_anti").select(*edges.columns)


def separator(edges: DataFrame, k: int, **options) -> DataFrame:
    """(v): a separator of fewer than k vertices; empty if there is none."""
    return is_k_vertex_connected(edges, k, **options).filter("not holds").select(F.explode("witness").alias("v"))


def components_after(edges: DataFrame, gone: DataFrame, **options) -> DataFrame:
    """(v, component) of what is left without the vertices of gone."""
    left = all_vertices(edges).join(gone.select("v"), "v", "left_anti")
    return components(remove_vertices(edges, gone), left, **options)


def edge_cut(edges: DataFrame, k: int, **options) -> DataFrame:
    """Edges of a cut of fewer than k edges; empty if there is none."""
    side = is_k_edge_connected(edges, k, **options).filter("not holds").select(F.explode("witness").alias("_s"))
    a, b = side.select(F.col("_s").alias("_a")), side.select(F.col("_s").alias("_b"))
    out = edges.join(a, F.col("u") == F.col("_a"), "left").join(b, F.col("v") == F.col("_b"), "left")
    return out.filter(F.col("_a").isNull() != F.col("_b").isNull()).select(*edges.columns)


def lightest_per_pair(edges: DataFrame) -> DataFrame:
    """The least (w, eid) of each pair: all that a minimum forest can use; partial sums before the shuffle."""
    pairs = edges.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"), "w", "eid")
    return pairs.groupBy("u", "v").agg(F.min(F.struct("w", "eid")).alias("m")).select("u", "v", "m.w", "m.eid")


def min_forest(edges: DataFrame, policy: GroupPolicy | None = None, kernel: str = "sort", sense: str = "min", **options) -> DataFrame:
    """Edges (u, v, w, eid) of the minimum (or maximum) spanning forest under the order (w, u, v, eid).

    options: n, parts, prefilter, pad_tail, and tier and overlap as in CertEngine.run.
    """
    return cert_of(edges, f"{sense}_forest", policy=policy, kernel=kernel, **options).edges


def min_forest_by_component(edges: DataFrame, **options) -> DataFrame:
    """Components first, then each one's forest by itself, from the certificates that tasks make of what they read of it."""
    labels = components(edges, **options).withColumnRenamed("v", "_v")
    placed = clean(edges).join(labels, F.col("u") == F.col("_v")).select("component", "u", "v", "w", "eid")
    return certs_by_key(placed, "component", of("min_forest")).select("u", "v", "w", "eid")


def min_tree(edges: DataFrame, vertices: DataFrame | None = None, **options) -> DataFrame:
    """The minimum spanning tree; an error if the graph isn't connected."""
    one = is_connected(edges, vertices).select("connected")
    ok = F.when(F.col("connected"), F.lit(True)).otherwise(F.raise_error(F.lit("the graph isn't connected: it has no spanning tree")))
    # one row; the check runs as the tree is read
    return min_forest(edges, **options).crossJoin(F.broadcast(one)).filter(ok).select("u", "v", "w", "eid")


def single_linkage(edges: DataFrame, most: int, vertices: DataFrame | None = None, **options) -> DataFrame:
    """(v, component) of the minimum forest's edges of weight `most` or less."""
    return components(min_forest(edges, **options).filter(F.col("w") <= most), all_vertices(edges, vertices))


def forest_labels(e: Edges) -> tuple[np.ndarray, np.ndarray]:
    ids, a, b = compact(e.u, e.v)
    return ids, ids[forest(len(ids), a, b)[1]]


@dataclass(frozen=True)
class Graph:
    """The methods on one graph."""

    edges: DataFrame
    vertices: DataFrame | None = None

    @staticmethod
    def from_edges(edges: DataFrame, vertices: DataFrame | None = None) -> Graph:
        return Graph(edges, vertices)

    def components(self, **options) -> DataFrame:
        return components(self.edges, self.vertices, **options)

    def bipartition(self, **options) -> DataFrame:
        return bipartition(self.edges, self.vertices, **options)

    def k_vertex_connected(self, k: int, **options) -> DataFrame:
        return is_k_vertex_connected(self.edges, k, self.vertices, **options)

    def k_edge_connected(self, k: int, **options) -> DataFrame:
        return is_k_edge_connected(self.edges, k, self.vertices, **options)

    def min_forest(self, **options) -> DataFrame:
        return min_forest(self.edges, **options)

"""Table functions, aggregates and scalar functions for SQL users.

SELECT * FROM graph_components(TABLE(SELECT u, v FROM edges) WITH SINGLE PARTITION)
"""

from __future__ import annotations

from array import array
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from sparsecert.functions.bounds import inv_ackermann
from sparsecert.kernels import answers
from sparsecert.kernels.certs import Edges, sides, sorted_forest
from sparsecert.kernels.fold import Fold, GroupPolicy, Property, of
from sparsecert.kernels.forest import compact, forest, labels_of


def _edges(u, v, w=None) -> Edges:
    u, v = np.asarray(u, dtype=np.int64), np.asarray(v, dtype=np.int64)
    return Edges(u, v, np.zeros(len(u), np.int64) if w is None else np.asarray(w, dtype=np.int64), np.arange(len(u)))


class _Folded:
    """Folds a partition's rows by groups as they come; subclasses say for what, and answer at the end.

    Rows are buffered as numbers in arrays and go to the fold a batch at a time, so what is held is a
    certificate, a group and a batch.
    """

    width, rows_a_batch = 2, 1 << 16

    def prop(self) -> Property:
        return of("components")

    def __init__(self) -> None:
        self.ends, self.fold, self.count, self.options = array("q"), None, 0, ()

    def eval(self, row, *options) -> None:
        self.options = options
        if row[0] is None or row[1] is None or row[0] == row[1]:
            return
        self.ends.append(row[0])
        self.ends.append(row[1])
        self.ends.append(row[2] if self.width > 2 and row[2] is not None else 0)
        if len(self.ends) >= 3 * self.rows_a_batch:
            self._flush()

    def _flush(self) -> None:
        if self.fold is None:
            self.fold = Fold(self.prop(), GroupPolicy.adaptive())
        x = np.frombuffer(self.ends, dtype=np.int64).reshape(-1, 3) if len(self.ends) else np.empty((0, 3), np.int64)
        self.fold.add(Edges(x[:, 0].copy(), x[:, 1].copy(), x[:, 2].copy(), np.arange(self.count, self.count + len(x))))
        self.count += len(x)
        self.ends = array("q")

    def edges(self) -> Edges:
        self._flush()
        return self.fold.finish(resolve=True)


class GraphComponents(_Folded):
    def terminate(self) -> Iterator[tuple]:
        e = self.edges()
        for v, c in zip(*labels_of(e.u, e.v), strict=True):
            yield int(v), int(c)


class GraphSides(_Folded):
    def prop(self) -> Property:
        return of("bipartite_each")

    def terminate(self) -> Iterator[tuple]:
        e = self.edges()
        ids, a, b = compact(e.u, e.v)
        comp, side = sides(len(ids), a, b)
        for v, c, s in zip(ids, ids[comp] if len(ids) else comp, side, strict=True):
            yield int(v), int(c), None if s == 2 else int(s)


class GraphForest(_Folded):
    def terminate(self) -> Iterator[tuple]:
        e = self.edges()
        yield from zip(e.u.tolist(), e.v.tolist(), strict=True)


class GraphMinForest(_Folded):
    width = 3

    def prop(self) -> Property:
        return of("min_forest")

    def terminate(self) -> Iterator[tuple]:
        e = self.edges()
        yield from zip(e.u.tolist(), e.v.tolist(), e.w.tolist(), strict=True)


class GraphVertexCert(_Folded):
    def prop(self) -> Property:
        return of("vertex", int(self.options[0]) if self.options else 1)

    def terminate(self) -> Iterator[tuple]:
        e = self.edges()
        yield from zip(e.u.tolist(), e.v.tolist(), strict=True)


class GraphEdgeCert(GraphVertexCert):
    def prop(self) -> Property:
        return of("edge", int(self.options[0]) if self.options else 1)


class GraphConnectivity(_Folded):
    """Local connectivities of two vertices, at most k: options x, y, k. An edge certificate with k copies
    of a pair answers for edges; vertices need one that drops copies, so both are kept."""

    def prop(self) -> Property:
        return of("edge", int(self.options[2]) if self.options else 1)

    def _flush(self) -> None:
        ends = self.ends
        super()._flush()
        if getattr(self, "apart", None) is None:
            self.apart = Fold(of("vertex", self.fold.prop.k), GroupPolicy.adaptive())
        x = np.frombuffer(ends, dtype=np.int64).reshape(-1, 3) if len(ends) else np.empty((0, 3), np.int64)
        self.apart.add(Edges(x[:, 0].copy(), x[:, 1].copy(), x[:, 2].copy(), np.arange(len(x))))

    def terminate(self) -> Iterator[tuple]:
        if self.options:
            (x, y, k), e = map(int, self.options), self.edges()
            yield x, y, answers.local_vertex(self.apart.finish(resolve=True), x, y, k)[0], answers.local_edge(e, x, y, k)[0]


def component_count(u: pd.Series, v: pd.Series) -> int:
    ids, a, b = compact(u.to_numpy(), v.to_numpy())
    return len(np.unique(forest(len(ids), a, b)[1]))


def is_bipartite(u: pd.Series, v: pd.Series) -> bool:
    ids, a, b = compact(u.to_numpy(), v.to_numpy())
    return not bool((sides(len(ids), a, b)[1] == 2).any())


def min_forest_weight(u: pd.Series, v: pd.Series, w: pd.Series) -> int:
    e = _edges(u, v, w)
    return int(e.w[sorted_forest(e)].sum())


def inverse(m: pd.Series, n: pd.Series) -> pd.Series:
    return pd.Series([inv_ackermann(int(a), int(b)) for a, b in zip(m, n, strict=True)], dtype="int64")


component_count_agg = F.pandas_udf(component_count, T.LongType())
is_bipartite_agg = F.pandas_udf(is_bipartite, T.BooleanType())
min_forest_weight_agg = F.pandas_udf(min_forest_weight, T.LongType())
inv_ackermann_udf = F.pandas_udf(inverse, T.LongType())

TABLE_FUNCTIONS = {
    "graph_components": (GraphComponents, "v bigint, component bigint"),
    "graph_bipartition": (GraphSides, "v bigint, component bigint, side int"),
    "graph_spanning_forest": (GraphForest, "u bigint, v bigint"),
    "graph_min_forest": (GraphMinForest, "u bigint, v bigint, w bigint"),
    "graph_vertex_cert": (GraphVertexCert, "u bigint, v bigint"),
    "graph_edge_cert": (GraphEdgeCert, "u bigint, v bigint"),
    "graph_connectivity": (GraphConnectivity, "x bigint, y bigint, kappa int, lambda int"),
}


#: Functions whose body is SQL, which Catalyst puts in place of each call.
SQL_FUNCTIONS = (
    f"encode_vertex(kind INT, id BIGINT) RETURNS BIGINT RETURN kind * {1 << 56}L + id",
    "dot_product(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), 0.0D, (s, x) -> s + x)",
    "cosine_distance(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN 1 - dot_product(a, b) / (sqrt(dot_product(a, a)) * sqrt(dot_product(b, b)))",
)


def register(spark: SparkSession) -> None:
    """All functions under their SQL names."""
    for body in SQL_FUNCTIONS:
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {body}")
    for name, (kind, schema) in TABLE_FUNCTIONS.items():
        spark.udtf.register(name, F.udtf(kind, returnType=schema))
    for name, f in {"component_count": component_count_agg, "is_bipartite": is_bipartite_agg, "min_forest_weight": min_forest_weight_agg, "inv_ackermann": inv_ackermann_udf}.items():
        spark.udf.register(name, f)

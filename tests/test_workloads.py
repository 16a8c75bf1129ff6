"""Registered queries against DuckDB on the smallest tables, and the methods on the same graph in other ways."""

import itertools

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
import pytest

from sparsecert.kernels.answers import EdgeAsked
from sparsecert.kernels.certs import Edges
from sparsecert.sources.graphs import KIND, graph
from sparsecert.workloads import measures, methods, streams, surroundings  # noqa: F401
from tests import brute
from tests.compare import SMALLEST, connection, rows_of, sorted_rows
from tests.test_classes import told_by_rows

#: One of each family; `python -m tests.compare` runs all of them at any scale.
SOME = [
    "components_customer_order", "components_doc_line", "components_tiny_sparse", "components_with_isolated_parts", "component_sizes_page_host", "is_connected_co_purchase", "same_component_customer_order", "relational_components_doc_line",
    "forest_size_by_group_user_adjacent", "bipartition_user_adjacent", "bipartition_customer_order", "is_bipartite_early_stop_co_purchase", "odd_cycle_user_adjacent", "relational_bipartite_customer_order", "k_vertex_5_user_type", "k_vertex_6_user_type",
    "k_edge_1_customer_order", "k_vertex_2_premium", "bridges_conv_turn", "cut_vertices_page_host", "separator_user_type", "min_forest_sort_user_adjacent", "min_forest_grow_user_adjacent", "max_forest_nation_trade", "min_forest_by_component_tiny_sparse",
    "relational_min_forest_user_adjacent", "single_linkage_embeddings", "grid_sparsified_components_co_purchase", "order_invariance", "union_law", "transitive_law", "per_edge_components_customer_order", "per_edge_min_forest_linkcut", "store_all_co_purchase",
    "density_regime", "bound_table_at_graphs", "tradeoff_groups_user_adjacent", "total_time_stream_vs_whole_components", "cap_multiplicity", "lightest_per_pair", "prefix_graph", "not_in_null", "balance_band_edges", "event_asof_purchase", "events_within_10min",
    "top3_partners_lateral", "hub_join", "trade_cube", "components_per_segment", "group_schedule", "rank_partners", "running_new_vertices", "edges_by_weight", "cert_minus_graph", "udtf_components", "recursive_reach", "stream_components_customer_order",
    "stream_keyed_state_components", "tumbling_window_forests", "sliding_window_forests", "user_sessions", "relational_vertex_cert_verdict",
]


@pytest.fixture(scope="module")
def duck():
    return connection(SMALLEST)


@pytest.mark.parametrize("name", SOME)
def test_query_equals_sql(spark, duck, name):
    got = methods.QUERIES[name](spark, SMALLEST).toArrow()
    names, want = rows_of(duck, methods.SQL[name])
    assert sorted(got.column_names) == names
    assert sorted_rows(got) == want


def test_every_oracle_belongs_to_a_query():
    assert set(methods.SQL) <= set(methods.QUERIES)


def test_entry(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() == 1650
    assert set(entry.oracle_sql()) <= set(entry.queries())


def _prim(x):
    """Weight and size of a minimum forest of all pairs of vectors, by growing one tree."""
    x = x / np.linalg.norm(x, axis=1, keepdims=True)
    w = np.round((1 - x @ x.T) * 1_000_000).astype(np.int64)
    best, inside, total = w[0].copy(), np.arange(len(x)) == 0, 0
    for _ in range(len(x) - 1):
        i = int(np.where(inside, np.iinfo(np.int64).max, best).argmin())
        total, inside[i] = total + int(best[i]), True
        best = np.minimum(best, w[i])
    return total


def test_the_forest_of_all_vectors_is_returned(spark):
    table = pq.read_table(f"{SMALLEST}/embeddings.parquet").sort_by("vec_id")
    got = methods.QUERIES["min_forest_embedding_whole"](spark, SMALLEST).toArrow()
    x = np.array(table.column("embedding").to_pylist(), dtype=np.float64)
    ends = set(got.column("u").to_pylist()) | set(got.column("v").to_pylist())
    assert got.num_rows == len(x) - 1 and len(ends) == len(x) > 200
    assert sum(got.column("w").to_pylist()) == _prim(x)


def test_questions_on_whole_graphs(spark):
    """All users take part, not the first 14 alone; values by trying all vertex sets below 4."""
    edges = [(r.u, r.v) for r in graph(spark, SMALLEST, "user_adjacent").select("u", "v").collect()]
    users = sorted({x for e in edges for x in e})
    got = {r.v: r[1:] for r in methods.QUERIES["local_lambda_whole_user_adjacent"](spark, SMALLEST).collect()}
    assert len(users) > 14 and sorted(got) == users
    asked = EdgeAsked(Edges(*(np.array(x, dtype=np.int64) for x in zip(*((u, v, 0, i) for i, (u, v) in enumerate(edges)), strict=True))))
    for x, y in itertools.combinations(users, 2):
        assert sum(a == b for a, b in zip(got[x], got[y], strict=True)) == asked.value(x, y, 4)[0]
    simple = sorted({tuple(sorted(e)) for e in edges})
    apart = set(itertools.combinations(users, 2)) - set(simple)
    rows = methods.QUERIES["local_kappa_whole_user_adjacent"](spark, SMALLEST).collect()
    assert {r.x for r in rows if r.y is None} == set(users) and all((r.x, r.y) in apart for r in rows if r.y is not None)
    kappa = {p: value for p, value in told_by_rows(rows, users).items() if p in apart}
    assert kappa == {(x, y): brute.local_vertex(users, simple, x, y, 4) for x, y in apart}
    assert methods.QUERIES["k_vertex_3_whole_user_adjacent"](spark, SMALLEST).first().holds == brute.k_vertex(users, simple, 3)
    near = {r.v: r.near for r in methods.QUERIES["neighbour_list_whole"](spark, SMALLEST).collect()}
    assert near == {v: ",".join(str(y) for y in sorted({b if a == v else a for a, b in simple if v in (a, b)})) for v in users}


def test_reach_has_no_bound_of_depth(spark, tmp_path):
    """A path of 18 vertices, and an edge apart from it."""
    rows = [(i // 2, (i + 1) // 2) for i in range(17)] + [(100, 100)]
    columns = {"l_suppkey": [a for a, _ in rows], "l_partkey": [b for _, b in rows], "l_orderkey": list(range(len(rows))), "l_linenumber": [1] * len(rows)}
    table = pa.table({**columns, "l_discount": [0.0] * len(rows), "l_tax": [0.0] * len(rows), "l_quantity": [50.0] * len(rows), "l_extendedprice": [1.0] * len(rows)})
    pq.write_table(table, tmp_path / "lineitem.parquet")
    got = sorted(r.v for r in methods.QUERIES["recursive_reach"](spark, str(tmp_path)).collect())
    assert got == sorted({KIND + a for a, _ in rows[:-1]} | {2 * KIND + b for _, b in rows[:-1]})
    assert len(got) == 18


def test_edges_of_a_per_edge_method_are_fed_once(spark, monkeypatch):
    """The planner's pass that counts vertices of a large input ran the method as often again."""
    from sparsecert.plans import batch

    want = {(k, n): methods.QUERIES[f"k_edge_{k}_whole_{n}"](spark, SMALLEST).first().holds for k in (3, 4) for n in ("premium_cust_supp", "user_adjacent")}

    def none(*_, **__):
        raise AssertionError("the planner was asked")

    monkeypatch.setattr(batch, "planned", none)
    assert {(k, n): methods.QUERIES[f"per_edge_edge_{k}_flow_whole_{n}"](spark, SMALLEST).first().holds for k, n in want} == want

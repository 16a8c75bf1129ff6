"""Queries of the subpackage that have SQL, on the smallest tables."""

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
import pytest

from sparsecert.llm import queries
from tests.compare import SMALLEST, connection, rows_of, sorted_rows

CONTRACT = {
    "op1": ["doc_id", "held_out", "score", "predicted"],
    "op2": ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"],
    "op5": ["doc_id", "size", "text_crc32", "law", "shard", "slot", "grown_shard"],
    "op6": ["doc_id", "n_email", "n_ip", "n_card", "n_phone", "base_sha256", "spans"],
    "op7": ["doc_id", "size", "source_size", "target", "taken"],
    "op9": ["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans"],
    "op10": ["doc_id", "keep_id", "group_size", "kept", "text_sha256"],
}


@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_query_equals_sql(spark, name):
    got = queries.queries()[name](spark, SMALLEST).toArrow()
    columns, want = rows_of(connection(SMALLEST), queries.oracle_sql()[name])
    assert sorted(got.column_names) == columns
    assert sorted_rows(got) == want


@pytest.mark.parametrize("number", CONTRACT)
def test_columns_of_the_contract(spark, number):
    name = next(q for q in queries.queries() if q.startswith(f"{number}_"))
    out = queries.queries()[name](spark, SMALLEST)
    assert out.columns[: len(CONTRACT[number])] == CONTRACT[number]
    rows = spark.read.parquet(f"{SMALLEST}/{'pages' if number == 'op2' else 'documents'}.parquet").count()
    assert out.count() == rows


def test_vectors_with_links_equal_sql(spark, tmp_path):
    """The given small tables hold no links; these have clusters, chains, copies, zeros, nulls and a length of their own."""
    draw = np.random.default_rng(4)
    centres = draw.standard_normal((12, 16))
    rows = [(centres[i % 12] + 0.22 * draw.standard_normal(16)).tolist() for i in range(400)]
    rows += [rows[3], rows[3], [2 * x for x in rows[4]], [0.0] * 16, None, [], [float("nan")] * 16, [None, *rows[5][1:]], rows[6][:8]]
    pq.write_table(pa.table({"vec_id": pa.array(range(len(rows)), pa.int64()), "embedding": pa.array(rows, pa.list_(pa.float32())), "label": pa.array([0] * len(rows), pa.int32())}), tmp_path / "embeddings.parquet")
    name = "op4_sorted_projection_vectors"
    got = queries.queries()[name](spark, str(tmp_path)).toArrow()
    columns, want = rows_of(connection(str(tmp_path)), queries.oracle_sql()[name])
    assert sorted(got.column_names) == columns
    assert sorted_rows(got) == want
    assert sum(got.column("n_links").to_pylist()) > 1000

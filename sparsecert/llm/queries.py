"""The subpackage's queries and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from sparsecert.llm.exactdedup import OP10_SQL, op10_polynomial_exact_dedup
from sparsecert.llm.mixing import OP7_SQL, op7_hash_prefix_mixing
from sparsecert.llm.neardup import op3_weighted_minhash_neardup
from sparsecert.llm.packing import op8_hierarchical_packing
from sparsecert.llm.pii import op6_crf_personal_data
from sparsecert.llm.quality import op1_additive_quality
from sparsecert.llm.secrets import op9_layered_secret_scan
from sparsecert.llm.sharding import op5_hash_tree_sharding
from sparsecert.llm.vectors import OP4_SQL, op4_sorted_projection_vectors
from sparsecert.llm.warc import OP2_SQL, op2_warc_transactions


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found = (
        op1_additive_quality, op2_warc_transactions, op3_weighted_minhash_neardup, op4_sorted_projection_vectors, op5_hash_tree_sharding, op6_crf_personal_data, op7_hash_prefix_mixing, op8_hierarchical_packing, op9_layered_secret_scan,
        op10_polynomial_exact_dedup,
    )
    return {f.__name__: f for f in found}


def oracle_sql() -> dict[str, str]:
    return {"op2_warc_transactions": OP2_SQL, "op4_sorted_projection_vectors": OP4_SQL, "op7_hash_prefix_mixing": OP7_SQL, "op10_polynomial_exact_dedup": OP10_SQL}

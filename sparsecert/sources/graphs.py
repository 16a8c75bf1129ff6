"""Graphs on the given tables, as SQL that Spark and DuckDB both run where their dialects agree.

A vertex is a kind code times 2^56 plus its key, so that keys of different tables never meet. Hashed
keys of strings take 56 bits of their md5: `hash_collisions` counts strings that meet, and
`operators.edges.dictionary` numbers strings exactly where hashes won't do (some 10^8 distinct ones).
Columns: u, v, w, eid; edges between unlike ends only.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from sparsecert.sources.tables import load, register

KIND = 1 << 56
SUPPLIER, PART, CUSTOMER, ORDER, NATION, USER, TYPE, DOCUMENT, LINE, TURN, PAGE, HOST, VECTOR = range(1, 14)


def code(kind: int, key: str) -> str:
    return f"{kind * KIND} + {key}"


def vertex(kind: int, key: Column) -> Column:
    return F.lit(kind * KIND) + key.cast("long")


def hashed(text: Column) -> Column:
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 14), 16, 10).cast("long")


def hashed_sql(text: str) -> str:
    """DuckDB's form of hashed."""
    return f"CAST('0x' || substr(md5({text}), 1, 14) AS BIGINT)"


_LINE_ID = "l_orderkey * 8 + l_linenumber"
_CENTS = "CAST(round(l_extendedprice * 100) AS BIGINT)"

#: The same text for both engines.
COMMON_SQL = {
    "supplier_part": f"SELECT {code(SUPPLIER, 'l_suppkey')} AS u, {code(PART, 'l_partkey')} AS v, {_CENTS} AS w, {_LINE_ID} AS eid FROM lineitem",
    "customer_part": f"SELECT {code(CUSTOMER, 'o_custkey')} AS u, {code(PART, 'l_partkey')} AS v, {_CENTS} AS w, {_LINE_ID} AS eid FROM orders JOIN lineitem ON o_orderkey = l_orderkey",
    "customer_supplier": f"SELECT {code(CUSTOMER, 'o_custkey')} AS u, {code(SUPPLIER, 'l_suppkey')} AS v, {_CENTS} AS w, {_LINE_ID} AS eid FROM orders JOIN lineitem ON o_orderkey = l_orderkey",
    "co_purchase": f"SELECT {code(PART, 'a.l_partkey')} AS u, {code(PART, 'b.l_partkey')} AS v, CAST(round((a.l_extendedprice + b.l_extendedprice) * 100) AS BIGINT) AS w, (a.l_orderkey * 8 + a.l_linenumber) * 8 + b.l_linenumber AS eid FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey",
    "customer_order": f"SELECT {code(CUSTOMER, 'o_custkey')} AS u, {code(ORDER, 'o_orderkey')} AS v, CAST(round(o_totalprice * 100) AS BIGINT) AS w, o_orderkey AS eid FROM orders",
    "nation_trade": f"SELECT {code(NATION, 'least(c_nationkey, s_nationkey)')} AS u, {code(NATION, 'greatest(c_nationkey, s_nationkey)')} AS v, {_CENTS} AS w, {_LINE_ID} AS eid FROM lineitem JOIN orders ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey JOIN supplier ON s_suppkey = l_suppkey WHERE c_nationkey <> s_nationkey",
    "premium_cust_supp": f"SELECT {code(CUSTOMER, 'o_custkey')} AS u, {code(SUPPLIER, 'l_suppkey')} AS v, {_CENTS} AS w, {_LINE_ID} AS eid FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE l_extendedprice > 100000 OR (l_returnflag = 'R' AND l_quantity >= 49)",
    "conv_turn": f"SELECT {code(TURN, 'a.conv_id * 16777216 + a.turn')} AS u, {code(TURN, 'b.conv_id * 16777216 + b.turn')} AS v, CAST(1 AS BIGINT) AS w, a.conv_id * 16777216 + a.turn AS eid FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1",
    "tiny_sparse": f"SELECT {code(SUPPLIER, 'l_suppkey')} AS u, {code(PART, 'l_partkey')} AS v, {_CENTS} AS w, {_LINE_ID} AS eid FROM lineitem WHERE l_discount = 0 AND l_tax = 0 AND l_quantity > 45",
    "key_tree": f"SELECT {code(NATION, 'n_nationkey')} AS u, {code(HOST, 'n_regionkey')} AS v, CAST(n_nationkey AS BIGINT) AS w, CAST(n_nationkey AS BIGINT) AS eid FROM nation",
}

#: DuckDB's form of graphs that Spark builds with functions of its own.
DUCK_SQL = COMMON_SQL | {
    "user_adjacent": f"SELECT {code(USER, 'least(a, b)')} AS u, {code(USER, 'greatest(a, b)')} AS v, w, eid FROM (SELECT user_id AS a, lead(user_id) OVER (ORDER BY ts, event_id) AS b, CAST(round(100 * value) AS BIGINT) AS w, event_id AS eid FROM events) WHERE a <> b",
    "user_type": f"SELECT {code(USER, 'user_id')} AS u, {code(TYPE, hashed_sql('event_type'))} AS v, CAST(round(100 * value) AS BIGINT) AS w, event_id AS eid FROM events",
    "doc_line": f"SELECT {code(DOCUMENT, 'doc_id')} AS u, {code(LINE, hashed_sql('line'))} AS v, CAST(length(line) AS BIGINT) AS w, doc_id * 268435456 + (ord - 1) AS eid FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) AS ord FROM documents) WHERE length(line) >= 20",
    "embedding_pairs": f"SELECT {code(VECTOR, 'a.vec_id')} AS u, {code(VECTOR, 'b.vec_id')} AS v, CAST(round(1000000 * (1 - list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])))) AS BIGINT) AS w, a.vec_id * 2147483648 + b.vec_id AS eid FROM embeddings a JOIN embeddings b ON a.vec_id < b.vec_id",
    "page_host": f"SELECT {code(PAGE, 'page_id')} AS u, {code(HOST, hashed_sql(chr(39).join(['regexp_extract(url, ', '^[a-z]+://([^/?#]*)', ', 1)'])))} AS v, CAST(1 AS BIGINT) AS w, page_id AS eid FROM pages",
}
DUCK_SQL["small_user_slice"] = f"SELECT * FROM ({DUCK_SQL['user_adjacent']}) WHERE u < {code(USER, '14')} AND v < {code(USER, '14')}"


def numbered(group: Column, place: Column, bits: int) -> Column:
    """A number for a place in a group; an error where either is too large for it."""
    fits = (place < (1 << bits)) & (group >= 0) & (group < (1 << (62 - bits)))
    return F.when(fits, group.cast("long") * (1 << bits) + place).otherwise(F.raise_error(F.lit(f"a group has more than 2^{bits} places, or a number beyond 2^{62 - bits}")).cast("long"))


def event_order(events: DataFrame) -> DataFrame:
    """Events with seq (place from 1 by ts, event_id) and next_user.

    The order is found within days; a table of days, one row each, links the last event of a day
    with the first of the next, so no task holds all events.
    """
    dated = events.withColumn("_day", F.to_date("ts"))
    within = Window.partitionBy("_day").orderBy("ts", "event_id")
    local = dated.withColumn("_n", F.row_number().over(within)).withColumn("_next", F.lead("user_id").over(within))
    days = dated.groupBy("_day").agg(F.count(F.lit(1)).alias("_c"), F.min_by("user_id", F.struct("ts", "event_id")).alias("_first"))
    by_day = Window.orderBy("_day")
    days = days.select(F.col("_day").alias("_d"), F.coalesce(F.sum("_c").over(by_day.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_before"), F.lead("_first").over(by_day).alias("_after"))
    out = local.join(days, F.col("_day").eqNullSafe(F.col("_d")))
    return out.withColumn("seq", F.col("_before") + F.col("_n")).withColumn("next_user", F.coalesce("_next", "_after")).drop("_day", "_n", "_next", "_d", "_before", "_after")


def cosine(a: Column, b: Column) -> Column:
    """In double precision; null for a zero vector."""
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, p: s + p)
    return dot(a, b) / (F.sqrt(dot(a, a)) * F.sqrt(dot(b, b)))


def vector_pairs(vectors: DataFrame, block: int = 1024) -> DataFrame:
    """(u, v, w, eid) of all pairs of vectors, which is what this graph is: quadratic by definition.

    Vectors are dealt to blocks; each pair of blocks meets in one task, as a product of two arrays.
    """
    blocks = max(1, -(-vectors.count() // block))
    placed = vectors.filter("embedding is not null").withColumn("b", F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int"))
    every = placed.withColumn("o", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    met = every.select(F.least("b", "o").alias("low"), F.greatest("b", "o").alias("high"), "b", "vec_id", "embedding")

    def run(table: pa.Table) -> pa.Table:
        table = table.combine_chunks().sort_by("vec_id")
        ids, mine, vectors_ = table.column("vec_id").to_numpy(), table.column("b").to_numpy(), table.column("embedding").combine_chunks()
        low, high = table.column("low")[0].as_py(), table.column("high")[0].as_py()
        x = vectors_.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(ids), -1)
        size = np.sqrt((x * x).sum(axis=1))
        at, to = np.flatnonzero(mine == low), np.flatnonzero(mine == high)
        us, vs, ws = [], [], []
        for lo in range(0, len(at), 128):
            some = at[lo : lo + 128]
            # einsum sums each product in the order of the components, like the SQL form
            with np.errstate(divide="ignore", invalid="ignore"):
                w = np.rint(1_000_000 * (1 - np.einsum("id,jd->ij", x[some], x[to]) / (size[some][:, None] * size[to][None])))
            i, j = np.nonzero(some[:, None] < to[None] if low == high else np.ones(w.shape, dtype=bool))
            us.append(ids[some[i]])
            vs.append(ids[to[j]])
            ws.append(w[i, j])
        u, v, w = (np.concatenate(c) if c else np.empty(0) for c in (us, vs, ws))
        u, v = np.minimum(u, v).astype(np.int64), np.maximum(u, v).astype(np.int64)
        bad = ~np.isfinite(w)
        weight = pa.array(np.where(bad, 0, w).astype(np.int64), mask=bad)
        return pa.table({"u": pa.array(u + VECTOR * KIND), "v": pa.array(v + VECTOR * KIND), "w": weight, "eid": pa.array(u * 2147483648 + v)})

    return met.groupBy("low", "high").applyInArrow(run, "u bigint, v bigint, w bigint, eid bigint")


def _built(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    if name in ("user_adjacent", "small_user_slice"):
        e = event_order(load(spark, sf_dir, "events")).filter(F.col("user_id") != F.col("next_user"))
        out = e.select(vertex(USER, F.least("user_id", "next_user")).alias("u"), vertex(USER, F.greatest("user_id", "next_user")).alias("v"), F.round(F.col("value") * 100).cast("long").alias("w"), F.col("event_id").alias("eid"), F.col("seq").cast("long").alias("seq"))
        if name == "small_user_slice":
            top = USER * KIND + 14
            out = out.filter((F.col("u") < top) & (F.col("v") < top))
        return out
    if name == "user_type":
        e = load(spark, sf_dir, "events")
        return e.select(vertex(USER, F.col("user_id")).alias("u"), vertex(TYPE, hashed(F.col("event_type"))).alias("v"), F.round(F.col("value") * 100).cast("long").alias("w"), F.col("event_id").alias("eid"))
    if name == "doc_line":
        lines = load(spark, sf_dir, "documents").select("doc_id", F.posexplode(F.split("text", "\n")).alias("ord", "line")).filter(F.length("line") >= 20)
        return lines.select(vertex(DOCUMENT, F.col("doc_id")).alias("u"), vertex(LINE, hashed(F.col("line"))).alias("v"), F.length("line").cast("long").alias("w"), numbered(F.col("doc_id"), F.col("ord"), 28).alias("eid"))
    if name == "embedding_pairs":
        return vector_pairs(load(spark, sf_dir, "embeddings").select("vec_id", "embedding"))
    if name == "page_host":
        p = load(spark, sf_dir, "pages")
        host = F.regexp_extract("url", r"^[a-z]+://([^/?#]*)", 1)
        return p.select(vertex(PAGE, F.col("page_id")).alias("u"), vertex(HOST, hashed(host)).alias("v"), F.lit(1).cast("long").alias("w"), F.col("page_id").alias("eid"))
    raise KeyError(name)


GRAPHS = (*COMMON_SQL, "user_adjacent", "user_type", "doc_line", "embedding_pairs", "page_host", "small_user_slice")


def graph(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """u, v, w, eid, seq; seq is the order of arrival where the table has one, else eid."""
    if name in COMMON_SQL:
        register(spark, sf_dir, tuple(t for t in ("lineitem", "orders", "customer", "supplier", "conversations", "nation") if t in COMMON_SQL[name]))
        df = spark.sql(COMMON_SQL[name])
    else:
        df = _built(spark, sf_dir, name)
    df = df.select(F.col("u").cast("long").alias("u"), F.col("v").cast("long").alias("v"), F.col("w").cast("long").alias("w"), F.col("eid").cast("long").alias("eid"), *(["seq"] if "seq" in df.columns else []))
    return df if "seq" in df.columns else df.withColumn("seq", F.col("eid"))

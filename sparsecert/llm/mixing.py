"""Mixing sources to target weights: hash-random order, distributed prefix sums, exact cuts.

The budget is spread over the sources by weight; no source gets more than `most_epochs` times its
size, and what one can't use is spread again over the others by weight. Within a source the
documents stand in the order of a hash; whole epochs are taken first, then documents up to the
exact rest of the budget, the last one in part.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from sparsecert.llm.common import load, staged
from sparsecert.llm.prefix import prefix_before

#: What separates words, and the weights by rank of the source.
WORD = r"[^\x20\x09-\x0D]+"
WEIGHTS = (3, 1, 2)


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def source_targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: float = 1.5, most_epochs: int = 2) -> DataFrame:
    """sizes: a row per source (source, source_size). Adds weight and target.

    Sources fill up in the order of cap / weight; a level by weight serves all that stay below
    their caps, and the first source whose cap isn't reached fixes the level.
    """
    ranked = sizes.withColumn("_rank", F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1)
    weight = F.element_at(F.array(*[F.lit(w) for w in weights]), (F.col("_rank") % len(weights) + 1).cast("int")).cast("double")
    ranked = ranked.withColumn("weight", weight).withColumn("_cap", F.col("source_size").cast("double") * most_epochs)
    order = [F.col("_cap") / F.col("weight"), F.col("_rank")]
    ahead, onward, every = Window.orderBy(*order).rowsBetween(Window.unboundedPreceding, -1), Window.orderBy(*order).rowsBetween(0, Window.unboundedFollowing), Window.partitionBy()
    filled = (
        ranked.withColumn("_taken", F.coalesce(F.sum("_cap").over(ahead), F.lit(0.0)))
        .withColumn("_open", F.sum("weight").over(onward))
        .withColumn("_budget", F.sum("source_size").over(every).cast("double") * share)
        .withColumn("_level", (F.col("_budget") - F.col("_taken")) / F.col("_open"))
        .withColumn("_level", F.max(F.when(F.col("_level") * F.col("weight") <= F.col("_cap"), F.col("_level"))).over(every))
    )
    return filled.select("source", "source_size", "weight", F.least(F.col("_cap"), F.coalesce(F.col("_level") * F.col("weight"), F.col("_cap"))).alias("target"))


def mix(docs: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: float = 1.5, most_epochs: int = 2) -> DataFrame:
    """One row per row of docs: doc_id, size, source_size, target, taken.

    Null texts have size 0, a null source is a source of its own and stands last, rows that repeat
    an id are rows like others, an empty table gives an empty result. Reruns agree: the order is
    that of a hash of the id, then id, size and a hash of the text; rows that agree in all of these
    are alike.
    """
    return _mixed(staged(_narrow(docs.withColumn("_row", F.monotonically_increasing_id())), "mix"), weights, share, most_epochs).drop("_row")


def _narrow(docs: DataFrame) -> DataFrame:
    return docs.select("doc_id", "source", word_count(F.col("text")).alias("size"), F.xxhash64(F.col("text")).alias("_tie"), "_row")


#: The order within a source: by a hash of the id, then so that only rows alike in id and text are level.
ORDER = ["_key", "doc_id", "size", "_tie"]


def _source(source: Column) -> Column:
    return F.coalesce(F.concat(F.lit("s"), source), F.lit("n"))


def _key(doc_id: Column) -> Column:
    return F.md5(F.coalesce(doc_id.cast("string"), F.lit("null")).cast("binary"))


def _placed(narrow: DataFrame, weights: tuple[int, ...], share: float, most_epochs: int) -> DataFrame:
    """narrow with _before, its source's size and target, the whole epochs, and the rest of the budget in words."""
    keyed = narrow.withColumn("_source", _source(F.col("source"))).withColumn("_key", _key(F.col("doc_id")))
    targets = source_targets(keyed.groupBy("source").agg(F.sum("size").alias("source_size")), weights, share, most_epochs)
    targets = targets.select(_source(F.col("source")).alias("_of"), "source_size", "target")
    placed = prefix_before(keyed, "_source", [*ORDER, "_row"], F.col("size"), "_before", narrow.count())
    goal = F.floor(F.col("target") + 0.5)
    epochs = F.when(F.col("source_size") > 0, F.floor(goal / F.greatest(F.col("source_size"), F.lit(1)))).otherwise(F.lit(0))
    joined = placed.join(targets, F.col("_source") == F.col("_of")).withColumn("_epochs", epochs)
    return joined.withColumn("_rest", goal - F.col("_epochs") * F.col("source_size"))


def _mixed(narrow: DataFrame, weights: tuple[int, ...], share: float, most_epochs: int) -> DataFrame:
    part = F.greatest(F.lit(0), F.least(F.col("size"), F.col("_rest") - F.col("_before")))
    taken = (F.col("_epochs") * F.col("size") + part).cast("long")
    return _placed(narrow, weights, share, most_epochs).select("doc_id", "size", "source_size", "target", taken.alias("taken"), "_row")


def _cuts(narrow: DataFrame, weights: tuple[int, ...], share: float, most_epochs: int) -> DataFrame:
    """A row per source: its whole epochs, where in the order its budget ends, and how many words the
    document there gives. Rows that are level there, copies of one document, give as many each."""
    placed = staged(_placed(narrow, weights, share, most_epochs), "placed")
    at = placed.filter((F.col("_before") < F.col("_rest")) & (F.col("_rest") <= F.col("_before") + F.col("size")))
    at = at.select(F.col("_source").alias("_cut_source"), F.struct(*ORDER).alias("_cut"))
    level = placed.join(at, (F.col("_source") == F.col("_cut_source")) & F.struct(*ORDER).eqNullSafe(F.col("_cut")))
    level = level.groupBy("_source").agg(F.first("_cut").alias("_cut"), F.floor((F.first("_rest") - F.min("_before")) / F.count(F.lit(1))).alias("_share"))
    sources = placed.groupBy("_source").agg(F.first("_epochs").alias("_epochs"))
    return sources.join(level, "_source", "left").select(F.col("_source").alias("_mix_source"), F.struct("_epochs", "_cut", "_share").alias("_mix_cut"))


def mixed_documents(docs: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: float = 1.5, most_epochs: int = 2) -> DataFrame:
    """The mix itself, with docs' columns: a row per document and epoch, the last one cut to its words.

    A document whose last epoch is taken in part appears with its first words, parted by a space. The
    texts are neither copied nor shuffled: a row per source tells where the order is cut. Where
    copies of one document (same id, same text) stand at the cut, they give the same number of words
    each, which may leave fewer words of the budget than there are copies.
    """
    size = word_count(F.col("text"))
    cuts = staged(_cuts(staged(_narrow(docs.withColumn("_row", F.monotonically_increasing_id())), "mix"), weights, share, most_epochs), "cuts")
    place = F.struct(_key(F.col("doc_id")).alias("_key"), F.col("doc_id"), size.alias("size"), F.xxhash64(F.col("text")).alias("_tie"))
    work = docs.select("*", place.alias("_mix_place"), _source(F.col("source")).alias("_mix_of"))
    joined = work.join(cuts, F.col("_mix_of") == F.col("_mix_source"))
    words, cut = F.col("_mix_place.size"), F.col("_mix_cut._cut")
    part = F.when(cut.isNull(), F.lit(0)).when(F.col("_mix_place") < cut, words).when(F.col("_mix_place").eqNullSafe(cut), F.col("_mix_cut._share")).otherwise(F.lit(0))
    taken = joined.withColumn("_mix_taken", F.col("_mix_cut._epochs") * words + part).filter("_mix_taken > 0")
    copies = taken.withColumn("_mix_epoch", F.explode(F.sequence(F.lit(0), F.floor((F.col("_mix_taken") - 1) / words).cast("int"))))
    left = F.least(words, F.col("_mix_taken") - F.col("_mix_epoch") * words).cast("int")
    first = F.array_join(F.slice(F.filter(F.split(F.col("text"), r"[\x20\x09-\x0D]+"), lambda w: w != ""), F.lit(1), left), " ")
    return copies.withColumn("text", F.when(left < words, first).otherwise(F.col("text"))).select(*docs.columns)


def op7_hash_prefix_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix(load(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


OP7_SQL = r"""
WITH d AS (
  SELECT doc_id, source, CAST(coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS BIGINT) AS size,
         md5(coalesce(CAST(doc_id AS VARCHAR), 'null')) AS k
  FROM documents
), s AS (
  SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM d GROUP BY source
), r AS (
  SELECT *, row_number() OVER (ORDER BY source ASC NULLS LAST) - 1 AS rk FROM s
), w AS (
  SELECT *, CAST(CASE rk % 3 WHEN 0 THEN 3 WHEN 1 THEN 1 ELSE 2 END AS DOUBLE) AS weight, CAST(source_size AS DOUBLE) * 2 AS cap FROM r
), f AS (
  SELECT *, coalesce(sum(cap) OVER (ORDER BY cap / weight, rk ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS used,
         sum(weight) OVER (ORDER BY cap / weight, rk ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS open_weight,
         CAST(sum(source_size) OVER () AS DOUBLE) * 1.5 AS budget
  FROM w
), l AS (
  SELECT max((budget - used) / open_weight) FILTER (WHERE (budget - used) / open_weight * weight <= cap) AS level FROM f
), t AS (
  SELECT source, source_size, least(cap, coalesce(level * weight, cap)) AS target FROM f, l
), p AS (
  SELECT d.*, coalesce(sum(size) OVER (PARTITION BY source ORDER BY k, doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before
  FROM d
), g AS (
  SELECT p.doc_id, p.size, t.source_size, t.target, p.before, floor(t.target + 0.5) AS goal,
         CASE WHEN t.source_size > 0 THEN floor(floor(t.target + 0.5) / t.source_size) ELSE 0 END AS epochs
  FROM p JOIN t ON p.source IS NOT DISTINCT FROM t.source
)
SELECT doc_id, size, source_size, target,
       CAST(epochs * size + greatest(0, least(size, goal - epochs * source_size - before)) AS BIGINT) AS taken
FROM g
"""

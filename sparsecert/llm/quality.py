"""Quality classifier: a generalised additive model with pairwise interactions.

Features of a text are cut into bins. Shallow trees are boosted in turn over single features, each
adding to that feature's table, then over the pairs of features that explain most of what is left.
A score is the logistic function of the sum of one entry of each table.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from sparsecert.llm.common import load, slices

FEATURES = ("log_bytes", "upper", "symbols", "bangs", "pipes", "digits", "blanks", "lines", "stops", "wide", "word_length", "distinct_words", "short_words", "distinct_lines", "longest_word", "repeats", "ends")
LETTERS_UP, LETTERS_LOW, DIGITS = np.arange(65, 91), np.arange(97, 123), np.arange(48, 58)
SYMBOLS = np.frombuffer(b"#$%&*+<=>@[]^_`{}~\\/", dtype=np.uint8)


def text_features(data: bytes) -> list[float]:
    """Shares of kinds of bytes and measures of words and lines; an empty text has zeros."""
    n = len(data)
    if not n:
        return [0.0] * len(FEATURES)
    counts = np.bincount(np.frombuffer(data, dtype=np.uint8), minlength=256)
    upper, lower = int(counts[LETTERS_UP].sum()), int(counts[LETTERS_LOW].sum())
    words = data.split()
    total = len(words) or 1
    distinct = set(words)
    lengths = np.fromiter(map(len, words), dtype=np.int64, count=len(words)) if words else np.zeros(1, dtype=np.int64)
    lines = data.split(b"\n")
    repeats = sum(map(bytes.__eq__, words[1:], words[:-1])) if len(words) > 1 else 0
    return [
        float(np.log1p(n)), upper / (upper + lower or 1), int(counts[SYMBOLS].sum()) / n, int(counts[33]) / total, int(counts[124]) / total, int(counts[DIGITS].sum()) / n, total / n, len(lines) / total, int(counts[46] + counts[44]) / total,
        int(counts[128:].sum()) / n, float(lengths.mean()), len(distinct) / total, float((lengths <= 3).mean()), len(set(lines)) / len(lines), float(np.log1p(lengths.max())), repeats / total, int(counts[63] + counts[58] + counts[59]) / total,
    ]


@dataclass
class AdditiveModel:
    """Tables by feature and by pair of features; bins are places among the edges."""

    edges: list[np.ndarray]
    bias: float = 0.0
    tables: list[np.ndarray] = field(default_factory=list)
    pairs: list[tuple[int, int]] = field(default_factory=list)
    pair_tables: list[np.ndarray] = field(default_factory=list)

    def bins(self, x: np.ndarray) -> np.ndarray:
        return np.stack([np.searchsorted(e, x[:, j], side="right") for j, e in enumerate(self.edges)], axis=1) if len(x) else np.zeros((0, len(self.edges)), dtype=np.int64)

    def margins(self, x: np.ndarray) -> np.ndarray:
        b = self.bins(x)
        out = np.full(len(x), self.bias)
        for j, table in enumerate(self.tables):
            out += table[b[:, j]]
        for (i, j), table in zip(self.pairs, self.pair_tables, strict=True):
            out += table[b[:, i], b[:, j]]
        return out

    def scores(self, x: np.ndarray) -> np.ndarray:
        return 1.0 / (1.0 + np.exp(-np.clip(self.margins(x), -30, 30)))


def _gain(g: np.ndarray, h: np.ndarray, ridge: float) -> np.ndarray:
    return g * g / (h + ridge)


def _shallow_tree(g: np.ndarray, h: np.ndarray, leaves: int, ridge: float) -> np.ndarray:
    """Leaf value of each bin, for gradient and curvature sums by bin: best cuts are taken one after another."""
    parts = [(0, len(g))]
    cg, ch = np.concatenate([[0], np.cumsum(g)]), np.concatenate([[0], np.cumsum(h)])
    while len(parts) < leaves:
        best = (1e-9, None, None)
        for lo, hi in parts:
            cuts = np.arange(lo + 1, hi)
            if len(cuts):
                left, right = (cg[cuts] - cg[lo], ch[cuts] - ch[lo]), (cg[hi] - cg[cuts], ch[hi] - ch[cuts])
                gains = _gain(*left, ridge) + _gain(*right, ridge) - _gain(cg[hi] - cg[lo], ch[hi] - ch[lo], ridge)
                k = int(gains.argmax())
                if gains[k] > best[0]:
                    best = (float(gains[k]), (lo, hi), int(cuts[k]))
        if best[1] is None:
            break
        parts.remove(best[1])
        parts += [(best[1][0], best[2]), (best[2], best[1][1])]
    out = np.zeros(len(g))
    for lo, hi in parts:
        out[lo:hi] = -(cg[hi] - cg[lo]) / (ch[hi] - ch[lo] + ridge)
    return out


def _quadrants(g: np.ndarray, h: np.ndarray, ridge: float) -> tuple[float, np.ndarray]:
    """The best tree with one cut in each of two features: its gain, and leaf values by pair of bins."""
    def sums(x: np.ndarray) -> list[np.ndarray]:
        c = np.zeros((x.shape[0] + 1, x.shape[1] + 1))
        c[1:, 1:] = x.cumsum(0).cumsum(1)
        low, a, b, all_ = c[1:-1, 1:-1], c[1:-1, -1:], c[-1:, 1:-1], c[-1, -1]
        return [low, a - low, b - low, all_ - a - b + low]

    if min(g.shape) < 2:
        return 0.0, np.zeros_like(g)
    gs, hs = sums(g), sums(h)
    gains = sum(_gain(a, b, ridge) for a, b in zip(gs, hs, strict=True)) - _gain(g.sum(), h.sum(), ridge)
    i, j = np.unravel_index(int(gains.argmax()), gains.shape)
    low, right, left, high = (-a[i, j] / (b[i, j] + ridge) for a, b in zip(gs, hs, strict=True))
    out = np.empty_like(g)
    out[: i + 1, : j + 1], out[: i + 1, j + 1 :], out[i + 1 :, : j + 1], out[i + 1 :, j + 1 :] = low, right, left, high
    return float(gains[i, j]), out


def fit(x: np.ndarray, y: np.ndarray, most_bins: int = 48, rounds: int = 80, pair_rounds: int = 40, most_pairs: int = 8, rate: float = 0.15, leaves: int = 4, ridge: float = 2.0) -> AdditiveModel:
    """Cyclic boosting on the logistic loss. No rows, or labels all alike, give a constant score."""
    if not len(y):
        return AdditiveModel([np.empty(0)] * len(FEATURES))
    edges = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, most_bins + 1)[1:-1])) for j in range(x.shape[1])]
    share = np.clip(y.mean(), 1e-3, 1 - 1e-3)
    model = AdditiveModel(edges, float(np.log(share / (1 - share))), [np.zeros(len(e) + 1) for e in edges])
    b, f = model.bins(x), np.full(len(y), model.bias)

    def slopes() -> tuple[np.ndarray, np.ndarray]:
        p = 1.0 / (1.0 + np.exp(-np.clip(f, -30, 30)))
        return p - y, np.maximum(p * (1 - p), 1e-6)

    for _ in range(rounds):
        for j, e in enumerate(edges):
            g, h = slopes()
            step = rate * _shallow_tree(np.bincount(b[:, j], g, len(e) + 1), np.bincount(b[:, j], h, len(e) + 1), leaves, ridge)
            model.tables[j] += step
            f += step[b[:, j]]
    shape = [len(e) + 1 for e in edges]

    def grid(i: int, j: int, w: np.ndarray) -> np.ndarray:
        return np.bincount(b[:, i] * shape[j] + b[:, j], w, shape[i] * shape[j]).reshape(shape[i], shape[j])

    g, h = slopes()
    ranked = sorted(((_quadrants(grid(i, j, g), grid(i, j, h), ridge)[0], (i, j)) for i in range(len(shape)) for j in range(i)), reverse=True)
    model.pairs = [p for gain, p in ranked[:most_pairs] if gain > 0]
    model.pair_tables = [np.zeros((shape[i], shape[j])) for i, j in model.pairs]
    for _ in range(pair_rounds):
        for n, (i, j) in enumerate(model.pairs):
            g, h = slopes()
            step = rate * _quadrants(grid(i, j, g), grid(i, j, h), ridge)[1]
            model.pair_tables[n] += step
            f += step[b[:, i], b[:, j]]
    return model


def in_fold(key: Column) -> Column:
    """Whether a document is held out: crc32 of its id as text is divisible by 5."""
    return F.crc32(F.coalesce(key.cast("string"), F.lit("")).cast("binary")) % 5 == 0


def train(docs: DataFrame, labels: DataFrame, most_rows: int = 20_000, text: str = "text", key: str = "doc_id") -> AdditiveModel:
    """Fits on at most most_rows labelled rows that aren't held out, the ones with the least hash of their id.

    The sample's ids are most_rows rows at most, so they are sent to all tasks. An id that many rows
    repeat gives one row to the fit, the one with the least features, so that the fit stays bounded.
    """
    marks = labels.select(F.col("doc_id").alias("_label_id"), F.col("quality").alias("_quality")).filter(F.col("_quality").isin(0, 1) & F.col("_label_id").isNotNull() & ~in_fold(F.col("_label_id")))
    marks = marks.orderBy(F.xxhash64("_label_id"), "_label_id", "_quality").limit(most_rows)
    sample = docs.select(F.col(key).alias("_key"), F.coalesce(F.col(text), F.lit("")).cast("binary").alias("_bytes")).join(F.broadcast(marks), F.col("_key") == F.col("_label_id")).select("_key", "_quality", "_bytes")
    kind = sample.schema["_key"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "_bytes"):
            rows = [text_features(d) for d in batch.column("_bytes").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("_key"), batch.column("_quality").cast(pa.float64()), pa.array(rows, pa.list_(pa.float64()))], names=["k", "y", "x"])

    table = sample.mapInArrow(run, f"k {kind}, y double, x array<double>").groupBy("k", "y").agg(F.min("x").alias("x")).select("y", "x").toArrow()
    y = table.column("y").to_numpy()
    x = np.array(table.column("x").to_pylist(), dtype=np.float64).reshape(len(y), len(FEATURES))
    order = np.lexsort([*x.T[::-1], y])  # rows come in any order; the model must not depend on it
    return fit(x[order], y[order])


def with_scores(docs: DataFrame, model: AdditiveModel, columns: list[str], text: str = "text") -> DataFrame:
    """The given columns of docs, and _score."""
    kept = docs.select(*columns, F.coalesce(F.col(text), F.lit("")).cast("binary").alias("_bytes"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "_bytes"):
            x = np.array([text_features(d) for d in batch.column("_bytes").to_pylist()], dtype=np.float64).reshape(batch.num_rows, len(FEATURES))
            yield pa.RecordBatch.from_arrays([*[batch.column(c) for c in columns], pa.array(model.scores(x))], names=[*columns, "_score"])

    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in kept.schema.fields if f.name != "_bytes"), "_score double"])
    return kept.mapInArrow(run, schema)


def score_documents(docs: DataFrame, labels: DataFrame, threshold: float = 0.3, text: str = "text", key: str = "doc_id") -> DataFrame:
    """One row per row of docs: doc_id, held_out, score, predicted.

    Null texts score as empty ones; null ids count as held out; rows that repeat an id are scored
    each; labels that are null or not 0 or 1 are ignored; an empty table gives an empty result;
    further columns of docs are ignored.
    """
    model = train(docs, labels, text=text, key=key)
    scored = with_scores(docs.select(F.col(key).alias("doc_id"), F.col(text).alias("text")), model, ["doc_id"])
    return scored.select("doc_id", in_fold(F.col("doc_id")).alias("held_out"), F.col("_score").alias("score"), (F.col("_score") >= threshold).cast("int").alias("predicted"))


def accepted(docs: DataFrame, labels: DataFrame, threshold: float = 0.3, text: str = "text", key: str = "doc_id") -> DataFrame:
    """The rows of docs, with their columns, whose score reaches the threshold."""
    model = train(docs, labels, text=text, key=key)
    return with_scores(docs, model, docs.columns, text).filter(F.col("_score") >= threshold).select(*docs.columns)


def op1_additive_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score_documents(load(spark, sf_dir, "documents"), load(spark, sf_dir, "labels"))

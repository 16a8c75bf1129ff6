import gzip
import hashlib
import zlib
from pathlib import Path

import numpy as np
import pytest

from sparsecert.llm import quality, warc
from sparsecert.llm.common import load
from sparsecert.llm.quality import FEATURES, accepted, fit, score_documents, text_features
from sparsecert.llm.warc import assemble, read_records, round_trip, write_archives
from tests.llm.common_cases import DOCUMENTS, dicts, documents, prose

SF = "/root/testdata/sf0.01"


def auc(y, p):
    order = np.argsort(p, kind="stable")
    rank = np.empty(len(p))
    rank[order] = np.arange(1, len(p) + 1)
    good = y == 1
    return (rank[good].sum() - good.sum() * (good.sum() + 1) / 2) / (good.sum() * (~good).sum())


def test_tables_learn_steps_and_interactions():
    draw = np.random.default_rng(0)
    x = draw.random((4000, len(FEATURES)))
    y = ((x[:, 0] > 0.5) ^ (x[:, 3] > 0.3)).astype(float)
    model = fit(x[:3000], y[:3000])
    assert auc(y[3000:], model.scores(x[3000:])) > 0.97
    assert {0, 3} == set(model.pairs[0])
    by_hand = model.bias + sum(t[b] for t, b in zip(model.tables, model.bins(x[:1])[0], strict=True)) + sum(t[model.bins(x[:1])[0, i], model.bins(x[:1])[0, j]] for (i, j), t in zip(model.pairs, model.pair_tables, strict=True))
    assert model.margins(x[:1])[0] == pytest.approx(by_hand)


def test_model_without_labels_or_with_one_label():
    none = fit(np.zeros((0, len(FEATURES))), np.zeros(0))
    assert none.scores(np.zeros((2, len(FEATURES)))).tolist() == [0.5, 0.5]
    ones = fit(np.random.default_rng(0).random((50, len(FEATURES))), np.ones(50))
    assert (ones.scores(np.zeros((3, len(FEATURES)))) > 0.9).all()
    assert text_features(b"") == [0.0] * len(FEATURES)
    assert len(text_features(b"word")) == len(FEATURES)


def test_held_out_quality(spark):
    got = score_documents(load(spark, SF, "documents"), load(spark, SF, "labels")).toPandas()
    assert all(h == (zlib.crc32(str(i).encode()) % 5 == 0) for i, h in zip(got.doc_id, got.held_out, strict=True))
    assert got.score.between(0, 1).all()
    assert ((got.score >= 0.3).astype(int) == got.predicted).all()
    both = got.merge(load(spark, SF, "labels").toPandas(), on="doc_id")
    held = both[both.held_out]
    assert auc(held.quality.to_numpy(), held.score.to_numpy()) > 0.9
    clean = held[held.quality == 1]
    assert (clean.predicted == 1).mean() > 0.95


def test_labels_of_held_out_rows_teach_nothing(spark):
    docs, labels = load(spark, SF, "documents"), load(spark, SF, "labels")
    flipped = labels.withColumn("quality", quality.F.when(quality.in_fold(quality.F.col("doc_id")), 1 - quality.F.col("quality")).otherwise(quality.F.col("quality")))
    a, b = (score_documents(docs, x).orderBy("doc_id").toPandas().score.to_numpy() for x in (labels, flipped))
    assert np.array_equal(a, b)


def test_odd_documents_are_scored(spark):
    labels = spark.createDataFrame([(1, 1, 0), (2, 0, 0), (8, None, 0), (9, 7, 1), (None, 1, 1)], "doc_id bigint, quality int, toxic int")
    docs = documents(spark)
    assert score_documents(docs, labels).count() == len(DOCUMENTS)
    assert score_documents(docs, labels.limit(0)).select("score").distinct().count() == 1
    assert score_documents(documents(spark, []), labels).count() == 0
    kept = accepted(docs, labels.limit(0))
    assert kept.columns == docs.columns
    assert kept.count() == len(DOCUMENTS)


BIG = "<p>" + "x" * 1200 + "</p>"
PAGES = [
    (1, "http://a.example/x?y=1#z", BIG), (2, "http://b.example/", BIG), (9, "https://c.example", BIG), (3, None, "small"), (4, "http://a.example/", "small"), (5, "http://a.example/e", None), (6, "http://a.example/e", ""), (7, "bad url\r\nX: y", "ends\r\n\r\n"),
    (8, "http://u.example/", "\r\n\r\nWARC/1.1\r\nContent-Length: 9\r\n\r\nünï\r\n"), (None, "http://n.example/", BIG), (10, "http://r.example/", "twice"), (10, "http://r.example/", "twice"), (11, "http://l.example/", "é\r\n" * 100_000), (12, "http://m.example/", "é\r\n" * 100_000),
]


def pages(spark, rows=None):
    df = spark.createDataFrame(PAGES if rows is None else rows, "page_id bigint, url string, html string")
    for name in ("digest", "bytes", "value", "kind"):
        df = df.selectExpr("*", f"'extra' as {name}")
    return df


def test_archives_come_back_as_they_were(spark):
    got = sorted(tuple(str(v) for v in r.values()) for r in dicts(round_trip(pages(spark))))
    want = []
    for i, _, html in PAGES:
        body = (html or "").encode()
        top = max(j for j, _, h in PAGES if j is not None and (h or "").encode() == body) if i is not None or html else i
        revisit = len(body) >= 1000 and i != top
        want.append((i, len(body), hashlib.sha1(body).hexdigest(), "revisit" if revisit else "response", top if revisit else None))
    assert got == sorted(tuple(str(v) for v in r) for r in want)
    assert round_trip(pages(spark, [])).count() == 0


def test_captures_nest_three_records(spark, tmp_path):
    path = str(tmp_path / "archives")
    write_archives(pages(spark), path)
    rows = assemble(read_records(spark, path, with_payload=True)).collect()
    assert len(rows) == len(PAGES)
    for r in rows:
        assert r.request.record_id != r.response.record_id != r.metadata.record_id
        if r.response.kind == "response":
            assert hashlib.sha1(r.response.payload).hexdigest() == r.response.payload_digest
            assert len(r.response.payload) == r.response.payload_bytes
    by = {r.metadata.page_id: r for r in rows}
    assert by[1].response.refers_to_id == by[9].response.record_id
    assert bytes(by[8].response.payload).decode() == PAGES[8][2]
    whole = b"".join(gzip.decompress(p.read_bytes()) for p in Path(path).glob("*.gz"))
    assert whole.count(b"WARC-Type: request\r\n") == len(PAGES)
    assert whole.endswith(b"\r\n\r\n")


def test_a_changed_payload_is_noticed(spark, tmp_path):
    path = tmp_path / "archives"
    write_archives(pages(spark, [(1, "http://a.example/", "hello world")]), str(path))
    part = next(p for p in path.glob("*.gz") if b"hello world" in gzip.decompress(p.read_bytes()))
    data = gzip.decompress(part.read_bytes()).replace(b"hello world", b"hello earth")
    for crc in path.glob(".*.crc"):
        crc.unlink()
    part.write_bytes(gzip.compress(data))
    with pytest.raises(Exception, match="digest"):
        read_records(spark, str(path)).collect()


def test_pipeline_on_small_tables(spark):
    import corpus_pipeline

    assert [name for name, _ in corpus_pipeline.STAGES] == ["quality", "exact_copies", "near_copies", "mixing", "packing"]
    sf = "/root/testdata/sf0.001"
    docs = load(spark, sf, "documents")
    seen = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = warc.staged(stage(spark, seen, sf), name)
        assert out.columns == docs.columns
        assert out.count() > 0
        if name != "mixing":
            assert out.exceptAll(seen).count() == 0
        if name == "near_copies":
            texts = [r.text for r in out.collect()]
            sets = [{tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} for t in texts if (w := t.split())]
            assert all(len(a & b) < 0.9 * len(a | b) for i, a in enumerate(sets) for b in sets[:i])
        seen = out
    packed = corpus_pipeline.run(spark, sf)
    totals = packed.groupBy("sequence_id").sum("length").collect()
    assert all(r[1] <= 2048 for r in totals)
    assert set(r.doc_id for r in packed.select("doc_id").distinct().collect()) <= set(r.doc_id for r in docs.collect())
    assert prose(1) == prose(1)


def test_a_repeated_id_gives_the_fit_one_row(spark, monkeypatch):
    docs = spark.range(3000).selectExpr("if(id < 2900, 1L, id) AS doc_id", "concat('text ', id) AS text")
    labels = spark.createDataFrame([(1, 1), (1, 1), (2901, 0), (2902, 1), (2903, None)], "doc_id long, quality int")
    seen = []
    real = quality.fit
    monkeypatch.setattr(quality, "fit", lambda x, y: seen.append(len(y)) or real(x, y))
    quality.train(docs, labels)
    assert 1 <= seen[0] <= 3

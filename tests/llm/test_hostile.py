"""Texts that break what even prose doesn't, through every operation and the pipeline; a slow scorer for quality."""

import base64
import bisect
import gzip
import hashlib
import math
import re
import zlib

import pytest

from sparsecert.llm import exactdedup, mixing, neardup, packing, pii, quality, secrets, sharding
from sparsecert.llm.common import load, staged
from tests.llm.common_cases import DOCUMENTS, dicts, documents, prose
from tests.llm.test_scans import slow_personal, slow_secrets

HIDDEN = base64.b64encode(gzip.compress(b"pad " * 800_000 + b"password = layered-value-12345")).decode()
HOSTILE = [
    (1, " " * 1_200_000, "en", "a", 1), (2, "x" * 1_500_000, "en", "a", 1), (3, " ".join(str(i % 97) for i in range(60_000)), "en", "b", 1), (4, "see " + HIDDEN, "en", "b", 1), (5, ("word " * 40_000).strip(), "en", "c", 1),
    (6, "\n" * 300_000 + "end", "en", "c", 1), (7, "a1@" * 50_000, "en", None, 1), (8, "%41" * 100_000, "en", "c", 1), (9, prose(5, 80), "en", "a", 1), (10, prose(5, 80), "en", "a", 1),
]


@pytest.fixture(scope="module")
def hostile(spark):
    return staged(spark.createDataFrame(HOSTILE, "doc_id bigint, text string, lang string, source string, n_chars bigint"), "hostile")


def test_scores(spark, hostile):
    got = dicts(quality.score_documents(hostile, load(spark, "/root/testdata/sf0.01", "labels").limit(50)))
    assert len(got) == len(HOSTILE) and all(0 <= r["score"] <= 1 for r in got)


def test_exact_classes(hostile):
    got = {r["doc_id"]: r for r in dicts(exactdedup.exact_classes(hostile))}
    for i, text, *_ in HOSTILE:
        assert got[i]["text_sha256"] == hashlib.sha256(re.sub(r"[\x20\x09-\x0D]", "", text).encode()).hexdigest()
    assert got[10]["keep_id"] == 9 and sum(r["kept"] for r in got.values()) == len(HOSTILE) - 1


def test_near_classes(hostile):
    got = {r["doc_id"]: r["class_id"] for r in dicts(neardup.near_duplicates(hostile))}
    assert got == {i: 9 if i == 10 else i for i, *_ in HOSTILE}


def test_shards_mix_and_packing(hostile):
    got = dicts(sharding.assign_shards(hostile, sharding.HashTree.of(8)))
    assert {r["doc_id"]: (r["size"], r["text_crc32"]) for r in got} == {i: (len(t.encode()) + 1, zlib.crc32(t.encode())) for i, t, *_ in HOSTILE}
    sizes = {r["doc_id"]: r["size"] for r in dicts(mixing.mix(hostile))}
    assert sizes == {i: len(re.findall(r"[^\x20\x09-\x0D]+", t)) for i, t, *_ in HOSTILE}
    encoder = packing.Encoder(packing.default_vocabulary())
    lengths = {}
    for r in dicts(packing.pack(hostile)):
        lengths[r["doc_id"]] = lengths.get(r["doc_id"], 0) + r["length"]
    assert lengths == {i: len(encoder.ids(t)) + 1 for i, t, *_ in HOSTILE}


def test_scans(hostile):
    personal = {r["doc_id"]: r for r in dicts(pii.scan_documents(hostile))}
    hidden = {r["doc_id"]: r for r in dicts(secrets.scan_documents(hostile))}
    for i, text, *_ in HOSTILE:
        if i in (1, 3, 5, 6, 9, 10):  # the plain pattern takes quadratic time on the others
            assert personal[i]["base_sha256"] == hashlib.sha256(pii.joined(slow_personal(text)).encode()).hexdigest()
        assert hidden[i]["base_sha256"] == hashlib.sha256(secrets.joined(slow_secrets(text)).encode()).hexdigest()
    assert hidden[4]["spans"] == f"assign:4:{4 + len(HIDDEN)}"


def test_the_pipeline_on_odd_rows(spark, tmp_path):
    """Each stage on what its predecessor kept: nulls, repeated ids, ties, further columns, and nothing at all."""
    import corpus_pipeline

    spark.createDataFrame([(1, 1, 0), (2, 1, 0), (9, 1, 0)], "doc_id bigint, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    for rows in (DOCUMENTS, HOSTILE, []):
        docs = documents(spark, rows)
        seen = docs
        for name, stage in corpus_pipeline.STAGES:
            out = staged(stage(spark, seen, str(tmp_path)), name)
            if name != "packing":
                assert out.columns == docs.columns
                if name != "mixing":
                    assert out.exceptAll(seen).count() == 0
                assert bool(out.count()) == bool(rows), name
                seen = out
        assert bool(out.count()) == bool(rows)
        if rows is DOCUMENTS:
            texts = {r["text"] for r in dicts(seen)}
            assert prose(1) + " tail" not in texts or prose(1) not in texts, "one of the near copies stays"


def test_scores_of_a_slow_scorer(spark):
    """Features counted sign by sign, bins by searching their edges, table entries added one by one."""
    docs, labels = load(spark, "/root/testdata/sf0.001", "documents"), load(spark, "/root/testdata/sf0.001", "labels")
    model = quality.train(docs, labels)

    def slow(text):
        data = (text or "").encode()
        if not data:
            return [0.0] * len(quality.FEATURES)
        count = lambda some: sum(data.count(bytes([b])) for b in some)
        words, lines, n = data.split(), data.split(b"\n"), len(data)
        total, upper, lower = len(words) or 1, count(range(65, 91)), count(range(97, 123))
        sizes = [len(w) for w in words] or [0]
        return [
            math.log(1 + n), upper / max(1, upper + lower), count(b"#$%&*+<=>@[]^_`{}~\\/") / n, count(b"!") / total, count(b"|") / total, count(b"0123456789") / n, total / n, len(lines) / total, count(b".,") / total, sum(b > 127 for b in data) / n,
            sum(sizes) / len(sizes), len(set(words)) / total, sum(s <= 3 for s in sizes) / len(sizes), len(set(lines)) / len(lines), math.log(1 + max(sizes)), sum(a == b for a, b in zip(words, words[1:], strict=False)) / total, count(b"?:;") / total,
        ]

    text = {r.doc_id: r.text for r in docs.select("doc_id", "text").collect()}
    for r in dicts(quality.score_documents(docs, labels)):
        x = slow(text[r["doc_id"]])
        place = [bisect.bisect_right(e.tolist(), x[j]) for j, e in enumerate(model.edges)]
        margin = model.bias + sum(t[place[j]] for j, t in enumerate(model.tables)) + sum(t[place[i]][place[j]] for (i, j), t in zip(model.pairs, model.pair_tables, strict=True))
        assert r["score"] == pytest.approx(1 / (1 + math.exp(-margin)), abs=1e-9)
        assert r["predicted"] == (r["score"] >= 0.3)

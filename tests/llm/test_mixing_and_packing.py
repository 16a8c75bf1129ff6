import re
import zlib
from array import array

import pytest

from sparsecert.llm import mixing, packing
from sparsecert.llm.mixing import mix, mixed_documents, source_targets
from sparsecert.llm.packing import best_fit, pack, pieces_of
from tests.llm.common_cases import DOCUMENTS, dicts, documents

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def filled(sizes, share=1.5, most=2):
    """Targets by rounds: what goes beyond a cap is spread again by weight."""
    order = sorted(sizes, key=lambda s: (s is None, s or ""))
    weight = {s: (3, 1, 2)[i % 3] for i, s in enumerate(order)}
    target, open_, left = {}, set(order), share * sum(sizes.values())
    while open_:
        total = sum(weight[s] for s in open_)
        over = {s for s in open_ if left * weight[s] / total > most * sizes[s]}
        if not over:
            return target | {s: left * weight[s] / total for s in open_}
        for s in over:
            target[s] = most * sizes[s]
            left -= target[s]
        open_ -= over
    return target


@pytest.mark.parametrize("sizes", [{"a": 10, "b": 20, "c": 5}, {"a": 1000, "b": 10, "c": 10, None: 3}, {"a": 0, "b": 7}, {"x": 4}, {f"s{i}": (i * 37) % 101 for i in range(20)}])
def test_targets(spark, sizes):
    df = spark.createDataFrame(list(sizes.items()), "source string, source_size bigint")
    got = {r.source: r.target for r in source_targets(df).collect()}
    want = filled(sizes)
    assert got == pytest.approx(want)
    assert sum(got.values()) == pytest.approx(1.5 * sum(sizes.values()))


def test_mix_meets_its_targets(spark):
    rows = [(i, " ".join(["w"] * (1 + i * 7 % 50)), "en", f"s{i % 4}" if i % 9 else None, 1) for i in range(200)] + DOCUMENTS
    got = dicts(mix(documents(spark, rows)))
    assert len(got) == len(rows)
    assert sorted(r["size"] for r in got) == sorted(len(WORD.findall(t or "")) for _, t, *_ in rows)
    assert all(0 <= r["taken"] <= 2 * r["size"] for r in got)
    by = {}
    for (_, _, _, source, _), target in ((r, None) for r in rows):
        by.setdefault(source, target)
    for target in {(r["source_size"], r["target"]) for r in got}:
        mine = [r for r in got if (r["source_size"], r["target"]) == target]
        assert sum(r["taken"] for r in mine) == int(target[1] + 0.5)
    again = dicts(mix(documents(spark, rows).repartition(7)))
    key = lambda r: (r["doc_id"] is None, r["doc_id"] or 0, r["size"], r["taken"])
    assert sorted(got, key=key) == sorted(again, key=key)
    assert mix(documents(spark, [])).count() == 0


def test_mixed_documents_repeat_and_cut(spark):
    rows = [(i, f"a{i} b c d e", "en", "s" if i % 2 else "t", 1) for i in range(40)]
    docs = documents(spark, rows)
    out = mixed_documents(docs)
    assert out.columns == docs.columns
    words = {r["source"]: 0 for r in dicts(out)}
    for r in dicts(out):
        words[r["source"]] += len(r["text"].split())
    targets = {r["doc_id"]: r["target"] for r in dicts(mix(docs))}
    assert words["s"] == int(targets[1] + 0.5)
    assert words["t"] == int(targets[0] + 0.5)
    assert "Python" not in mixed_documents(docs)._jdf.queryExecution().toString()


def test_mixed_documents_agree_with_the_mix(spark):
    """Words by id are those that mix takes, null ids and sources included; copies at the cut share what is left."""
    rows = [(i if i % 13 else None, " ".join([f"w{i}"] * (1 + i * 7 % 50)), "en", f"s{i % 4}" if i % 9 else None, 1) for i in range(200)]
    docs = documents(spark, rows)
    want, got = {}, {}
    for r in dicts(mix(docs)):
        want[r["doc_id"]] = want.get(r["doc_id"], 0) + r["taken"]
    for r in dicts(mixed_documents(docs)):
        got[r["doc_id"]] = got.get(r["doc_id"], 0) + len(r["text"].split())
    assert got == {i: n for i, n in want.items() if n}
    copies = documents(spark, [(7, "a b c d e", "en", "s", 1)] * 30 + [(8, "f g h", "en", "t", 1)] * 3)
    words = sum(len(r["text"].split()) for r in dicts(mixed_documents(copies)))
    assert 0 <= 1.5 * (150 + 9) - words <= 33


def test_no_text_at_all(spark):
    got = dicts(mix(documents(spark, [(1, None, None, None, None), (2, "", None, "a", 0)])))
    assert [r["taken"] for r in got] == [0, 0]
    assert mixed_documents(documents(spark, [(1, None, None, None, None)])).count() == 0


def test_pieces():
    assert pieces_of(5, 10) == [(0, 5)]
    assert pieces_of(20, 10) == [(0, 10), (10, 10)]
    assert pieces_of(23, 10) == [(0, 3), (3, 10), (13, 10)]


def test_best_fit_takes_the_fullest_bin():
    assert sorted(map(sorted, best_fit([6, 5, 4, 3, 2], 10))) == [[0, 2], [1, 3, 4]]
    assert best_fit([], 10) == []


def reference_ids(text):
    import public_tokenizers
    from tokenizers import Tokenizer

    return Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json")).encode(text or "", add_special_tokens=False).ids + [0]


def test_ids_are_those_of_tokenizers_on_any_text():
    """Runs of millions too, on which the split pattern's engine fails when it meets them whole."""
    encoder = packing.Encoder(packing.default_vocabulary())
    blanks = " \t\n\x85\xa0\u2003\u3000"
    for text in ("", " ", "a" * 1_000_000, " " * 1_500_000, "x" + " " * 1_200_000 + "y z", "\n" * 1_100_000 + "\u00a0end", (blanks * 20_000)[:-1] + "q" + blanks * 20_000, "7" * 300_000 + "#" * 300_000, "\x1c" * 20_000, "ab<|endoftext|>" + " " * 700_000 + "<|endoftext|>c", "\u6f22" * 100_000):
        assert [*encoder.ids(text), 0] == reference_ids(text), text[:20]
    import random

    draw = random.Random(8)
    for _ in range(400):
        text = "".join(draw.choice(["a", "Z", "9", " ", "  ", "\n", "'s", "'ll", ".", "\u00fc", "\u6f22", "\x00", "\x1f", "<|endoftext|>", "\ud7ff", "\U0001f600"]) for _ in range(draw.randrange(60)))
        assert [*encoder.ids(text), 0] == reference_ids(text)


def test_cutting_at_long_blanks_keeps_ids(monkeypatch):
    """With runs of two blanks cut, every text is cut somewhere."""
    import random

    encoder, draw = packing.Encoder(packing.default_vocabulary()), random.Random(9)
    monkeypatch.setattr(packing, "BLANK_RUN", re.compile(packing.BLANK_RUN.pattern.replace("10000", "2")))
    for _ in range(300):
        text = "".join(draw.choice(["word", "9", " ", "   ", "\n\n", "\t ", "'s", ".", "\xa0", "\u3000 "]) for _ in range(40))
        assert [*encoder._ordinary(text * 100), 0] == reference_ids(text * 100)


def check_packing(got, rows, capacity):
    whole = {}
    for r in got:
        whole.setdefault(r["sequence_id"], []).append(r)
    for members in whole.values():
        at = 0
        for r in sorted(members, key=lambda r: r["offset"]):
            assert r["offset"] == at
            at += r["length"]
        assert at <= capacity
    want = []
    for i, text, *_ in rows:
        ids = reference_ids(text)
        for piece, (start, length) in enumerate(pieces_of(len(ids), capacity)):
            want.append((i is None, i or 0, piece, start, length, zlib.crc32(array("I", ids[start : start + length]).tobytes())))
    assert sorted((r["doc_id"] is None, r["doc_id"] or 0, r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in got) == sorted(want)
    return len(whole)


def test_packing_is_exact_and_tight(spark):
    rows = DOCUMENTS + [(100 + i, " ".join(["word"] * (i * 31 % 400)), "en", "s", 1) for i in range(150)]
    used = check_packing(dicts(pack(documents(spark, rows))), rows, 2048)
    tokens = sum(len(reference_ids(t)) for _, t, *_ in rows)
    assert used <= -(-tokens // 2048) + 2
    assert pack(documents(spark, [])).count() == 0


def test_rounds_of_many_partitions(spark, monkeypatch):
    rows = [(i, " ".join(["word"] * (i * 37 % 61)), "en", "s", 1) for i in range(400)]
    real = packing.pack_items
    monkeypatch.setattr(packing, "pack_items", lambda items, capacity: real(items, capacity, most_items=25))
    used = check_packing(dicts(pack(documents(spark, rows), capacity=64)), rows, 64)
    assert used <= 1.15 * sum(len(reference_ids(t)) for _, t, *_ in rows) / 64


def test_sql_of_mixing_names_the_same_weights():
    assert mixing.WEIGHTS == (3, 1, 2)

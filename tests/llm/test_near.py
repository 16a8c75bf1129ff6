import itertools

import numpy as np
import pytest

from sparsecert.llm import neardup, vectors
from sparsecert.llm.neardup import Sampler, Shingler, band_keys, near_duplicates, one_of_each
from sparsecert.llm.vectors import link_vectors
from tests.llm.common_cases import DOCUMENTS, dicts, documents, prose


def grams(text):
    words = (text or "").split()
    return {tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4))} if words else set()


def edited(text, at):
    words = text.split()
    words[at % len(words)] = f"edit{at}"
    return " ".join(words)


def test_shingles_are_those_of_words():
    texts = ["a b c d e f", " a  b\tc d\ne", "x y", "", "a b c d e f"]
    owner, shingles, counts = Shingler().of([t.encode() for t in texts])
    sets = [set(shingles[owner == i].tolist()) for i in range(5)]
    assert [len(s) for s in sets] == [2, 1, 1, 0, 2]
    assert sets[0] == sets[4]
    assert sets[1] < sets[0]
    assert counts.tolist() == [1] * 6
    assert Shingler().of([b"q q q q q q q"])[2].tolist() == [3]


def test_words_cut_by_a_stretch_have_one_hash(monkeypatch):
    """With stretches of a few signs every text is cut; hashes and places are those of whole words."""
    draw = np.random.default_rng(6)
    monkeypatch.setattr(neardup, "STRETCH", 1 << 12)
    whole = Shingler()
    for size in (1, 2, 3, 7, 64):
        monkeypatch.setattr(neardup, "STRETCH", size)
        part = Shingler()
        for _ in range(40):
            data = np.frombuffer(bytes(draw.choice(list(b"ab \n"), int(draw.integers(0, 90)))), dtype=np.uint8)
            monkeypatch.setattr(neardup, "STRETCH", 1 << 12)
            want = whole.word_hashes(data)
            monkeypatch.setattr(neardup, "STRETCH", size)
            got = part.word_hashes(data)
            assert all(np.array_equal(x, y) for x, y in zip(got, want, strict=True))


def test_signatures_agree_as_often_as_weighted_sets_do():
    draw = np.random.default_rng(0)
    sampler = Sampler(hashes=512)
    ids = draw.integers(0, 1 << 40, 300).astype(np.uint64)
    a, b = np.sort(ids[:200]), np.sort(ids[100:])
    for level in (0, 6):
        sig = sampler.signatures(np.array([0, 200]), np.concatenate([a, b]), np.full(400, level))
        assert abs((sig[0] == sig[1]).mean() - 100 / 300) < 0.08
    mixed = np.concatenate([np.full(200, 8), np.zeros(200, dtype=np.int64)])
    sig = sampler.signatures(np.array([0, 200]), np.concatenate([a, b]), mixed)
    heavy = neardup.GRID**8
    assert abs((sig[0] == sig[1]).mean() - 100 / (200 * heavy + 100)) < 0.06
    assert band_keys(sig[:, : neardup.BANDS * neardup.ROWS]).shape == (2, neardup.BANDS)


def test_near_copies_meet_and_others_do_not(spark):
    base = [prose(s, 150) for s in range(20)]
    rows = [(i, t, "en", "a", 1) for i, t in enumerate(base)]
    rows += [(100 + 10 * i + j, edited(base[i], 13 * j + 1), "en", "a", 1) for i in range(6) for j in range(4)]
    rows += [(300 + i, " ".join(t.split()[:75]) + " " + prose(500 + i, 75), "en", "a", 1) for i, t in enumerate(base[6:10])]
    got = {r["doc_id"]: r for r in dicts(near_duplicates(documents(spark, rows)))}
    sets = {i: grams(t) for i, t, *_ in rows}
    for a, b in itertools.combinations(sets, 2):
        j = len(sets[a] & sets[b]) / len(sets[a] | sets[b])
        if j >= 0.85:
            assert got[a]["class_id"] == got[b]["class_id"]
        if j < 0.5:
            assert got[a]["class_id"] != got[b]["class_id"]
    for r in got.values():
        assert r["kept"] == (r["doc_id"] == r["class_id"])
        assert r["class_size"] == sum(x["class_id"] == r["class_id"] for x in got.values())


def test_a_group_larger_than_a_task(spark, monkeypatch):
    """Two families share bands: hubs join most, and what is left meets all."""
    monkeypatch.setattr(neardup, "CHUNK", 8)
    monkeypatch.setattr(neardup, "HUBS", 2)
    base = prose(1, 200)
    other = " ".join([*base.split()[:150], *prose(2, 50).split()])
    rows = [(i, edited(base, i), "en", "a", 1) for i in range(40)] + [(100 + i, edited(other, i), "en", "a", 1) for i in range(20)]
    got = {r["doc_id"]: r["class_id"] for r in dicts(near_duplicates(documents(spark, rows)))}
    assert {got[i] for i in range(40)} == {0}
    assert {got[100 + i] for i in range(20)} == {100}


def test_texts_outside_the_main_component_meet_all_in_blocks(spark, monkeypatch):
    """With blocks of a few texts; links are those of all pairs whose weighted similarity reaches the threshold."""
    monkeypatch.setattr(neardup, "CHUNK", 8)
    monkeypatch.setattr(neardup, "HUBS", 2)
    monkeypatch.setattr(neardup, "MEET_BYTES", 4000)
    base = prose(1, 200)
    families = [base, " ".join([*base.split()[:150], *prose(2, 50).split()]), " ".join([*base.split()[:140], *prose(3, 60).split()])]
    rows = [(100 * f + i, edited(t, i), "en", "a", 1) for f, t in enumerate(families) for i in range(25)]
    got = {r["doc_id"]: r["class_id"] for r in dicts(near_duplicates(documents(spark, rows)))}
    assert [{got[100 * f + i] for i in range(25)} for f in range(3)] == [{0}, {100}, {200}]


def test_links_at_the_threshold_against_all_pairs(spark):
    """Classes are the components of all pairs of 0.8 or more under the operator's own weights, found by brute force."""
    from sparsecert.llm.neardup import GRID, levels, shingle_weights, similarity

    draw = np.random.default_rng(17)
    rows = []
    for f in range(30):
        words = prose(900 + f, 120).split()
        rows.append((100 * f, " ".join(words), "en", "a", 1))
        for i in range(1, 5):  # each copy has more places changed: similarities from 0.95 down to 0.5
            other = list(words)
            for at in draw.choice(120, int(draw.integers(1, 7)), replace=False):
                other[at] = f"new{f}x{i}x{at}"
            rows.append((100 * f + i, " ".join(other), "en", "a", 1))
    docs = documents(spark, rows)
    got = {r["doc_id"]: r["class_id"] for r in dicts(near_duplicates(docs))}
    weights = shingle_weights(docs.select(neardup.F.col("text").cast("binary").alias("_bytes")))
    owner, shingles, counts = Shingler().of([t.encode() for _, t, *_ in rows])
    sets = [(shingles[owner == n], GRID ** levels(shingles[owner == n], counts[owner == n], weights).astype(float)) for n in range(len(rows))]
    label = list(range(len(rows)))
    found = lost = 0
    for a, b in itertools.combinations(range(len(rows)), 2):
        if similarity(sets[a], sets[b]) >= neardup.THRESHOLD:
            found += 1
            lost += got[rows[a][0]] != got[rows[b][0]]
            old, new = max(label[a], label[b]), min(label[a], label[b])
            label = [new if x == old else x for x in label]
    assert found > 40
    assert lost <= 0.02 * found
    for a, b in itertools.combinations(range(len(rows)), 2):
        if got[rows[a][0]] == got[rows[b][0]]:
            assert label[a] == label[b], "no class joins what no chain of links joins"


def test_odd_documents(spark):
    got = dicts(near_duplicates(documents(spark)))
    assert len(got) == len(DOCUMENTS)
    by = {}
    for r in got:
        by.setdefault(r["doc_id"], []).append(r)
    assert by[1][0]["class_id"] == by[2][0]["class_id"] == by[3][0]["class_id"] == by[10][0]["class_id"] == 1
    assert by[4][0]["kept"] and by[5][0]["kept"] and by[6][0]["kept"], "texts without words stand alone"
    assert sorted(r["kept"] for r in by[9]) == [False, True]
    assert sorted(r["kept"] for r in by[None]) == [False, True]
    docs = documents(spark)
    out = one_of_each(docs)
    assert out.columns == docs.columns
    assert out.count() == sum(r["kept"] for r in got)
    assert near_duplicates(documents(spark, [])).count() == 0
    assert one_of_each(documents(spark, [])).count() == 0


def brute(x, ok, threshold=0.95):
    unit = np.where(ok[:, None], x / np.maximum(np.linalg.norm(x, axis=1)[:, None], 1e-300), 0)
    hit = (unit @ unit.T >= threshold) & ok[:, None] & ok[None]
    np.fill_diagonal(hit, False)
    label = np.arange(len(x))
    for _ in range(len(x)):
        new = np.array([min([label[i], *label[hit[i]]]) for i in range(len(x))])
        if (new == label).all():
            break
        label = new
    return hit.sum(1), label


@pytest.mark.parametrize(("spread", "window"), [(0.02, 512), (0.12, 16)])
def test_vectors_against_brute_force(spark, spread, window, monkeypatch):
    monkeypatch.setattr(vectors, "BLOCK", 16)
    draw = np.random.default_rng(3)
    centres = draw.standard_normal((30, 16))
    x = np.concatenate([draw.standard_normal((150, 16)), (centres[draw.integers(0, 5, 150)] + spread * draw.standard_normal((150, 16))), np.tile(centres[:1], (4, 1)), centres[:1] * 3])
    rows = [(i, [float(v) for v in r]) for i, r in enumerate(x)]
    df = spark.createDataFrame(rows, "vec_id bigint, embedding array<double>").selectExpr("*", "1 as n", "'x' as rep", "2 as row")
    got = {r["vec_id"]: r for r in dicts(link_vectors(df, window=window))}
    links, label = brute(x, np.ones(len(x), dtype=bool))
    assert [got[i]["n_links"] for i in range(len(x))] == links.tolist()
    assert [got[i]["component_id"] for i in range(len(x))] == label.tolist()
    assert all(r["kept"] == (r["vec_id"] == r["component_id"]) for r in got.values())


@pytest.mark.parametrize("blocks", [True, False])
def test_a_dense_cluster_of_a_third_of_the_rows(spark, blocks, monkeypatch):
    """Its vectors share many signs and few links: pairs at the threshold are found there as elsewhere."""
    if not blocks:
        monkeypatch.setattr(vectors, "_crowd_links", lambda crowd, *_: spark.createDataFrame([], "u bigint, v bigint"))
    draw = np.random.default_rng(9)
    unit = lambda x: x / np.linalg.norm(x, axis=1, keepdims=True)
    a, b = unit(draw.standard_normal((500, 64))), unit(draw.standard_normal((500, 64)))
    near = unit(0.8875 * a + 0.461 * b)
    centre = unit(draw.standard_normal((1, 64)))
    dense = unit(np.concatenate([1.83 * centre + a, 1.83 * centre + near]))
    x = np.concatenate([dense, draw.standard_normal((2000, 64))])
    df = spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(x)], "vec_id bigint, embedding array<double>")
    got = {r["vec_id"]: r for r in dicts(link_vectors(df, window=16))}
    links, _ = brute(x, np.ones(len(x), dtype=bool))
    assert 800 < links.sum() < 2000
    found = sum(got[i]["n_links"] for i in range(len(x)))
    assert found == links.sum() if blocks else found >= 0.9 * links.sum()


def test_odd_vectors(spark):
    nan, inf = float("nan"), float("inf")
    rows = [(1, [1.0, 0.0]), (2, [1.0, 0.0]), (3, None), (4, []), (5, [0.0, 0.0]), (6, [nan, 1.0]), (7, [inf, 1.0]), (8, [None, 1.0]), (9, [1.0, 0.0, 0.0]), (None, [2.0, 0.0]), (10, [1e30, 1.0]), (11, [-1.0, 0.0])]
    df = spark.createDataFrame(rows, "vec_id bigint, embedding array<float>")
    got = {r["vec_id"]: r for r in dicts(link_vectors(df))}
    assert {i for i, r in got.items() if r["n_links"]} == {1, 2, None, 10}
    assert {got[i]["component_id"] for i in (1, 2, None, 10)} == {1}
    assert all(got[i]["n_links"] == 3 for i in (1, 2, None, 10))
    assert all(got[i]["component_id"] == i and got[i]["kept"] for i in (3, 4, 5, 6, 7, 8, 9, 11))
    assert link_vectors(spark.createDataFrame([], "vec_id bigint, embedding array<float>")).count() == 0


def test_passes_grow_with_the_table():
    assert vectors.passes_for(1000, 512, 0.95) <= vectors.passes_for(10**6, 512, 0.95) <= vectors.passes_for(10**9, 512, 0.95) < 100

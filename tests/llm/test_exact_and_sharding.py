import hashlib
import random
import zlib

import pytest
import xxhash

from sparsecert.llm import exactdedup, sharding
from sparsecert.llm.common import load
from sparsecert.llm.exactdedup import Fingerprint, exact_classes, without_copies
from sparsecert.llm.sharding import HashTree, assign_shards
from tests.llm.common_cases import DOCUMENTS, dicts, documents


def plain(text):
    return (text or "").translate({ord(c): None for c in " \t\n\x0b\x0c\r"})


def check_classes(got, rows):
    groups = {}
    for i, t, *_ in rows:
        groups.setdefault(plain(t), []).append((-len(t or ""), i is None, i))
    assert len(got) == len(rows)
    for key, members in groups.items():
        mine = [r for r in got if r["text_sha256"] == hashlib.sha256(key.encode()).hexdigest()]
        assert len(mine) == len(members)
        assert {r["group_size"] for r in mine} == {len(members)}
        assert {r["keep_id"] for r in mine} == {min(members, key=lambda m: (m[0], m[1], m[2] or 0))[2]}
        assert sum(r["kept"] for r in mine) == 1


def test_fingerprints_combine_by_length():
    f = Fingerprint()
    draw = random.Random(1)
    data = bytes(draw.randrange(256) for _ in range(30_000))
    for cut in (0, 1, 8191, 8192, 8193, 20_000, 30_000):
        assert f.join(f.of(data[:cut]), f.of(data[cut:]), len(data) - cut) == f.of(data)
    slow = [0] * 4
    for b in data[:500]:
        slow = [(h * base + b + 1) % exactdedup.PRIME for h, base in zip(slow, f.bases, strict=True)]
    assert tuple(slow) == f.of(data[:500])


def test_exact_classes_on_odd_rows(spark):
    check_classes(dicts(exact_classes(documents(spark))), DOCUMENTS)
    assert exact_classes(documents(spark, [])).count() == 0


def test_equal_fingerprints_of_unequal_texts_part_in_the_next_round(spark):
    """With fingerprints that only tell lengths, texts of a length collide at first."""

    def weak(df, text, seed):
        real = exactdedup.with_fingerprints(df, text, seed)
        return real.selectExpr(*[c for c in real.columns if c not in ("_f1", "_f2")], "bigint(0) as _f1", "bigint(0) as _f2") if seed < 2 else real

    rows = [(i, t, "en", "s", 1) for i, t in enumerate(["abc", "a bc", "abd", "xyz", "ab d", "zz", "z z", "q" * 200_000, "q" * 199_999 + "r"])]
    check_classes(dicts(exact_classes(documents(spark, rows), hasher=weak)), rows)


def test_pieces_of_long_texts_are_hashed_apart(spark):
    """Dealt in pieces or whole, a text has one fingerprint; classes are those of brute force."""
    rows = [(i, t, "en", "s", 1) for i, t in enumerate(["ab " * 5000, "ab" * 5000, "ab" * 4999 + "ac", "c" * 2560, "c" * 2561, " " * 9000, "é" * 3000 + "\t", "é" * 3000, None, "x"])]
    dealt = lambda df, text, seed: exactdedup.with_fingerprints(df, text, seed, longest=500, piece=256)
    check_classes(dicts(exact_classes(documents(spark, rows), hasher=dealt)), rows)
    docs = documents(spark, rows).coalesce(1).withColumn("_row", exactdedup.F.monotonically_increasing_id())
    prints = [sorted((r["_row"], r["_f1"], r["_f2"], r["_len"], r["_sha"]) for r in dicts(f)) for f in (dealt(docs, "text", 3), exactdedup.with_fingerprints(docs, "text", 3))]
    assert prints[0] == prints[1]


def hot_rows(n=30_000):
    """A third of all rows share one id, another third has none."""
    return [(None if i % 3 == 0 else 7 if i % 3 == 1 else i, f"w{i % 11} " * (i % 5), "en", f"s{min(i % 4, 1)}", 1) for i in range(n)]


def test_slots_of_hot_ids_are_gapless_and_spread(spark):
    rows = hot_rows()
    out = assign_shards(documents(spark, rows), HashTree.of(8))
    got = dicts(out)
    for shard in range(8):
        assert sorted(r["slot"] for r in got if r["shard"] == shard) == list(range(sum(r["shard"] == shard for r in got)))


def test_prefix_stretches_are_even_whatever_the_keys(spark):
    from sparsecert.llm import prefix
    from sparsecert.llm.common import staged

    df = staged(spark.range(20_000).selectExpr("id", "case when id % 3 = 0 then 'hot' else 'cold' end as g", "int(id % 3 = 0) as k", "id % 7 as x"), "prefix")
    got = prefix.prefix_before(df, "g", ["k", "id"], prefix.F.col("x"), "before", 20_000, rows_per_stretch=1000).collect()
    for g in ("hot", "cold"):
        total = 0
        for r in sorted((r for r in got if r["g"] == g), key=lambda r: r["id"]):
            assert r["before"] == total
            total += r["x"]
    parts = df.repartitionByRange(20, "g", "k", "id").groupBy(prefix.F.spark_partition_id()).count().collect()
    assert max(r["count"] for r in parts) < 2000


def test_shards_against_a_plain_walk_of_the_tree(spark):
    """The draws, recomputed outside Spark with an xxhash of the key and the child's name."""
    import math

    def draw(seed, name, weight):
        h = xxhash.xxh64(name.encode(), seed=xxhash.xxh64(seed.encode(), seed=42).intdigest()).intdigest()
        return math.log(((h >> 11) + 0.5) / float(1 << 53)) / weight

    tree = HashTree.of(8).reweighted(3, 2.5).grown(8)
    got = spark.range(500).select("id", sharding.shard_of(sharding.F.col("id"), tree).alias("s")).collect()
    for r in got:
        key = f"k{r['id']}"
        i = max(range(len(tree.regions)), key=lambda i: draw(key, f"r{i}", sum(sum(rack.values()) for rack in tree.regions[i])))
        j = max(range(len(tree.regions[i])), key=lambda j: draw(key, f"r{i}/k{j}", sum(tree.regions[i][j].values())))
        want = max(tree.regions[i][j], key=lambda s: draw(key, f"r{i}/k{j}/s{s}", tree.regions[i][j][s]))
        assert r["s"] == want


def test_without_copies_keeps_columns(spark):
    docs = documents(spark)
    out = without_copies(docs)
    assert out.columns == docs.columns
    assert sorted(plain(r.text) for r in out.collect()) == sorted({plain(t) for _, t, *_ in DOCUMENTS})


def test_shards(spark):
    tree = HashTree.of(8)
    got = dicts(assign_shards(documents(spark), tree, grown=tree.grown(8)))
    assert len(got) == len(DOCUMENTS)
    assert sorted((r["size"], r["text_crc32"]) for r in got) == sorted((len((t or "").encode()) + 1, zlib.crc32((t or "").encode())) for _, t, *_ in DOCUMENTS)
    for shard in range(8):
        slots = sorted(r["slot"] for r in got if r["shard"] == shard)
        assert slots == list(range(len(slots)))
    assert all(r["grown_shard"] in (r["shard"], 8) for r in got)
    for key in {r["doc_id"] for r in got}:
        assert len({r["shard"] for r in got if r["doc_id"] == key}) == 1
    assert assign_shards(documents(spark, []), tree).count() == 0


def test_growth_moves_keys_only_into_the_new_shard(spark):
    for n in range(8, 12):
        old, new = HashTree.of(n), HashTree.of(n + 1)
        rows = spark.range(4000).select(sharding.shard_of(sharding.F.col("id"), old).alias("a"), sharding.shard_of(sharding.F.col("id"), new).alias("b")).collect()
        assert all(r.b in (r.a, n) for r in rows)
        moved = sum(r.b == n for r in rows)
        assert 0.6 < moved / (4000 / (n + 1)) < 1.4


def test_a_new_weight_moves_keys_along_its_path_only(spark):
    old = HashTree.of(8)
    lighter, heavier = old.reweighted(5, 0.5), old.reweighted(5, 2.0)
    key = sharding.F.col("id")
    rows = spark.range(6000).select(*[sharding.shard_of(key, t).alias(n) for n, t in (("a", old), ("low", lighter), ("high", heavier))]).collect()
    assert all(not (r.a in (0, 1, 2, 3) and r.low != r.a) for r in rows), "a lighter region only loses keys"
    assert all(not (r.a in (6, 7) and r.low in (5,)) for r in rows)
    assert all(not (r.a == 5 and r.high != 5) for r in rows), "a heavier shard keeps what it has"
    assert sum(r.high == 5 for r in rows) > sum(r.a == 5 for r in rows) > sum(r.low == 5 for r in rows)


def test_shards_are_near_even(spark):
    n = 8000
    counts = spark.range(n).select(sharding.shard_of(sharding.F.col("id"), HashTree.of(8)).alias("s")).groupBy("s").count().collect()
    assert len(counts) == 8
    assert all(abs(r["count"] - n / 8) < 0.15 * n / 8 for r in counts)
    with pytest.raises(ValueError):
        sharding.shard_of(sharding.F.col("id"), HashTree(()))


def test_native_plans(spark):
    docs = load(spark, "/root/testdata/sf0.001", "documents")
    plan = assign_shards(docs, HashTree.of(8))._jdf.queryExecution().toString()
    assert "Python" not in plan
    assert "Arrow" not in plan

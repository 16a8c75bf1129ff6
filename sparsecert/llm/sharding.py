"""Hierarchical weighted hash tree: region, rack and shard are chosen by weighted hash draws.

At each level every child draws ln(u) / weight, u being a hash of the key and the child's name, and
the largest draw wins. A child's weight is the sum of the shards below it, so a change of a weight
moves keys only into or out of the subtrees on that shard's path. `grown` adds a shard as a region
of its own: all keys that move then go to the new shard.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from sparsecert.llm.common import load, staged
from sparsecert.llm.prefix import prefix_before

UNIT = float(1 << 53)


@dataclass(frozen=True)
class HashTree:
    """regions[i][j] maps a shard number to its weight; names of nodes follow from their places."""

    regions: tuple[tuple[dict[int, float], ...], ...]

    @staticmethod
    def of(shards: int, base: int = 8, racks: int = 2, regions: int = 2) -> HashTree:
        """The first `base` shards in regions x racks of equal size; each further shard is a region of its own."""
        first = list(range(min(shards, base)))
        per_region = -(-len(first) // regions)
        tree = []
        for r in range(0, len(first), per_region or 1):
            part = first[r : r + per_region]
            per_rack = -(-len(part) // racks)
            tree.append(tuple({s: 1.0 for s in part[k : k + per_rack]} for k in range(0, len(part), per_rack)))
        out = HashTree(tuple(tree))
        for s in range(base, shards):
            out = out.grown(s)
        return out

    def grown(self, shard: int, weight: float = 1.0) -> HashTree:
        return HashTree((*self.regions, ({shard: weight},)))

    def reweighted(self, shard: int, weight: float) -> HashTree:
        return HashTree(tuple(tuple({s: weight if s == shard else w for s, w in rack.items()} for rack in region) for region in self.regions))

    def shards(self) -> list[int]:
        return [s for region in self.regions for rack in region for s in rack]


def _drawn(key: Column, children: Column) -> Column:
    """The index of the child with the largest draw. children: array of (name, weight, index)."""

    def draw(child: Column) -> Column:
        u = (F.shiftrightunsigned(F.xxhash64(key, child["name"]), 11) + F.lit(0.5)) / F.lit(UNIT)
        return F.struct((F.log(u) / child["weight"]).alias("draw"), child["index"].alias("index"))

    return F.array_max(F.transform(children, draw))["index"]


def _children(rows: list[tuple[str, float, int]]) -> Column:
    return F.array(*[F.struct(F.lit(n).alias("name"), F.lit(float(w)).alias("weight"), F.lit(int(i)).alias("index")) for n, w, i in rows if w > 0])


def shard_of(key: Column, tree: HashTree) -> Column:
    """The shard of a key. Null keys share one place; shards of weight 0 get nothing."""
    name = key.cast("string")
    name = F.coalesce(F.concat(F.lit("k"), name), F.lit("null"))
    live = [(i, [(j, {s: w for s, w in rack.items() if w > 0}) for j, rack in enumerate(region)]) for i, region in enumerate(tree.regions)]
    live = [(i, [(j, rack) for j, rack in region if rack]) for i, region in live]
    live = [(i, region) for i, region in live if region]
    if not live:
        raise ValueError("the tree has no shard of positive weight")
    regions = _children([(f"r{i}", sum(sum(rack.values()) for _, rack in region), n) for n, (i, region) in enumerate(live)])
    racks = F.array(*[_children([(f"r{i}/k{j}", sum(rack.values()), m) for m, (j, rack) in enumerate(region)]) for i, region in live])
    leaves = F.array(*[F.array(*[_children([(f"r{i}/k{j}/s{s}", w, s) for s, w in rack.items()]) for j, rack in region]) for i, region in live])
    region = _drawn(name, regions)
    placed = F.struct(region.alias("region"), name.alias("name"))
    # transform over a one-element array binds each choice once instead of repeating its expression
    with_rack = F.transform(F.array(placed), lambda p: F.struct(p["region"].alias("region"), _drawn(p["name"], F.get(racks, p["region"])).alias("rack"), p["name"].alias("name")))
    leaf = F.transform(with_rack, lambda p: _drawn(p["name"], F.get(F.get(leaves, p["region"]), p["rack"])))
    return F.get(leaf, F.lit(0)).cast("int")


def assign_shards(docs: DataFrame, tree: HashTree, key: str = "doc_id", text: str = "text", grown: HashTree | None = None) -> DataFrame:
    """One row per row of docs: key, size (UTF-8 bytes + 1), text_crc32, shard, slot, grown_shard.

    Slots are gapless from 0 in each shard, in the order of a hash of key and checksum. Null texts
    count as empty; null keys are a key of their own; rows that repeat a key share its shard and get
    slots of their own; an empty table gives an empty result; further columns of docs are ignored.
    """
    content = F.coalesce(F.col(text), F.lit(""))
    narrow = docs.select(
        F.col(key).alias("doc_id"), (F.octet_length(content).cast("long") + 1).alias("size"), F.crc32(content.cast("binary")).alias("text_crc32"),
    )
    narrow = narrow.withColumn("shard", shard_of(F.col("doc_id"), tree)).withColumn("grown_shard", shard_of(F.col("doc_id"), grown) if grown else F.lit(None).cast("int"))
    narrow = narrow.withColumn("_h", F.xxhash64(F.col("doc_id"), F.col("text_crc32"), F.col("size"))).withColumn("_row", F.monotonically_increasing_id())
    narrow = staged(narrow, "shards")
    slots = prefix_before(narrow, "shard", ["_h", "doc_id", "_row"], F.lit(1), "slot", narrow.count())
    return slots.select("doc_id", "size", "text_crc32", "shard", F.col("slot").cast("long").alias("slot"), "grown_shard")


def op5_hash_tree_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    tree = HashTree.of(8)
    out = assign_shards(load(spark, sf_dir, "documents"), tree, grown=tree.grown(8))
    return out.select("doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard", "slot", "grown_shard")

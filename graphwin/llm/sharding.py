"""Shards by a weighted hash tree: region, rack, shard.

A key descends the tree. At each level every child of the node reached draws an exponential variate from the hash of the
key and the child's own name (its path), divided by the weight of its subtree, and the least draw wins: a child is chosen
in proportion to its weight, at a cost of the fan-outs on the way and not of all shards. A changed weight alters the
draws of the nodes above it only: at each level rows move into what gained weight or out of what lost it, never between
two children that kept theirs.

The first `base` shards are laid out by the shape. A tree grows by whole regions: each further shard is one of its own, so
it takes rows only into itself, and the number of shards decides alone.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphwin.functions.ranks import with_global_rank, with_local_rank
from graphwin.session import materialize


@dataclass(frozen=True)
class ShardTree:
    """racks_per_region and shards_per_rack give the shape of the first `base` shards (all, if not given); weights differ
    from 1 only where given, and a shard of weight 0 gets no rows."""

    shards: int
    shards_per_rack: int = 4
    racks_per_region: int = 2
    weights: dict[int, float] = field(default_factory=dict)
    base: int | None = None

    def levels(self) -> list[list[list[int]]]:
        base = self.shards if self.base is None else min(self.base, self.shards)
        racks = [list(range(a, min(a + self.shards_per_rack, base))) for a in range(0, base, self.shards_per_rack)]
        shaped = [racks[a : a + self.racks_per_region] for a in range(0, len(racks), self.racks_per_region)]
        return shaped + [[[s]] for s in range(base, self.shards)]

    def grown(self, by: int = 1) -> "ShardTree":
        return ShardTree(self.shards + by, self.shards_per_rack, self.racks_per_region, self.weights, self.shards if self.base is None else self.base)

    def weight(self, shard: int) -> float:
        return float(self.weights.get(shard, 1.0))


def _choice(key: Column, node: list[Column], weights: Column | list[float], fan: int, seed: int) -> Column:
    """Number of the child that draws least; children of weight 0, or that aren't there, draw nothing."""

    def draw(k: int) -> Column:
        bits = F.shiftrightunsigned(F.xxhash64(F.lit(seed), *node, F.lit(k), key), 11)
        w = F.lit(weights[k]) if isinstance(weights, list) else F.get(weights, F.lit(k))
        return F.struct(F.when(w > 0, -F.log((bits.cast("double") + 0.5) / float(1 << 53)) / w).otherwise(float("inf")).alias("draw"), F.lit(k).alias("at"))

    return (draw(0) if fan == 1 else F.least(*[draw(k) for k in range(fan)]))["at"]


def _numbers(rows: list) -> Column:
    return F.array(*[_numbers(r) if isinstance(r, list) else F.lit(r) for r in rows])


def shard_of(key: Column, tree: ShardTree, seed: int = 17) -> Column:
    """The shard at which the descent ends. Null keys all descend alike."""
    regions = tree.levels()
    racks, shards = max(map(len, regions)), max(len(rack) for region in regions for rack in region)
    pad = lambda row, n, none: row + [none] * (n - len(row))
    of_rack = [pad([sum(map(tree.weight, rack)) for rack in region], racks, 0.0) for region in regions]
    of_shard = [pad([pad([tree.weight(s) for s in rack], shards, 0.0) for rack in region], racks, [0.0] * shards) for region in regions]
    name = [pad([pad(list(rack), shards, -1) for rack in region], racks, [-1] * shards) for region in regions]
    region = _choice(key, [F.lit("region")], [sum(w) for w in of_rack], len(regions), seed)
    # one step a level: the node reached is bound once, and its children draw from its name
    down = F.transform(F.array(region), lambda r: F.struct(r.alias("r"), _choice(key, [F.lit("rack"), r], F.get(_numbers(of_rack), r), racks, seed).alias("k")))
    down = F.transform(down, lambda x: F.get(F.get(F.get(_numbers(name), x["r"]), x["k"]), _choice(key, [F.lit("shard"), x["r"], x["k"]], F.get(F.get(_numbers(of_shard), x["r"]), x["k"]), shards, seed)))
    return F.get(down, F.lit(0))


def assign_shards(docs: DataFrame, tree: ShardTree, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard. Null text has size 1; repeated rows share a shard and
    have slots of their own; slots are gapless from 0 in every shard; an empty table gives no rows."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    key = F.col(id_col).cast("long")
    placed = docs.select(
        key.alias("doc_id"), (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), F.lit("key").alias("law"),
        shard_of(key, tree).cast("int").alias("shard"), shard_of(key, tree.grown()).cast("int").alias("grown_shard"),
    )
    return with_global_rank(materialize(with_local_rank(placed, "shard"), "shards"), "shard", "slot").select("doc_id", "size", "text_crc32", "law", "shard", "slot", "grown_shard")

"""Sharding by a hierarchical weighted hash tree: a key descends from the root to a region, a rack and a shard.

At each level every child draws -ln(u) / weight, u from a hash of (key, level, child) and the weight the sum of the shards below;
the least draw wins. Children are thus chosen in proportion to their weights, at a cost of one hash for each child on the way
instead of one for each shard. A draw depends on its own child alone: where weights change in one subtree, keys move
into it or out of it and inside it, and between other subtrees nothing moves. A shard beyond the regular tree is a region
of its own, so it takes keys into itself alone.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import number, table


@dataclass(frozen=True)
class Leaf:
    region: int
    rack: int
    shard: int
    weight: float = 1.0


def tree(shards: int, base: int = 24, racks_of: int = 4, regions_of: int = 3) -> list[Leaf]:
    """Of shards 0..n-1 the first `base` four to a rack and three racks to a region; each further one in a region of its own."""
    regular = [Leaf(s // (racks_of * regions_of), s // racks_of, s) for s in range(min(shards, base))]
    return regular + [Leaf(base + s, base + s, s) for s in range(base, shards)]


def nested(leaves: list[Leaf]) -> Column:
    """Regions as structs (id, weight, below) whose racks, and the racks' shards, are given likewise."""

    def node(i: int, own: list[Leaf], below: list[Column] | None) -> Column:
        fields = [F.lit(i).alias("id"), F.lit(float(sum(x.weight for x in own))).alias("weight")]
        return F.struct(*fields, *([F.array(*below).alias("below")] if below is not None else []))

    def level(own: list[Leaf], keys: tuple[str, ...]) -> list[Column]:
        if not keys:
            return []
        groups: dict[int, list[Leaf]] = {}
        for x in own:
            groups.setdefault(getattr(x, keys[0]), []).append(x)
        return [node(i, g, level(g, keys[1:]) if len(keys) > 1 else None) for i, g in sorted(groups.items())]

    return F.array(*level(leaves, ("region", "rack", "shard")))


def chosen(key: Column, level: int, children: Column) -> Column:
    """Of an array of children the one with the least draw (ties: the first); 53 bits of a hash make u in (0, 1)."""
    u = lambda x: (F.shiftrightunsigned(F.xxhash64(key, F.lit(level), x["id"]), 11).cast("double") + 0.5) / F.lit(float(1 << 53))
    draws = F.transform(children, lambda x: -F.ln(u(x)) / x["weight"])
    return F.element_at(children, F.array_position(draws, F.array_min(draws)).cast("int"))


def descend(docs: DataFrame, key: Column, leaves: list[Leaf], name: str = "shard") -> DataFrame:
    """docs with the shard of each key; a step of the descent is a projection of its own, so that each draw is made once."""
    step = lambda df, level, children: df.withColumn("_at", chosen(F.col("_key"), level, children))
    out = docs.withColumn("_key", key).withColumn("_tree", nested(leaves))
    out = step(out, 0, F.col("_tree"))
    for level in (1, 2):
        out = step(out, level, F.col("_at")["below"])
    return out.withColumn(name, F.col("_at")["id"]).drop("_key", "_tree", "_at")


def assign(docs: DataFrame, key: Column, leaves: list[Leaf], grown: list[Leaf] | None = None) -> DataFrame:
    """docs with shard (and grown_shard, under the tree `grown`)."""
    out = descend(docs, key, leaves)
    return out if grown is None else descend(out, key, grown, "grown_shard")


def op3_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Null ids share one key; a null text counts 8 bytes and the crc of the empty text; repeated rows get slots of their own."""
    docs = table(spark, sf_dir, "documents")
    body = F.coalesce(F.col("text"), F.lit("")).cast("binary")
    rows = docs.select("doc_id", (F.octet_length(body) + 8).cast("long").alias("size"), F.crc32(body).alias("text_crc32"))
    placed = assign(rows, F.coalesce(F.col("doc_id").cast("string"), F.lit("")), tree(24), tree(25))
    out = number(placed, "shard", "slot")
    return out.select("doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard", "slot", "grown_shard")

"""The lattice of blocks under inclusion of role sets. Pairs are found through shared roles, which is an equi-join."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def overlaps(blocks: DataFrame) -> DataFrame:
    """a, b, la, lb, common: ordered pairs of different blocks that share a role."""
    one = blocks.select(F.col("block_id").alias("a"), F.col("layer").alias("la"), F.explode("roles").alias("role_id"))
    two = blocks.select(F.col("block_id").alias("b"), F.col("layer").alias("lb"), F.explode("roles").alias("role_id"))
    return one.join(two, "role_id").where("a <> b").groupBy("a", "b", "la", "lb").agg(F.count("*").alias("common"))


def descendant_ancestor(blocks: DataFrame) -> DataFrame:
    """descendant, ancestor: the ancestor's role set is strictly within the descendant's."""
    return overlaps(blocks).where("common = la and la < lb").select(F.col("b").alias("descendant"), F.col("a").alias("ancestor"))


def edges(blocks: DataFrame) -> DataFrame:
    """parent_id, child_id: inclusion with no present block strictly between."""
    pairs = descendant_ancestor(blocks).select(F.col("ancestor").alias("parent_id"), F.col("descendant").alias("child_id"))
    between = pairs.select("parent_id", F.col("child_id").alias("mid")).join(pairs.select(F.col("parent_id").alias("mid"), "child_id"), "mid").select("parent_id", "child_id").distinct()
    return pairs.join(between, ["parent_id", "child_id"], "left_anti")


def related(blocks: DataFrame, sibling_rule: str = "overlap") -> DataFrame:
    """a, b, kind of b seen from a: ancestor, descendant or sibling (sets that meet without inclusion; rule same_layer: of one size, too)."""
    kind = F.when((F.col("common") == F.col("lb")) & (F.col("lb") < F.col("la")), "ancestor").when((F.col("common") == F.col("la")) & (F.col("la") < F.col("lb")), "descendant").otherwise("sibling")
    out = overlaps(blocks).withColumn("kind", kind)
    return (out.where("kind <> 'sibling' or la = lb") if sibling_rule == "same_layer" else out).select("a", "b", "kind")


def layers(blocks: DataFrame) -> DataFrame:
    """layer (null: all), blocks, vectors."""
    return blocks.rollup("layer").agg(F.count("*").alias("blocks"), F.sum("n").alias("vectors"))

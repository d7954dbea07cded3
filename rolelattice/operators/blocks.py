"""Exclusive blocks: vectors grouped by the exact set of roles that may read them."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def access_tags(grants: DataFrame) -> DataFrame:
    """(vec_id, role_id) -> (vec_id, roles, role_key, layer)."""
    return named(grants.groupBy("vec_id").agg(F.sort_array(F.collect_set("role_id")).alias("roles")))


def named(tags: DataFrame) -> DataFrame:
    """Tags with their key and layer; a vector that no role may read is refused."""
    return tags.where(F.size("roles") > 0).withColumns({"role_key": F.array_join(F.transform("roles", lambda r: r.cast("string")), ","), "layer": F.size("roles")})


def exclusive_blocks(tags: DataFrame) -> DataFrame:
    """(block_id, role_key, roles, layer, n). Sizes are one partial aggregate, so what is shuffled is a row for each task and
    block; the numbering runs over the blocks alone."""
    sizes = tags.groupBy("roles").agg(F.count("*").alias("n"))
    sizes = sizes.withColumns({"role_key": F.array_join(F.transform("roles", lambda r: r.cast("string")), ","), "layer": F.size("roles")})
    return sizes.select((F.row_number().over(Window.orderBy("layer", "role_key")) - 1).alias("block_id"), "role_key", "roles", "layer", "n")


def authorized(blocks: DataFrame) -> DataFrame:
    """role_id, n: size of what each role may read."""
    return blocks.select(F.explode("roles").alias("role_id"), "n").groupBy("role_id").agg(F.sum("n").alias("n"))


def authorized_sets(blocks: DataFrame, classes: DataFrame) -> DataFrame:
    """qclass, n for role sets (qclass, roles): union semantics, so blocks that share a role count once."""
    met = classes.select("qclass", F.explode("roles").alias("role_id")).join(blocks.select("block_id", "n", F.explode("roles").alias("role_id")), "role_id").select("qclass", "block_id", "n").distinct()
    return met.groupBy("qclass").agg(F.sum("n").alias("n"))


def check_partition(tags: DataFrame, blocks: DataFrame) -> DataFrame:
    """One row of counts: vectors, vectors in blocks, blocks, vectors without a block, empty tags."""
    return tags.agg(F.count("*").alias("vectors"), F.sum(F.when(F.size("roles") == 0, 1).otherwise(0)).alias("empty_tags")).crossJoin(blocks.agg(F.sum("n").alias("in_blocks"), F.count("*").alias("blocks"), F.countDistinct("role_key").alias("keys"))).crossJoin(tags.join(blocks, "role_key", "left_anti").agg(F.count("*").alias("left_over")))


def selectivity(blocks: DataFrame) -> DataFrame:
    """role_id, share of all vectors."""
    total = blocks.agg(F.sum("n").alias("total"))
    return authorized(blocks).crossJoin(total).select("role_id", (F.col("n") / F.col("total")).alias("share"))


def oracle_sa(blocks: DataFrame) -> DataFrame:
    """Storage of one pure index for each role over that of the vectors."""
    return blocks.agg((F.sum(F.col("n") * F.col("layer")) / F.sum("n")).alias("oracle_sa"))

"""Query sets: uniform and weighted, one role or several, inside or outside what the role may read, and a log's history."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .policy import CUT
from .tables import table


#: What a role may read is counted in so many slices of ids; only the slices that queries point at are sorted.
SLICES = 4096


def single_role(spark: SparkSession, tags: DataFrame, blocks: DataFrame, roles: list[int], n: int = 100) -> DataFrame:
    """qid, role_id, vec_id: roles in turn; the vector at a spread position among what the role may read, ordered by slice and id."""
    sizes = blocks.select(F.explode("roles").alias("role_id"), "n").groupBy("role_id").agg(F.sum("n").alias("n"))
    q = spark.range(n).select(F.col("id").alias("qid"), F.element_at(F.array(*[F.lit(r) for r in roles]), (F.col("id") % len(roles) + 1).cast("int")).alias("role_id"))
    at = q.join(sizes, "role_id").select("qid", "role_id", ((F.col("qid") * 7919) % F.col("n")).alias("pos"))
    each = tags.select("vec_id", (F.col("vec_id") % SLICES).alias("slice"), F.explode("roles").alias("role_id"))
    w = Window.partitionBy("role_id").orderBy("slice")
    counts = each.groupBy("role_id", "slice").agg(F.count("*").alias("c")).withColumn("upto", F.sum("c").over(w))
    hit = at.join(counts, "role_id").where("pos >= upto - c and pos < upto").select("qid", "role_id", "slice", F.expr("pos - upto + c").alias("nth"))
    # as many rows as there are queries
    near = each.join(F.broadcast(hit.select("role_id", "slice").distinct()), ["role_id", "slice"])
    near = near.withColumn("nth", F.row_number().over(Window.partitionBy("role_id", "slice").orderBy("vec_id")).cast("long") - 1)
    return near.join(F.broadcast(hit), ["role_id", "slice", "nth"]).select("qid", "role_id", "vec_id")


def _u(qid: F.Column) -> F.Column:
    return (qid * 7919 + 13) % CUT


def weighted_role(spark: SparkSession, blocks: DataFrame, n: int = 100) -> DataFrame:
    """qid, role_id: a role as often as it may read; the cumulative weights are met by a range join with a hash fraction."""
    sizes = blocks.select(F.explode("roles").alias("role_id"), "n").groupBy("role_id").agg(F.sum("n").alias("n"))
    w = Window.orderBy("role_id")
    cum = sizes.select("role_id", "n", F.sum("n").over(w).alias("hi"), F.sum("n").over(w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("all"))
    q = spark.range(n).select(F.col("id").alias("qid"), _u(F.col("id")).alias("u"))
    return q.join(F.broadcast(cum), F.expr(f"u * all >= (hi - n) * {CUT} and u * all < hi * {CUT}")).select("qid", "role_id")


def multi_role(spark: SparkSession, blocks: DataFrame, n: int = 100, weighted: bool = False) -> DataFrame:
    """qid, role_key: the role set of a block of several roles, in turn or by size."""
    many = blocks.where("layer > 1")
    w = Window.orderBy("block_id")
    num = many.select("role_key", "n", (F.row_number().over(w) - 1).alias("i"), F.count("*").over(w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("c"), F.sum("n").over(w).alias("hi"), F.sum("n").over(w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("all"))
    q = spark.range(n).select(F.col("id").alias("qid"), _u(F.col("id")).alias("u"))
    on = f"u * all >= (hi - n) * {CUT} and u * all < hi * {CUT}" if weighted else "qid % c = i"
    return q.join(F.broadcast(num), F.expr(on)).select("qid", "role_key")


def history(spark: SparkSession, sf_dir: str, roles: list[int], until: str = "2024-01-21") -> DataFrame:
    """role_id, past, future: queries of the log before and after a day."""
    log = table(spark, sf_dir, "events").select(F.element_at(F.array(*[F.lit(r) for r in roles]), (F.col("user_id") % len(roles) + 1).cast("int")).alias("role_id"), "ts")
    return log.groupBy("role_id").agg(F.sum(F.when(F.col("ts") < F.lit(until).cast("timestamp"), 1).otherwise(0)).alias("past"), F.sum(F.when(F.col("ts") >= F.lit(until).cast("timestamp"), 1).otherwise(0)).alias("future"))

"""Measures over layouts, plans and results."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def sa(node_blocks: DataFrame, blocks: DataFrame) -> DataFrame:
    """Stored vectors over vectors."""
    return node_blocks.join(blocks, "block_id").agg(F.sum("n").alias("stored")).crossJoin(blocks.agg(F.sum("n").alias("total"))).select((F.col("stored") / F.col("total")).alias("sa"))


def recall(result: DataFrame, truth: DataFrame, k: int = 10) -> DataFrame:
    """Mean share of the true top k that is returned, over queries with a truth."""
    hit = truth.join(result.select("qid", "vec_id", F.lit(1).alias("hit")), ["qid", "vec_id"], "left")
    return hit.groupBy("qid").agg((F.sum(F.coalesce("hit", F.lit(0))) / F.count("*")).alias("r")).agg(F.avg("r").alias("recall"))


def purity(plan: DataFrame) -> DataFrame:
    """Mean over classes of authorized among touched vectors."""
    return plan.groupBy("qclass").agg((F.sum(F.col("n") / F.col("lambda")) / F.sum("n")).alias("p")).agg(F.avg("p").alias("purity"))


def units_per_query(plan: DataFrame) -> DataFrame:
    return plan.groupBy("qclass").agg(F.sum(F.when(F.col("kind") == "index", 1).otherwise(0)).alias("i"), F.count("*").alias("u")).agg(F.avg("i").alias("indices"), F.avg("u").alias("units"))


def split(node_blocks: DataFrame, blocks: DataFrame) -> DataFrame:
    """kind, units, vectors."""
    return node_blocks.join(blocks, "block_id").groupBy("kind").agg(F.countDistinct("unit_id").alias("units"), F.sum("n").alias("vectors"))


def lambda_profile(plan: DataFrame) -> DataFrame:
    return plan.agg(F.min("lambda").alias("least"), F.percentile("lambda", F.lit(0.5)).alias("median"), F.max("lambda").alias("most"), F.avg("lambda").alias("mean"))


def coordination(counters: DataFrame, *by: str) -> DataFrame:
    """Share of impure visits that were skipped, and of the inflated beam that was not spent (null where nothing is impure)."""
    return counters.groupBy(*by).agg(F.try_divide(F.sum("skipped"), F.sum("impure")).alias("skip_rate"), (1 - F.try_divide(F.sum("spent"), F.sum("inflated"))).alias("beam_reduction"))


def robustness(runs: DataFrame, rate: str) -> DataFrame:
    """Worst over best rate of a grid."""
    return runs.agg((F.min(rate) / F.max(rate)).alias("worst_over_best"))


def speedup(runs: DataFrame, rate: str, of: str) -> DataFrame:
    """method, speedup: mean over the grid of the rate over that of one method."""
    base = runs.where(F.col("method") == of).select("efs", F.col(rate).alias("_base"))
    return runs.join(base, "efs").groupBy("method").agg(F.avg(F.col(rate) / F.col("_base")).alias("speedup"))


def timed(run: Callable[[], DataFrame], repeats: int = 3) -> float:
    """Mean wall seconds of a run that is forced by a sink without output."""
    took = []
    for _ in range(repeats):
        t = time.perf_counter()
        run().write.format("noop").mode("overwrite").save()
        took.append(time.perf_counter() - t)
    return sum(took) / len(took)


def qps(run: Callable[[], DataFrame], queries: int, repeats: int = 3) -> float:
    return queries / timed(run, repeats)

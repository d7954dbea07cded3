"""The given tables and the vectors that are derived from them."""

from __future__ import annotations

import string

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def emb(spark: SparkSession, sf_dir: str) -> DataFrame:
    """vec_id, embedding, label; a vector without id or with a null or missing component is refused."""
    rows = table(spark, sf_dir, "embeddings").select("vec_id", "embedding", "label")
    return rows.where(F.col("vec_id").isNotNull() & F.col("embedding").isNotNull() & ~F.exists("embedding", lambda v: v.isNull()))


def emb_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    """vec_id, label without the vectors, for everything that needs sizes and tags only; vectors are checked where they are read."""
    return table(spark, sf_dir, "embeddings").select("vec_id", "label").where(F.col("vec_id").isNotNull())


LIN_KEYS = ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber")


def lin_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lineitem with vec_id, 60 bits of a hash of its key: no row needs to meet another one to get its id."""
    named = F.conv(F.substring(F.md5(F.concat_ws("|", *LIN_KEYS)), 1, 15), 16, 10).cast("long")
    return table(spark, sf_dir, "lineitem").withColumn("vec_id", named)


def lin_embedding() -> F.Column:
    """Eight numbers of a line item, each about 0 to 1."""
    c = F.col
    return F.array(c("l_quantity") / 50, c("l_extendedprice") / 105000, c("l_discount") / 0.1, c("l_tax") / 0.08, c("l_linenumber") / 7, F.month("l_shipdate") / 12, F.dayofmonth("l_shipdate") / 31, (c("l_partkey") % 1000) / 1000)


def lin(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lin_ids(spark, sf_dir).select("vec_id", lin_embedding().alias("embedding"), F.lit(0).alias("label"))


def letter_profile(text: F.Column) -> F.Column:
    """Share of each letter a to z among the characters."""
    low, n = F.lower(text), F.greatest(F.length(text), F.lit(1))
    return F.array(*[(F.length(text) - F.length(F.replace(low, F.lit(x), F.lit("")))) / n for x in string.ascii_lowercase])


def doc(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "documents").where("text is not null")
    return rows.select(F.col("doc_id").alias("vec_id"), letter_profile(F.col("text")).alias("embedding"), F.lit(0).alias("label"))

"""Exact top-k by inner product with block-at-a-time pruning.

Vectors lie in blocks of consecutive rows, each a forward index (its rows' components) with the largest and smallest
value of every component. For a query, the sum over components of the larger product with those two bounds every score
in a block. Blocks are taken in order of falling bound and scored until the bound falls below the k-th best score so far.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import table

BLOCK_ROWS = 256
#: Queries that are broadcast and answered in one pass over the vectors.
QUERY_BLOCK = 2048
SCALE = 1024.0


def matrix(ids: pa.Array, vectors: pa.Array) -> tuple[np.ndarray, list[np.ndarray]]:
    """Ids and whole-number vectors of the rows that take part."""
    keep_ids, rows = [], []
    flat = vectors.flatten()
    lens = np.asarray(vectors.value_lengths().fill_null(-1))
    values = np.asarray(flat.cast(pa.float64()).to_numpy(zero_copy_only=False), np.float64)  # nulls become NaN
    at = 0
    for i, n in zip(ids.to_pylist(), lens.tolist(), strict=True):
        if n < 0:
            continue
        v = values[at : at + n]
        at += n
        if i is not None and np.isfinite(v).all():
            keep_ids.append(i)
            rows.append(np.floor(v * SCALE))
    return np.array(keep_ids, np.int64), rows


def stack(rows: list[np.ndarray], wide: int) -> np.ndarray:
    out = np.zeros((len(rows), wide))
    for i, r in enumerate(rows):
        out[i, : min(wide, len(r))] = r[:wide]
    return out


class Best:
    """The k best (score, id) of each query so far: higher score first, then smaller id."""

    def __init__(self, n: int, k: int) -> None:
        self.k, self.score, self.id = k, np.full((n, k), -np.inf), np.full((n, k), np.iinfo(np.int64).max)

    def add(self, q: np.ndarray, score: np.ndarray, ids: np.ndarray) -> None:
        s = np.concatenate([self.score[q], score], axis=1)
        i = np.concatenate([self.id[q], np.broadcast_to(ids, score.shape)], axis=1)
        order = np.lexsort((i, -s), axis=-1)[:, : self.k]
        self.score[q], self.id[q] = np.take_along_axis(s, order, 1), np.take_along_axis(i, order, 1)


def search_blocks(query_ids: np.ndarray, queries: np.ndarray, ids: np.ndarray, vectors: np.ndarray, best: Best, counters: dict | None = None) -> None:
    """Score the blocks of these vectors that may still change the best; sums of products stay exact in doubles (below 2**53)."""
    cuts = range(0, len(ids), BLOCK_ROWS)
    high = np.array([vectors[c : c + BLOCK_ROWS].max(0) for c in cuts])
    low = np.array([vectors[c : c + BLOCK_ROWS].min(0) for c in cuts])
    bound = np.maximum(queries, 0) @ high.T + np.minimum(queries, 0) @ low.T
    order = np.argsort(-bound, axis=1, kind="stable")
    for r in range(bound.shape[1]):
        block = order[:, r]
        # a block whose bound equals the k-th score may hold a smaller id
        live = np.flatnonzero(bound[np.arange(len(queries)), block] >= best.score[:, -1])
        if not len(live):
            break
        for b in np.unique(block[live]):
            q = live[block[live] == b]
            part = slice(b * BLOCK_ROWS, (b + 1) * BLOCK_ROWS)
            score = queries[q] @ vectors[part].T
            score[query_ids[q][:, None] == ids[part][None, :]] = -np.inf
            best.add(q, score, ids[part])
            if counters is not None:
                counters["scored"] = counters.get("scored", 0) + len(q)
    if counters is not None:
        counters["blocks"] = counters.get("blocks", 0) + bound.size


def top_k(vectors: DataFrame, queries: DataFrame, k: int = 10, query_block: int = QUERY_BLOCK) -> DataFrame:
    """Both with vec_id and embedding -> query_id, rank, vec_id, score; one pass over the vectors for each block of queries.

    Shorter vectors count as padded with zeros. Rows that share the query's id are its own. A row without an id takes no part."""
    spark = vectors.sparkSession
    parts, held = [], []

    def one_pass() -> None:
        ids, rows = matrix(pa.array([r[0] for r in held], pa.int64()), pa.array([r[1] for r in held], pa.list_(pa.float64())))
        held.clear()
        if len(ids):
            shared = spark.sparkContext.broadcast((ids, stack(rows, max(map(len, rows)))))
            parts.append(_pass(vectors, shared, k))

    for r in queries.select("vec_id", "embedding").toLocalIterator():
        held.append((r[0], r[1]))
        if len(held) == query_block:
            one_pass()
    one_pass()
    if not parts:
        return spark.createDataFrame([], "query_id bigint, rank int, vec_id bigint, score bigint")
    found = parts[0]
    for p in parts[1:]:
        found = found.union(p)
    rank = F.row_number().over(Window.partitionBy("pass", "nth").orderBy(F.desc("score"), "vec_id"))
    return found.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def _pass(vectors: DataFrame, shared, k: int) -> DataFrame:  # noqa: ANN001
    schema = "nth int, query_id bigint, vec_id bigint, score bigint"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        query_ids, queries = shared.value
        best = Best(len(query_ids), k)
        for batch in batches:
            if batch.num_rows:
                ids, rows = matrix(batch.column(0), batch.column(1))
                if len(ids):
                    search_blocks(query_ids, queries, ids, stack(rows, queries.shape[1]), best)
        q, j = np.nonzero(np.isfinite(best.score))
        yield pa.RecordBatch.from_arrays([pa.array(q, pa.int32()), pa.array(query_ids[q]), pa.array(best.id[q, j]), pa.array(best.score[q, j].astype(np.int64))], ["nth", "query_id", "vec_id", "score"])

    return vectors.select(F.col("vec_id").cast("long"), "embedding").mapInArrow(run, schema).withColumn("pass", F.lit(shared.id if hasattr(shared, "id") else id(shared)))


def op9_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Vectors that are null or hold a null or non-finite component take no part, as query or candidate."""
    rows = table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    return top_k(rows, rows.where(F.col("vec_id") % 100 == 0))


ORACLE = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(1024 * CAST(x AS DOUBLE)) AS BIGINT)) AS e FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (
  SELECT q.vec_id AS query_id, c.vec_id, CAST(list_sum(list_transform(list_zip(q.e, c.e), lambda p: p[1] * p[2])) AS BIGINT) AS score
  FROM v q JOIN v c ON q.vec_id % 100 = 0 AND c.vec_id <> q.vec_id)
SELECT query_id, CAST(rank AS INTEGER) AS rank, vec_id, score
FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s) WHERE rank <= 10
"""

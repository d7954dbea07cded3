"""The data plane of a layout: each unit's vectors, in shards of bounded size, and graphs over those of indexed units."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..storage import local, trim
from . import hnsw

#: Rows that a shard may hold; larger units are spread by a hash of the id.
SHARD_ROWS = 200_000
#: Rows that a control table (blocks, plans, shards) may have to be broadcast.
BROADCAST_ROWS = 200_000


def small(control: DataFrame) -> DataFrame:
    """A control table, to be broadcast if it is as small as control tables should be; else joins decide for themselves."""
    return F.broadcast(control) if control.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS else control


def _mixed(h: int, k: int) -> int:
    """Spark's hash of an int with the hash of the columns before it."""
    word = (1 << 32) - 1
    k = (k & word) * 0xCC9E2D51 & word
    k = (k << 15 | k >> 17) * 0x1B873593 & word
    h ^= k
    h = ((h << 13 | h >> 19) & word) * 5 + 0xE6546B64 & word
    h ^= 4
    h = (h ^ h >> 16) * 0x85EBCA6B & word
    h = (h ^ h >> 13) * 0xC2B2AE35 & word
    h ^= h >> 16
    return h - (1 << 32) if h >> 31 else h


def salted(keys: list[tuple[int, int]], first: list[int], step: list[int], wide: int) -> list[int]:
    """For each key a number out of first, first + step, ..., such that both, hashed into `wide` partitions, fall into one after the other."""
    out = []
    for i, (key, a, by) in enumerate(zip(keys, first, step, strict=True)):
        h = _mixed(_mixed(42, key[0]) & 0xFFFFFFFF, key[1]) & 0xFFFFFFFF
        tries = (a + by * j for j in range(100 * wide))
        out.append(next((x for x in tries if _mixed(h, x) % wide == i % wide), a))
    return out


def spread_out(spark: SparkSession, shards: list[tuple[int, int, float, int]], most: int) -> tuple[DataFrame, int]:
    """unit_id, shard, parts, nth, part of all parts of shards (unit_id, shard, weight, parts), and the partitions to hash unit_id, shard and
    part into: as many as parts, up to `most`, so that none is empty and the heavy ones do not meet."""
    rows = sorted(((-w / n, u, s, n, i) for u, s, w, n in shards for i in range(n)))
    wide = max(1, min(most, len(rows)))
    part = salted([r[1:3] for r in rows], [r[4] for r in rows], [r[3] for r in rows], wide)
    made = local(spark, [(*r[1:], p) for r, p in zip(rows, part, strict=True)], "unit_id int, shard int, parts int, nth int, part int")
    return F.broadcast(made) if len(rows) <= BROADCAST_ROWS else made, wide


def place(vectors: DataFrame, tags: DataFrame, blocks: DataFrame, node_blocks: DataFrame, shard_rows: int = SHARD_ROWS) -> DataFrame:
    """unit_id, kind, shard, block_id, vec_id, embedding: a row for each place that holds a vector.

    Tags and vectors join by id once; the block of a tag and the units of a block come from control tables (checked small)."""
    ids = small(blocks.select("role_key", "block_id"))
    block_of = tags.select("vec_id", "role_key").join(ids, "role_key").select("vec_id", "block_id")
    sizes = node_blocks.join(blocks.select("block_id", "n"), "block_id").groupBy("unit_id").agg(F.ceil(F.sum("n") / shard_rows).cast("int").alias("shards"))
    units = small(node_blocks.join(sizes, "unit_id"))
    rows = vectors.join(block_of, "vec_id").join(units, "block_id")
    return rows.select("unit_id", "kind", F.pmod(F.xxhash64("vec_id"), F.col("shards")).cast("int").alias("shard"), "block_id", "vec_id", "embedding")


def write(placed: DataFrame, path: str) -> None:
    """One folder for each unit, so that a plan prunes what it does not read and a changed unit is rewritten alone."""
    placed.repartition("unit_id", "shard").sortWithinPartitions("unit_id", "block_id").write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("unit_id").parquet(path)


def runs(batches: Iterator[pa.RecordBatch], most: int = 1 << 14) -> Iterator[tuple[tuple[int, int, int], pa.RecordBatch]]:
    """Runs of rows of one unit, shard and part (the first three columns), of at most so many rows, in their order."""
    for b in batches:
        key = np.stack([np.asarray(b.column(i)) for i in range(3)], axis=1) if b.num_rows else np.zeros((0, 3), int)
        new = np.flatnonzero(np.append(True, (key[1:] != key[:-1]).any(1))).tolist() if len(key) else []
        for begin, end in zip(new, [*new[1:], len(key)], strict=True):
            for a in range(begin, end, most):
                yield tuple(key[begin].tolist()), b.slice(a, min(most, end - a))


def matrix(column: pa.ChunkedArray) -> np.ndarray:
    """Lists of equal length as the rows of a matrix, in the type of their numbers."""
    flat = column.combine_chunks().flatten()
    return flat.to_numpy(zero_copy_only=False).reshape(len(column), -1)


def graphs(placed: DataFrame, m: int = 16, efc: int = 64, seed: int = 1) -> DataFrame:
    """unit_id, shard, n, nth, graph: the graphs of the indexed units' shards, each in pieces, since no row should be as large as a graph."""
    schema = pa.schema([("unit_id", pa.int32()), ("shard", pa.int32()), ("n", pa.int64()), ("nth", pa.int32()), ("graph", pa.binary())])

    def built(key: tuple[int, int, int], held: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = pa.Table.from_batches(held)
        held.clear()
        ids, of, x = t["vec_id"].to_numpy(), t["block_id"].to_numpy(), matrix(t["embedding"])
        del t
        g = hnsw.build(ids, x, of, m, efc, seed)
        del x
        for i, piece in enumerate(g.pieces()):
            yield pa.RecordBatch.from_pydict({"unit_id": [key[0]], "shard": [key[1]], "n": [len(g.ids)], "nth": [i], "graph": [piece]}, schema=schema)

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held = None, []
        for key, rows in runs(batches):
            if key != now and held:
                yield from built(now, held)
            now = key
            held.append(rows)
        if held:
            yield from built(now, held)
        trim()

    # the rows are few bytes and much work: each shard in a partition of its own, the largest first
    session, rows = placed.sparkSession, placed.where("kind = 'index'")
    sizes = [(r["unit_id"], r["shard"], float(r["n"]) ** 2, 1) for r in rows.groupBy("unit_id", "shard").agg(F.count("*").alias("n")).collect()]  # a row for each shard
    part, wide = spread_out(session, sizes, max(2 * session.sparkContext.defaultParallelism, int(session.conf.get("spark.sql.shuffle.partitions"))))
    key = ["unit_id", "shard", "part"]
    dealt = rows.join(part, ["unit_id", "shard"]).select(*key, "vec_id", "block_id", "embedding").repartition(wide, *key).sortWithinPartitions(*key)
    return dealt.mapInArrow(make, "unit_id int, shard int, n bigint, nth int, graph binary")

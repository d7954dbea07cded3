"""Shared pieces of the text operators: table access, checkpoints, Arrow text buffers, vectorised hashing."""

from __future__ import annotations

import ctypes
import gc
import sys
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Bytes of text that a worker holds as numpy intermediates at once (a longer single text is taken alone).
CHUNK_BYTES = 1 << 20
#: Odd multiplier of the polynomial hash and its inverse modulo 2**64.
_BASE = 0x9E3779B97F4A7C15
_BASE_INV = pow(_BASE, -1, 1 << 64)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def cut(df: DataFrame, eager: bool = True) -> DataFrame:
    """Write df to the shared checkpoint folder and go on from the files, so that a lost executor costs no recomputation."""
    shared_folder(df.sparkSession)
    return df.checkpoint(eager)


def shared_folder(spark: SparkSession) -> str:
    """The folder for what must outlive an executor: that of the session, or one of this machine where all of Spark runs in one process."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        given = spark.conf.get("spark.checkpoint.dir", None)
        if given is None and not sc._jsc.sc().isLocal():
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        sc.setCheckpointDir(given or tempfile.mkdtemp(prefix="checkpoints-"))
    return sc.getCheckpointDir()


def crc_mod4() -> F.Column:
    """crc32 of doc_id as text, modulo 4; a null doc_id counts as the empty text."""
    return F.pmod(F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary")), F.lit(4))


def stored(df: DataFrame) -> DataFrame:
    """df written once as compressed Parquet beside the checkpoints, and read from there; it lasts as long as that folder."""
    path = f"{shared_folder(df.sparkSession)}/stored-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def discard(spark: SparkSession, *tables: DataFrame) -> None:
    """Delete stored tables that no later step reads, and let Spark's cleaner delete the shuffles of steps that are over, which it does once the
    driver's JVM has collected its garbage."""
    for df in tables:
        for folder in {f.rpartition("/")[0] for f in df.inputFiles()}:
            path = spark._jvm.org.apache.hadoop.fs.Path(folder)
            path.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).delete(path, True)
    gc.collect()
    spark._jvm.System.gc()


def extend(df: DataFrame, name: str, kind: str) -> tuple[DataFrame, T.StructType]:
    """df without a column of this name (in any case of letters), and its schema with that column at the end."""
    df = df.drop(*[c for c in df.columns if c.lower() == name.lower()])
    return df, T.StructType([*df.schema.fields, T.StructField(name, T._parse_datatype_string(kind))])


def parts(spark: SparkSession) -> int:
    """Partitions for shuffles whose number a call must state."""
    return max(int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism)


def number(rows: DataFrame, by: str, name: str, groups: int = 64) -> DataFrame:
    """Number the rows of each value of `by` from 0 without gaps, in an order that the rows' values alone decide.

    Rows are numbered within `groups` sub-groups by hash, so that no task sorts all rows of a value; sub-groups' offsets come
    from their counts: (values of by) x groups rows, which the caller's bound on the values makes safe to broadcast."""
    given = rows.columns
    rows = rows.withColumn("_g", F.pmod(F.xxhash64(*given), F.lit(groups)).cast("int"))
    before = Window.partitionBy(by).orderBy("_g").rowsBetween(Window.unboundedPreceding, -1)
    offsets = rows.groupBy(by, "_g").agg(F.count("*").alias("_n")).select(by, "_g", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_before"))
    within = F.row_number().over(Window.partitionBy(by, "_g").orderBy(*[c for c in given if c != by]))
    return rows.withColumn("_in", within).join(F.broadcast(offsets), [by, "_g"]).select(*given, (F.col("_before") + F.col("_in") - 1).cast("long").alias(name))


def utf8(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a string or binary array and its row offsets; nulls are empty."""
    if column.null_count:
        column = column.fill_null("" if pa.types.is_string(column.type) or pa.types.is_large_string(column.type) else b"")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, offsets, data = column.buffers()
    offs = np.frombuffer(offsets, np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[offs[0] : offs[-1]], offs - offs[0]


def own(operator: str) -> dict:
    """What an operator keeps in a worker from task to task; it goes when a task of another one begins there."""
    return sys.__dict__.setdefault("_kept_by_operator", {}).setdefault(operator, {})


def trim(operator: str | None = None) -> None:
    """Drop what other operators keep, and give back what freed arrays left with the allocators: a worker outlives its task, and all workers
    share the executor's memory."""
    held = sys.__dict__.get("_kept_by_operator", {})
    for name in [x for x in held if x != operator]:
        del held[name]
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # another C library than glibc
        return


def chunks(batches: Iterator[pa.RecordBatch], name: str = "text", limit: int = CHUNK_BYTES, operator: str | None = None) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    """slices() of all batches of a task of this operator, whose worker is trimmed before and after."""
    trim(operator)
    yield from slices(batches, name, limit)
    trim(operator)


def slices(batches: Iterator[pa.RecordBatch], name: str = "text", limit: int = CHUNK_BYTES) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    """Runs of rows of at most `limit` bytes of text (or one longer row): the rows, their bytes, their offsets."""
    for batch in batches:
        if not batch.num_rows:
            continue
        raw, offs = utf8(batch.column(batch.schema.get_field_index(name)))
        at = 0
        while at < batch.num_rows:
            to = max(at + 1, int(np.searchsorted(offs, offs[at] + limit, "right")) - 1)
            yield batch.slice(at, to - at), raw[offs[at] : offs[to]], offs[at : to + 1] - offs[at]
            at = to


_tables: dict[str, np.ndarray] = {}


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_tables.get("pow", ())) < n:
        with np.errstate(over="ignore"):
            for key, base in (("pow", _BASE), ("inv", _BASE_INV)):
                t = np.full(max(n, CHUNK_BYTES + 1), base, np.uint64)
                t[0] = 1
                _tables[key] = np.cumprod(t, dtype=np.uint64)
    return _tables["pow"], _tables["inv"]


def mix(h: np.ndarray) -> np.ndarray:
    """The finaliser of splitmix64 on an array of uint64."""
    h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def prefix_hash(codes: np.ndarray) -> np.ndarray:
    """h such that (h[e] - h[s]) * base**-s names codes[s:e]."""
    pw, _ = powers(len(codes) + 1)
    h = np.empty(len(codes) + 1, np.uint64)
    h[0] = 0
    np.cumsum((codes.astype(np.uint64) + np.uint64(1)) * pw[: len(codes)], out=h[1:])
    return h


def span_hash(h: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    return mix((h[ends] - h[starts]) * powers(len(h))[1][starts])


def lower_table() -> np.ndarray:
    t = np.arange(256, dtype=np.uint8)
    t[65:91] += 32
    return t


def runs(kind: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of the runs of equal non-zero kind that lie within one row, and the first run of each row (one more entry at the end)."""
    n = len(kind)
    if not n:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(offs), np.int64)
    change = np.empty(n + 1, bool)
    change[0] = change[n] = True
    np.not_equal(kind[1:], kind[:-1], out=change[1:n])
    change[offs] = True
    at = np.flatnonzero(change)
    keep = kind[at[:-1]] != 0
    starts, ends = at[:-1][keep], at[1:][keep]
    return starts, ends, np.searchsorted(starts, offs)


def word_hashes(raw: np.ndarray, offs: np.ndarray, kind_of: np.ndarray, low: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(hash of each word, first word of each row with one more entry, byte starts, byte ends); kind_of maps a byte to 0 (between words) or a word's kind."""
    starts, ends, first = runs(kind_of[raw], offs)
    return span_hash(prefix_hash(low[raw]), starts, ends), first, starts, ends

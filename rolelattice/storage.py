"""Tables that are written once and read often, in the folder that all executors share."""

from __future__ import annotations

import ctypes
import tempfile
import uuid
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession


#: Bytes of a row group of what is kept.
ROW_GROUP = 16 << 20


def shared_folder(spark: SparkSession) -> str:
    """The checkpoint folder of the session. Where none is named, one of this machine, but only if all of Spark runs in one process."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        given = spark.conf.get("spark.checkpoint.dir", None)
        if given is None and not sc._jsc.sc().isLocal():
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        sc.setCheckpointDir(given or tempfile.mkdtemp(prefix="checkpoints-"))
    return sc.getCheckpointDir()


def scratch(spark: SparkSession) -> str:
    """A new path in the shared folder."""
    return f"{shared_folder(spark)}/{uuid.uuid4().hex}"


def kept(df: DataFrame) -> DataFrame:
    """df written once as Parquet and read from there. Row groups are small, since Spark reads a batch of up to 4,096 rows, whatever they hold, of one at once."""
    path = scratch(df.sparkSession)
    df.write.option("parquet.block.size", ROW_GROUP).option("parquet.page.size.row.check.min", 8).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def at_once(*runs: Callable) -> list:
    """What the functions return, whose jobs share the cluster: the wait for the last task of one is filled by another's."""
    with ThreadPoolExecutor(len(runs)) as pool:
        return [x.result() for x in [pool.submit(run) for run in runs]]


def local(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    """Rows of the driver as part of the plan, which takes no Python worker to read."""
    import pyarrow as pa

    kinds = {"int": pa.int32(), "bigint": pa.int64(), "double": pa.float64(), "boolean": pa.bool_(), "string": pa.string()}
    fields = [x.split() for x in schema.split(", ")]
    cols = list(zip(*rows, strict=True)) if rows else [()] * len(fields)
    return spark.createDataFrame(pa.table([pa.array(list(x), kinds[t]) for x, (_, t) in zip(cols, fields, strict=True)], names=[n for n, _ in fields]))


def trim() -> None:
    """Give back what freed arrays left with the allocators: a worker outlives its task, and all workers share the executor's memory."""
    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # another C library than glibc
        return

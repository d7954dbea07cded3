"""Streams over the events table: windows, late rows, joins and state, each run to the end of its files and compared with batch SQL."""

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..storage import scratch

Q: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}
SCHEMA = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string"


def _q(name: str, sql: str | None = None):  # noqa: ANN202
    def add(f: Callable) -> Callable:
        Q[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events as a stream of files; ts as the files hold it."""
    kind = dict(spark.read.parquet(f"{sf_dir}/events.parquet").dtypes)["ts"]
    rows = spark.readStream.schema(SCHEMA.replace("ts timestamp", f"ts {kind}")).parquet(f"{sf_dir}/events.parquet*")
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def finish(stream: DataFrame, mode: str) -> DataFrame:
    """Run a stream over all that is available and return what it wrote, which lies in files; the driver holds none of it."""
    spark, path, held = stream.sparkSession, scratch(stream.sparkSession), {}

    def put(batch: DataFrame, epoch: int) -> None:
        at = f"{path}/{epoch}-{uuid.uuid4().hex}"  # a batch may come twice
        batch.write.parquet(at)
        held[epoch] = at

    q = stream.writeStream.foreachBatch(put).outputMode(mode).option("checkpointLocation", scratch(spark)).trigger(availableNow=True).start()
    q.awaitTermination()
    if not held:
        return spark.createDataFrame([], stream.schema)
    return spark.read.schema(stream.schema).parquet(*([held[max(held)]] if mode == "complete" else held.values()))


_DAY = "epoch(date_trunc('day', ts))"
_q("stream_tumbling", f"SELECT CAST({_DAY} AS BIGINT) AS day, event_type, count(*) AS n FROM events GROUP BY ALL")(lambda s, d: finish(events(s, d).groupBy(F.window("ts", "1 day"), "event_type").agg(F.count("*").alias("n")), "complete").select(F.unix_timestamp("window.start").alias("day"), "event_type", "n"))
_q("stream_sliding", f"SELECT CAST({_DAY} AS BIGINT) + k * 86400 AS day, count(*) AS n FROM events, (VALUES (0), (-1)) AS v(k) GROUP BY ALL")(lambda s, d: finish(events(s, d).groupBy(F.window("ts", "2 days", "1 day")).agg(F.count("*").alias("n")), "complete").select(F.unix_timestamp("window.start").alias("day"), "n"))
_q("stream_session", "WITH x AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS b FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), y AS (SELECT user_id, sum(b) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS g FROM x) SELECT user_id, count(DISTINCT g) AS sessions, count(*) AS n FROM y GROUP BY 1")(lambda s, d: finish(events(s, d).groupBy(F.session_window("ts", "6 hours"), "user_id").agg(F.count("*").alias("c")), "complete").groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("c").alias("n")))
_q("stream_watermark_late")(lambda s, d: finish(events(s, d).withWatermark("ts", "1 day").groupBy(F.window("ts", "1 day")).agg(F.count("*").alias("n")), "append").select(F.unix_timestamp("window.start").alias("day"), "n"))
_q("stream_dedup", "SELECT count(DISTINCT (user_id, event_type)) AS n FROM events")(lambda s, d: finish(events(s, d).dropDuplicates(["user_id", "event_type"]).select("user_id", "event_type"), "append").agg(F.count("*").alias("n")))
_q("stream_static_join", "SELECT c_nationkey, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY 1")(lambda s, d: finish(events(s, d).join(s.read.parquet(f"{d}/customer.parquet").select("c_custkey", "c_nationkey"), F.expr("user_id = c_custkey")).groupBy("c_nationkey").agg(F.count("*").alias("n")), "complete"))


@_q("stream_stream_interval", "SELECT count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'signup' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 DAY")
def stream_stream(s: SparkSession, d: str) -> DataFrame:
    a = events(s, d).where("event_type = 'signup'").select(F.col("user_id").alias("u"), F.col("ts").alias("t0")).withWatermark("t0", "40 days")
    b = events(s, d).where("event_type = 'purchase'").select("user_id", "ts").withWatermark("ts", "40 days")
    return finish(a.join(b, F.expr("u = user_id and ts >= t0 and ts <= t0 + interval 1 day")).select("u", "t0", "ts"), "append").agg(F.count("*").alias("n"))


@_q("stream_stateful_counts", "SELECT user_id % 5 AS role_id, count(*) AS n FROM events GROUP BY 1")
def stateful(s: SparkSession, d: str) -> DataFrame:
    """Counts by role set in state of one number a key, never of vectors."""

    def add(key, batches, state):  # noqa: ANN001, ANN202
        import pandas as pd

        n = (state.get[0] if state.exists else 0) + sum(len(b) for b in batches)
        state.update((n,))
        yield pd.DataFrame({"role_id": [key[0]], "n": [n]})

    keyed = events(s, d).select((F.col("user_id") % 5).alias("role_id"), "event_id")
    out = keyed.groupBy("role_id").applyInPandasWithState(add, "role_id bigint, n bigint", "n bigint", "update", "NoTimeout")
    return finish(out, "update").groupBy("role_id").agg(F.max("n").alias("n"))


@_q("stream_policy_apply", "WITH x AS (SELECT user_id % 100 AS vec_id, user_id % 5 AS role_id, CASE WHEN event_id % 3 = 0 THEN 'revoke' ELSE 'grant' END AS op, row_number() OVER (PARTITION BY user_id % 100, user_id % 5 ORDER BY ts DESC, event_id DESC) AS r FROM events) SELECT role_id, count(*) AS n FROM x WHERE r = 1 AND op = 'grant' GROUP BY 1")
def policy_apply(s: SparkSession, d: str) -> DataFrame:
    """Grants and revokes as a stream: each micro-batch is merged into the policy by event time, the last writer winning."""
    path = scratch(s)
    state = {"at": None}
    last = F.max_by(F.struct("op", "ts", "event_id"), F.struct("ts", "event_id"))

    def merge(batch: DataFrame, epoch: int) -> None:
        rows = batch if state["at"] is None else batch.unionByName(s.read.parquet(state["at"]))
        at = f"{path}/{epoch}-{uuid.uuid4().hex}"
        rows.groupBy("vec_id", "role_id").agg(last.alias("x")).select("vec_id", "role_id", "x.op", "x.ts", "x.event_id").write.parquet(at)
        state["at"] = at

    ops = events(s, d).select((F.col("user_id") % 100).alias("vec_id"), (F.col("user_id") % 5).alias("role_id"), F.when(F.col("event_id") % 3 == 0, "revoke").otherwise("grant").alias("op"), "ts", "event_id")
    q = ops.writeStream.foreachBatch(merge).option("checkpointLocation", scratch(s)).trigger(availableNow=True).start()
    q.awaitTermination()
    return s.read.parquet(state["at"]).where("op = 'grant'").groupBy("role_id").agg(F.count("*").alias("n"))

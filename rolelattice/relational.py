"""The relational surface around the methods, each operation on the given tables, with its DuckDB counterpart."""

import uuid
from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .core_queries import _with, blocks_of, tags_of
from .functions import vectors as fv
from .sources.tables import letter_profile, table
from .storage import scratch

Q: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}
c = F.col


def _q(name: str, sql: str | None = None):  # noqa: ANN202
    def add(f: Callable) -> Callable:
        Q[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


# sources and sinks
_q("scan_parquet_pruned", "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_quantity > 45")(lambda s, d: table(s, d, "lineitem").where("l_quantity > 45").select("l_orderkey", "l_quantity"))
for _f in ("csv", "json", "orc"):
    def _trip(s: SparkSession, d: str, f: str = _f) -> DataFrame:
        src = table(s, d, "supplier").select("s_suppkey", "s_name", "s_nationkey")
        path = scratch(s)
        src.write.format(f).save(path)
        return s.read.format(f).schema(src.schema).load(path)

    _q(f"scan_{_f}_roundtrip", "SELECT s_suppkey, s_name, s_nationkey FROM supplier")(_trip)


@_q("scan_partitioned_layout", _with("A") + "SELECT block_id, count(*) AS n FROM tags JOIN blocks USING (role_key) WHERE block_id IN (1, 3) GROUP BY block_id")
def partitioned(s: SparkSession, d: str) -> DataFrame:
    """Write vectors by block, read two blocks: the others' folders are pruned."""
    path = scratch(s)
    ids = F.broadcast(blocks_of(s, d, "A").select("role_key", "block_id"))
    tags_of(s, d, "A").join(ids, "role_key").select("vec_id", "block_id").write.partitionBy("block_id").parquet(path)
    return s.read.parquet(path).where(c("block_id").isin(1, 3)).groupBy("block_id").agg(F.count("*").alias("n"))


@_q("range_rows", "SELECT o_orderkey AS id FROM orders WHERE o_orderkey % 7 = 0")
def range_rows(s: SparkSession, d: str) -> DataFrame:
    """Every seventh row of a range as wide as the table's keys, of which those with an order stay."""
    keys = table(s, d, "orders").select(c("o_orderkey").alias("id"))
    ends = keys.agg(F.min("id").alias("lo"), F.max("id").alias("hi")).first()
    lo, hi = (ends["lo"], ends["hi"] + 1) if ends["hi"] is not None else (0, 0)
    return s.range(lo, hi).where("id % 7 = 0").join(keys, "id", "left_semi")

# filters and projections
_q("filter_role", "SELECT vec_id FROM embeddings WHERE vec_id % 2 = 0")(lambda s, d: tags_of(s, d, "A").where(F.array_contains("roles", 1)).select("vec_id"))
_q("filter_role_and_attr", "SELECT vec_id FROM embeddings WHERE vec_id % 2 = 0 AND label >= 7")(lambda s, d: tags_of(s, d, "A").where(F.array_contains("roles", 1)).join(table(s, d, "embeddings").where("label >= 7").select("vec_id"), "vec_id").select("vec_id"))
_q("filter_in_between_like", "SELECT p_partkey FROM part WHERE p_size BETWEEN 10 AND 20 AND p_brand LIKE '%1%' AND p_partkey % 5 IN (1, 2)")(lambda s, d: table(s, d, "part").where(c("p_size").between(10, 20) & c("p_brand").like("%1%") & (c("p_partkey") % 5).isin(1, 2)).select("p_partkey"))
_q("filter_null_safe", "SELECT doc_id FROM documents LEFT JOIN labels USING (doc_id) WHERE toxic IS NOT DISTINCT FROM NULL")(lambda s, d: table(s, d, "documents").join(table(s, d, "labels"), "doc_id", "left").where(c("toxic").eqNullSafe(None)).select("doc_id"))
_q("filter_tag_overlap", _with("A") + "SELECT vec_id FROM tags WHERE len(list_intersect(roles, [1, 4])) > 0")(lambda s, d: tags_of(s, d, "A").where(F.arrays_overlap("roles", F.array(F.lit(1), F.lit(4)))).select("vec_id"))
_q("project_case", "SELECT o_orderkey, CASE WHEN o_totalprice > 200000 THEN 'high' WHEN o_totalprice > 100000 THEN 'mid' ELSE 'low' END AS band FROM orders")(lambda s, d: table(s, d, "orders").select("o_orderkey", F.when(c("o_totalprice") > 200000, "high").when(c("o_totalprice") > 100000, "mid").otherwise("low").alias("band")))
_q("project_cast", "SELECT c_custkey, CAST(floor(c_acctbal) AS BIGINT) AS whole, CAST(c_nationkey AS VARCHAR) AS nation FROM customer")(lambda s, d: table(s, d, "customer").select("c_custkey", F.floor("c_acctbal").cast("long").alias("whole"), c("c_nationkey").cast("string").alias("nation")))

@_q("sink_bucketed", "SELECT c_nationkey, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
def bucketed(s: SparkSession, d: str) -> DataFrame:
    """Both sides written in buckets by their key: the join then needs no exchange."""
    name = f"b{uuid.uuid4().hex}"
    for t, k in (("orders", "o_custkey"), ("customer", "c_custkey")):
        table(s, d, t).write.bucketBy(8, k).sortBy(k).option("path", scratch(s)).saveAsTable(f"{name}_{t}")
    both = s.table(f"{name}_orders").join(s.table(f"{name}_customer").hint("merge"), c("o_custkey") == c("c_custkey"))
    return both.groupBy("c_nationkey").agg(F.count("*").alias("n"))


@_q("sink_append", "SELECT n_nationkey, n_name FROM nation")
def appended(s: SparkSession, d: str) -> DataFrame:
    """Two appends to one table."""
    path = scratch(s)
    for even in (True, False):
        table(s, d, "nation").where((c("n_nationkey") % 2 == 0) == F.lit(even)).select("n_nationkey", "n_name").write.mode("append").parquet(path)
    return s.read.parquet(path)


@_q("sink_overwrite_partitions", "SELECT n_regionkey, n_nationkey, n_regionkey = 2 AS fresh FROM nation")
def overwritten(s: SparkSession, d: str) -> DataFrame:
    """Only the partitions that new rows fall in are replaced."""
    path = scratch(s)
    rows = table(s, d, "nation").select("n_nationkey", "n_regionkey")
    rows.withColumn("fresh", F.lit(False)).write.partitionBy("n_regionkey").parquet(path)
    rows.where("n_regionkey = 2").withColumn("fresh", F.lit(True)).write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("n_regionkey").parquet(path)
    return s.read.parquet(path).select("n_regionkey", "n_nationkey", "fresh")


# samples
_q("sample_hash", "SELECT o_orderkey FROM orders WHERE CAST('0x' || substr(md5(CAST(o_orderkey AS VARCHAR)), 1, 8) AS BIGINT) % 100 < 10")(lambda s, d: table(s, d, "orders").select("o_orderkey").where(F.conv(F.substring(F.md5(c("o_orderkey").cast("string")), 1, 8), 16, 10).cast("long") % 100 < 10))
_q("sample_strata", "SELECT o_orderpriority, o_orderkey FROM orders WHERE CAST('0x' || substr(md5(CAST(o_orderkey AS VARCHAR)), 1, 8) AS BIGINT) % 100 < CASE o_orderpriority WHEN '1-URGENT' THEN 50 ELSE 5 END")(lambda s, d: table(s, d, "orders").select("o_orderpriority", "o_orderkey").where(F.conv(F.substring(F.md5(c("o_orderkey").cast("string")), 1, 8), 16, 10).cast("long") % 100 < F.when(c("o_orderpriority") == "1-URGENT", 50).otherwise(5)))
_q("sample_bernoulli")(lambda s, d: table(s, d, "orders").sample(0.1, 7).agg(F.count("*").alias("n")))
_q("sample_by")(lambda s, d: table(s, d, "orders").sampleBy("o_orderpriority", {"1-URGENT": 0.5}, 7).groupBy("o_orderpriority").agg(F.count("*").alias("n")))


# joins
_ORD = "SELECT o_orderkey, c_nationkey FROM orders JOIN customer ON o_custkey = c_custkey"
for _h in ("merge", "shuffle_hash", "broadcast"):
    _q({"merge": "join_sortmerge", "shuffle_hash": "join_shuffle_hash", "broadcast": "join_broadcast"}[_h], _ORD if _h != "broadcast" else "SELECT c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey")(
        (lambda s, d, h=_h: table(s, d, "orders").join(table(s, d, "customer").hint(h), c("o_custkey") == c("c_custkey")).select("o_orderkey", "c_nationkey")) if _h != "broadcast" else (lambda s, d: table(s, d, "customer").join(F.broadcast(table(s, d, "nation")), c("c_nationkey") == c("n_nationkey")).select("c_custkey", "n_name"))
    )
_q("join_hash", "SELECT vec_id, role_id, label FROM (" + "SELECT vec_id, 1 AS role_id FROM embeddings WHERE vec_id % 2 = 0" + ") JOIN embeddings USING (vec_id)")(lambda s, d: tags_of(s, d, "A").select("vec_id", F.explode("roles").alias("role_id")).where("role_id = 1").join(table(s, d, "embeddings"), "vec_id").select("vec_id", "role_id", "label"))
_q("join_nested_loop_containment", _with("D") + "SELECT a.block_id AS a, b.block_id AS b FROM blocks a JOIN blocks b ON a.layer < b.layer AND len(list_intersect(a.roles, b.roles)) = a.layer")(lambda s, d: (b := blocks_of(s, d, "D")).select(c("block_id").alias("a"), c("roles").alias("ra"), c("layer").alias("la")).join(F.broadcast(b.select(c("block_id").alias("b"), c("roles").alias("rb"), c("layer").alias("lb"))), F.expr("la < lb and forall(ra, r -> array_contains(rb, r))")).select("a", "b"))


@_q("join_range_weights", "WITH n AS (SELECT r_regionkey, sum(1) OVER (ORDER BY r_regionkey) * 3 AS hi FROM region) SELECT s_suppkey, r_regionkey FROM supplier JOIN n ON s_suppkey % 15 >= hi - 3 AND s_suppkey % 15 < hi")
def range_join(s: SparkSession, d: str) -> DataFrame:
    cum = table(s, d, "region").select("r_regionkey", (F.sum(F.lit(1)).over(Window.orderBy("r_regionkey")) * 3).alias("hi"))
    return table(s, d, "supplier").join(F.broadcast(cum), F.expr("s_suppkey % 15 >= hi - 3 and s_suppkey % 15 < hi")).select("s_suppkey", "r_regionkey")


@_q("join_interval_validity", "WITH g AS (SELECT user_id, ts AS lo, ts + INTERVAL 2 DAY AS hi FROM events WHERE event_type = 'signup') SELECT count(*) AS n, count(DISTINCT e.user_id) AS users FROM events e JOIN g ON e.user_id = g.user_id AND e.ts > g.lo AND e.ts <= g.hi")
def interval_join(s: SparkSession, d: str) -> DataFrame:
    """Events within two days of a sign-up of their user: an equi-join with the interval as a residual condition."""
    e = table(s, d, "events")
    g = e.where("event_type = 'signup'").select(c("user_id").alias("u"), c("ts").alias("lo"), F.expr("ts + interval 2 days").alias("hi"))
    return e.join(g, (c("user_id") == c("u")) & (c("ts") > c("lo")) & (c("ts") <= c("hi"))).agg(F.count("*").alias("n"), F.countDistinct("user_id").alias("users"))


@_q("join_asof_grant", "WITH g AS (SELECT user_id, ts, max(value) AS v FROM events WHERE event_type = 'purchase' GROUP BY ALL), q AS (SELECT event_id, user_id, ts FROM events WHERE event_type = 'view') SELECT q.event_id, round(g.v, 6) AS v FROM q ASOF JOIN g ON q.user_id = g.user_id AND q.ts >= g.ts")
def asof(s: SparkSession, d: str) -> DataFrame:
    """Each view with its user's latest purchase: both sides in one sorted stream, the last value carried forward, so no range product arises."""
    e = table(s, d, "events")
    g = e.where("event_type = 'purchase'").groupBy("user_id", "ts").agg(F.max("value").alias("v")).select("user_id", "ts", F.lit(0).alias("side"), F.lit(None).cast("long").alias("event_id"), "v")
    q = e.where("event_type = 'view'").select("user_id", "ts", F.lit(1).alias("side"), "event_id", F.lit(None).cast("double").alias("v"))
    last = F.last("v", ignorenulls=True).over(Window.partitionBy("user_id").orderBy("ts", "side").rowsBetween(Window.unboundedPreceding, 0))
    return g.union(q).withColumn("v", last).where("side = 1 and v is not null").select("event_id", F.round("v", 6).alias("v"))


_q("join_semi", "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)")(lambda s, d: table(s, d, "customer").join(table(s, d, "orders"), c("c_custkey") == c("o_custkey"), "left_semi").select("c_custkey"))
_q("join_anti", "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)")(lambda s, d: table(s, d, "customer").join(table(s, d, "orders"), c("c_custkey") == c("o_custkey"), "left_anti").select("c_custkey"))
_q("join_left", "SELECT doc_id, coalesce(toxic, -1) AS toxic FROM documents LEFT JOIN labels USING (doc_id)")(lambda s, d: table(s, d, "documents").join(table(s, d, "labels"), "doc_id", "left").select("doc_id", F.coalesce("toxic", F.lit(-1)).alias("toxic")))
_q("join_right", "SELECT d.doc_id, coalesce(l.toxic, -1) AS toxic FROM labels l RIGHT JOIN documents d USING (doc_id)")(lambda s, d: table(s, d, "labels").join(table(s, d, "documents").select("doc_id"), "doc_id", "right").select("doc_id", F.coalesce("toxic", F.lit(-1)).alias("toxic")))
_q("join_full_delta", "WITH a AS (SELECT user_id, count(*) AS n FROM events WHERE ts < TIMESTAMP '2024-01-11' GROUP BY 1), b AS (SELECT user_id, count(*) AS n FROM events WHERE ts >= TIMESTAMP '2024-01-21' GROUP BY 1) SELECT coalesce(a.user_id, b.user_id) AS user_id, coalesce(b.n, 0) - coalesce(a.n, 0) AS delta FROM a FULL JOIN b ON a.user_id = b.user_id")(lambda s, d: table(s, d, "events").where("ts < timestamp '2024-01-11'").groupBy("user_id").agg(F.count("*").alias("a")).join(table(s, d, "events").where("ts >= timestamp '2024-01-21'").groupBy("user_id").agg(F.count("*").alias("b")), "user_id", "full").select("user_id", (F.coalesce("b", F.lit(0)) - F.coalesce("a", F.lit(0))).alias("delta")))
_q("join_cross", "SELECT r_regionkey, n_nationkey FROM region, nation WHERE n_nationkey < 3")(lambda s, d: table(s, d, "region").select("r_regionkey").crossJoin(F.broadcast(table(s, d, "nation").where("n_nationkey < 3").select("n_nationkey"))))
_q("join_self_shared", "SELECT a.s_suppkey AS a, b.s_suppkey AS b FROM supplier a JOIN supplier b ON a.s_nationkey = b.s_nationkey AND a.s_suppkey < b.s_suppkey")(lambda s, d: table(s, d, "supplier").select(c("s_suppkey").alias("a"), "s_nationkey").join(table(s, d, "supplier").select(c("s_suppkey").alias("b"), "s_nationkey"), "s_nationkey").where("a < b").select("a", "b"))
_q("join_nullsafe", "WITH x AS (SELECT doc_id, toxic FROM documents LEFT JOIN labels USING (doc_id)) SELECT coalesce(x.toxic, -1) AS toxic, count(*) AS n FROM x JOIN (VALUES (NULL), (1)) AS v(t) ON x.toxic IS NOT DISTINCT FROM v.t GROUP BY x.toxic")(lambda s, d: table(s, d, "documents").join(table(s, d, "labels"), "doc_id", "left").join(F.broadcast(s.createDataFrame([(None,), (1,)], "t int")), c("toxic").eqNullSafe(c("t"))).groupBy(F.coalesce("toxic", F.lit(-1)).alias("toxic")).agg(F.count("*").alias("n")))


@_q("join_salted", "SELECT n_regionkey, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
def salted(s: SparkSession, d: str) -> DataFrame:
    """A skewed key spread over eight salts on one side and repeated on the other; partial counts meet by the plain key."""
    left = table(s, d, "customer").withColumn("salt", F.pmod(F.xxhash64("c_custkey"), F.lit(8)).cast("int"))
    right = table(s, d, "nation").withColumn("salt", F.explode(F.array(*[F.lit(i) for i in range(8)])))
    return left.join(right.hint("merge"), (left["c_nationkey"] == right["n_nationkey"]) & (left["salt"] == right["salt"])).groupBy("n_regionkey").agg(F.count("*").alias("n"))


# aggregation
_q("agg_hash", "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS qty FROM lineitem GROUP BY ALL")(lambda s, d: table(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty")))
_q("agg_sorted_list", "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY 1")(lambda s, d: table(s, d, "nation").groupBy("n_regionkey").agg(F.array_join(F.sort_array(F.collect_list("n_name")), ",").alias("names")))
_q("agg_distinct", "SELECT count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem")(lambda s, d: table(s, d, "lineitem").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("suppliers")))
_q("agg_approx_distinct")(lambda s, d: table(s, d, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts")))
_q("agg_filter", "SELECT event_type, count(*) FILTER (value > 50) AS high, count(*) AS n FROM events GROUP BY 1")(lambda s, d: table(s, d, "events").groupBy("event_type").agg(F.count_if(c("value") > 50).alias("high"), F.count("*").alias("n")))
_q("agg_rollup", "SELECT coalesce(l_returnflag, '*') AS f, coalesce(l_linestatus, '*') AS s, count(*) AS n FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")(lambda s, d: table(s, d, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.count("*").alias("n")).select(F.coalesce("l_returnflag", F.lit("*")).alias("f"), F.coalesce("l_linestatus", F.lit("*")).alias("s"), "n"))
_q("agg_cube", "SELECT coalesce(l_returnflag, '*') AS f, coalesce(l_linestatus, '*') AS s, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")(lambda s, d: table(s, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n")).select(F.coalesce("l_returnflag", F.lit("*")).alias("f"), F.coalesce("l_linestatus", F.lit("*")).alias("s"), "n"))
_q("agg_grouping_sets", "SELECT coalesce(l_returnflag, '*') AS f, coalesce(l_linestatus, '*') AS s, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus))")(lambda s, d: table(s, d, "lineitem").groupingSets([["l_returnflag"], ["l_linestatus"]], "l_returnflag", "l_linestatus").agg(F.count("*").alias("n")).select(F.coalesce("l_returnflag", F.lit("*")).alias("f"), F.coalesce("l_linestatus", F.lit("*")).alias("s"), "n"))
_q("agg_pivot", "SELECT l_returnflag, count(*) FILTER (l_linestatus = 'F') AS \"F\", count(*) FILTER (l_linestatus = 'O') AS \"O\" FROM lineitem GROUP BY 1")(lambda s, d: table(s, d, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).count().fillna(0))
_q("agg_percentile", "SELECT l_returnflag, round(quantile_cont(l_quantity, 0.5), 6) AS med, round(quantile_cont(l_extendedprice, 0.9), 4) AS p90 FROM lineitem GROUP BY 1")(lambda s, d: table(s, d, "lineitem").groupBy("l_returnflag").agg(F.round(F.percentile("l_quantity", F.lit(0.5)), 6).alias("med"), F.round(F.percentile("l_extendedprice", F.lit(0.9)), 4).alias("p90")))
_q("agg_max_by", "SELECT o_orderpriority, max(o_totalprice) AS top FROM orders GROUP BY 1")(lambda s, d: table(s, d, "orders").groupBy("o_orderpriority").agg(F.max_by("o_totalprice", "o_totalprice").alias("top")))
_q("agg_bit_or", "SELECT label, bit_or(CAST(1 AS BIGINT) << CAST(vec_id % 20 AS INTEGER)) AS mask FROM embeddings GROUP BY 1")(lambda s, d: table(s, d, "embeddings").groupBy("label").agg(F.bit_or(F.expr("shiftleft(1L, cast(vec_id % 20 as int))")).alias("mask")))
_q("agg_regr", "SELECT round(regr_slope(l_extendedprice, l_quantity), 4) AS slope, round(regr_r2(l_extendedprice, l_quantity), 6) AS r2, round(corr(l_extendedprice, l_quantity), 6) AS corr FROM lineitem")(lambda s, d: table(s, d, "lineitem").agg(F.round(F.regr_slope("l_extendedprice", "l_quantity"), 4).alias("slope"), F.round(F.regr_r2("l_extendedprice", "l_quantity"), 6).alias("r2"), F.round(F.corr("l_extendedprice", "l_quantity"), 6).alias("corr")))
_q("agg_stats", "SELECT event_type, round(stddev_samp(value), 6) AS sd, round(var_pop(value), 4) AS vp, round(avg(value), 6) AS mean FROM events GROUP BY 1")(lambda s, d: table(s, d, "events").groupBy("event_type").agg(F.round(F.stddev_samp("value"), 6).alias("sd"), F.round(F.var_pop("value"), 4).alias("vp"), F.round(F.avg("value"), 6).alias("mean")))
_q("agg_having", "SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1 HAVING count(*) > 12")(lambda s, d: table(s, d, "orders").groupBy("o_custkey").agg(F.count("*").alias("n")).where("n > 12"))

# windows


def _w():  # noqa: ANN202
    """A customer's orders in time; made when asked for, since columns need a session."""
    return Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")


_OW = "OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)"
for _n, _sql, _col in (
    ("row_number", "row_number() " + _OW, lambda: F.row_number().over(_w())),
    ("rank_dense", "CAST(dense_rank() " + _OW + " AS BIGINT) + rank() " + _OW, lambda: F.dense_rank().over(_w()) + F.rank().over(_w())),
    ("ntile", "ntile(4) " + _OW, lambda: F.ntile(4).over(_w())),
    ("percent_rank", "round(percent_rank() " + _OW + ", 6)", lambda: F.round(F.percent_rank().over(_w()), 6)),
    ("cume_dist", "round(cume_dist() " + _OW + ", 6)", lambda: F.round(F.cume_dist().over(_w()), 6)),
    ("lag_lead", "coalesce(lag(o_orderkey) " + _OW + ", 0) + coalesce(lead(o_orderkey) " + _OW + ", 0)", lambda: F.coalesce(F.lag("o_orderkey").over(_w()), F.lit(0)) + F.coalesce(F.lead("o_orderkey").over(_w()), F.lit(0))),
    ("first_last_nth", "first_value(o_orderkey) " + _OW + " + coalesce(nth_value(o_orderkey, 2) " + _OW + ", 0)", lambda: F.first("o_orderkey").over(_w()) + F.coalesce(F.nth_value("o_orderkey", 2).over(_w()), F.lit(0))),
    ("rows_frame_budget", "round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING), 2)", lambda: F.round(F.sum("o_totalprice").over(_w().rowsBetween(Window.unboundedPreceding, 0)), 2)),
):
    _q(f"win_{_n}", f"SELECT o_orderkey, {_sql} AS v FROM orders")(lambda s, d, x=_col: table(s, d, "orders").select("o_orderkey", x().alias("v")))
_q("win_range_frame_time", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_ms(ts) // 1000 RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS n FROM events")(lambda s, d: table(s, d, "events").select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy(F.unix_timestamp("ts")).rangeBetween(-86400, 0)).alias("n")))
_q("win_topk_per_query", "SELECT * FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 3")(lambda s, d: table(s, d, "orders").select("o_custkey", "o_orderkey", F.row_number().over(Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")).alias("r")).where("r <= 3"))

# sort, limit, sets
_q("sort_global", "SELECT n_nationkey, row_number() OVER (ORDER BY n_name DESC) AS r FROM nation")(lambda s, d: table(s, d, "nation").select("n_nationkey", F.row_number().over(Window.orderBy(F.desc("n_name"))).alias("r")))
_q("sort_limit_offset", "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10 OFFSET 5")(lambda s, d: table(s, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(5).limit(10).select("o_orderkey"))
_q("topk_take_ordered", "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")(lambda s, d: table(s, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20).select("o_orderkey"))
_q("topk_min_by", "SELECT o_custkey, min(o_orderkey) AS first FROM orders GROUP BY 1")(lambda s, d: table(s, d, "orders").groupBy("o_custkey").agg(F.min_by("o_orderkey", "o_orderkey").alias("first")))
_A, _B = "SELECT c_nationkey AS k FROM customer", "SELECT s_nationkey AS k FROM supplier"
for _n, _op, _f in (("union", "UNION", lambda a, b: a.union(b).distinct()), ("union_all", "UNION ALL", lambda a, b: a.unionByName(b)), ("intersect", "INTERSECT", lambda a, b: a.intersect(b)), ("intersect_all", "INTERSECT ALL", lambda a, b: a.intersectAll(b)), ("except", "EXCEPT", lambda a, b: a.subtract(b)), ("except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b))):
    _q(f"set_{_n}", f"{_A} {_op} {_B}")(lambda s, d, f=_f: f(table(s, d, "customer").select(c("c_nationkey").cast("int").alias("k")), table(s, d, "supplier").select(c("s_nationkey").cast("int").alias("k"))))
_q("set_distinct", "SELECT DISTINCT l_returnflag, l_linestatus FROM lineitem")(lambda s, d: table(s, d, "lineitem").select("l_returnflag", "l_linestatus").distinct())

# scalar functions
_q("str_role_key", _with("C") + "SELECT role_key, length(role_key) AS len, split_part(role_key, ',', 1) AS head FROM blocks")(lambda s, d: blocks_of(s, d, "C").select("role_key", F.length("role_key").alias("len"), F.split_part("role_key", F.lit(","), F.lit(1)).alias("head")))
_q("str_regexp", "SELECT p_partkey, regexp_replace(p_brand, '[0-9]', '#', 'g') AS b, upper(p_type) AS t FROM part")(lambda s, d: table(s, d, "part").select("p_partkey", F.regexp_replace("p_brand", "[0-9]", "#").alias("b"), F.upper("p_type").alias("t")))
_q("str_letter_profile", "SELECT doc_id, round((length(text) - length(replace(lower(text), 'e', ''))) / greatest(length(text), 1), 9) AS e, round((length(text) - length(replace(lower(text), 't', ''))) / greatest(length(text), 1), 9) AS t FROM documents")(lambda s, d: table(s, d, "documents").select("doc_id", letter_profile(c("text")).alias("v")).select("doc_id", F.round(c("v")[4], 9).alias("e"), F.round(c("v")[19], 9).alias("t")))
_q("str_md5_bucket", "SELECT substr(md5(c_name), 1, 1) AS bucket, count(*) AS n FROM customer GROUP BY 1")(lambda s, d: table(s, d, "customer").groupBy(F.substring(F.md5("c_name"), 1, 1).alias("bucket")).agg(F.count("*").alias("n")))
_q("date_parts", "SELECT year(o_orderdate) AS y, month(o_orderdate) AS m, count(*) AS n FROM orders GROUP BY ALL")(lambda s, d: table(s, d, "orders").groupBy(F.year("o_orderdate").cast("long").alias("y"), F.month("o_orderdate").cast("long").alias("m")).agg(F.count("*").alias("n")))
_q("date_trunc_arith", "SELECT event_id, datediff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS days FROM events")(lambda s, d: table(s, d, "events").select("event_id", F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date")).cast("long").alias("days")))
_q("math_cost", "SELECT o_orderkey, round(log2(o_totalprice) + sqrt(o_totalprice) + greatest(1.5, o_orderkey % 3), 6) AS v FROM orders")(lambda s, d: table(s, d, "orders").select("o_orderkey", F.round(F.log2("o_totalprice") + F.sqrt("o_totalprice") + F.greatest(F.lit(1.5), (c("o_orderkey") % 3).cast("double")), 6).alias("v")))
_q("math_bits", "SELECT vec_id, bit_count(vec_id) AS ones, xor(vec_id, 5) AS x FROM embeddings")(lambda s, d: table(s, d, "embeddings").select("vec_id", F.bit_count("vec_id").cast("int").alias("ones"), c("vec_id").bitwiseXOR(F.lit(5)).alias("x")))
_q("arr_set_ops", _with("A") + "SELECT vec_id, len(list_intersect(roles, [1, 2, 3])) AS common, len(list_distinct(list_concat(roles, [1, 2, 3]))) AS either FROM tags")(lambda s, d: tags_of(s, d, "A").select("vec_id", F.size(F.array_intersect("roles", F.array(*[F.lit(i) for i in (1, 2, 3)]))).cast("long").alias("common"), F.size(F.array_union("roles", F.array(*[F.lit(i) for i in (1, 2, 3)]))).cast("long").alias("either")))
_q("arr_higher_order", _with("A") + "SELECT vec_id, CAST(list_sum(list_transform(roles, lambda r: r * r)) AS BIGINT) AS v FROM tags")(lambda s, d: tags_of(s, d, "A").select("vec_id", F.aggregate("roles", F.lit(0).cast("long"), lambda a, r: a + r * r).alias("v")))
_q("arr_explode", _with("A") + "SELECT vec_id, role_id FROM grants")(lambda s, d: tags_of(s, d, "A").select("vec_id", F.explode("roles").alias("role_id")))
_q("map_plan", _with("D") + "SELECT role_id, count(*) AS units FROM (SELECT unnest(roles) AS role_id FROM blocks) GROUP BY 1")(lambda s, d: blocks_of(s, d, "D").select(F.explode("roles").alias("role_id"), "block_id").groupBy("role_id").agg(F.map_from_entries(F.collect_list(F.struct("block_id", F.lit(True).alias("v")))).alias("m")).select("role_id", F.size(F.map_keys("m")).cast("long").alias("units")))
_q("struct_heap_entry", "SELECT o_custkey, min(o_totalprice) AS low FROM orders GROUP BY 1")(lambda s, d: table(s, d, "orders").groupBy("o_custkey").agg(F.min(F.struct("o_totalprice", "o_orderkey")).alias("m")).select("o_custkey", c("m.o_totalprice").alias("low")))
_q("json_props", "SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1")(lambda s, d: table(s, d, "events").groupBy(F.get_json_object("props", "$.k").cast("long").alias("k")).agg(F.count("*").alias("n")))

# vectors: each with the vector of the next id
_NEXT = "FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1"
_PROD = "list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda p: CAST(p[1] AS DOUBLE) * CAST(p[2] AS DOUBLE)))"


def _next(s: SparkSession, d: str) -> DataFrame:
    e = table(s, d, "embeddings")
    return e.select("vec_id", c("embedding").alias("x")).join(e.select((c("vec_id") - 1).alias("vec_id"), c("embedding").alias("y")), "vec_id")


_q("vec_inner", f"SELECT a.vec_id, round({_PROD}, 9) AS v {_NEXT}")(lambda s, d: _next(s, d).select("vec_id", F.round(fv.inner(c("x"), c("y")), 9).alias("v")))
_q("vec_l2", f"SELECT a.vec_id, round(sqrt(list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda p: (CAST(p[1] AS DOUBLE) - CAST(p[2] AS DOUBLE)) ** 2))), 9) AS v {_NEXT}")(lambda s, d: _next(s, d).select("vec_id", F.round(fv.l2(c("x"), c("y")), 9).alias("v")))
_q("vec_norm", "SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda v: CAST(v AS DOUBLE) * CAST(v AS DOUBLE)))), 9) AS v FROM embeddings")(lambda s, d: table(s, d, "embeddings").select("vec_id", F.round(fv.norm(c("embedding")), 9).alias("v")))
_q("vec_cosine", f"SELECT a.vec_id, round({_PROD} / (sqrt({_PROD.replace('b.embedding', 'a.embedding')}) * sqrt({_PROD.replace('a.embedding', 'b.embedding')})), 9) AS v {_NEXT}")(lambda s, d: _next(s, d).select("vec_id", F.round(fv.cosine(c("x"), c("y")), 9).alias("v")))
_q("vec_centroid", "SELECT label, i AS pos, round(avg(CAST(v AS DOUBLE)), 9) AS v FROM (SELECT label, unnest(range(64)) AS i, unnest(embedding) AS v FROM embeddings) GROUP BY ALL")(lambda s, d: table(s, d, "embeddings").select("label", F.posexplode("embedding").alias("pos", "v")).groupBy("label", c("pos").cast("long").alias("pos")).agg(F.round(F.avg(c("v").cast("double")), 9).alias("v")))


# functions in Python
def _centroid(s: SparkSession, d: str) -> DataFrame:
    @F.pandas_udf("double")
    def mean(v: pd.Series) -> float:
        return float(v.mean())

    return table(s, d, "embeddings").groupBy("label").agg(mean(c("embedding")[0].cast("double")).alias("v")).select("label", F.round("v", 6).alias("v"))


_q("udf_pandas_agg", "SELECT label, round(avg(CAST(embedding[1] AS DOUBLE)), 6) AS v FROM embeddings GROUP BY 1")(_centroid)


@_q("udf_pandas_scalar", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda v: CAST(v AS DOUBLE))), 6) AS v FROM embeddings")
def scalar_udf(s: SparkSession, d: str) -> DataFrame:
    @F.pandas_udf("double")
    def total(v):  # noqa: ANN001, ANN202
        import numpy as np

        return v.map(lambda x: float(np.asarray(x, float).sum()))

    return table(s, d, "embeddings").select("vec_id", F.round(total("embedding"), 6).alias("v"))


@_q("udf_grouped_map", "SELECT label, count(*) AS n FROM embeddings GROUP BY 1")
def grouped_map(s: SparkSession, d: str) -> DataFrame:
    def count(pdf):  # noqa: ANN001, ANN202
        return pdf.groupby("label", as_index=False).agg(n=("vec_id", "size"))

    return table(s, d, "embeddings").select("label", "vec_id").groupBy("label").applyInPandas(count, "label int, n bigint")


@_q("udf_map_in_pandas", "SELECT vec_id FROM embeddings WHERE label = 3")
def map_in_pandas(s: SparkSession, d: str) -> DataFrame:
    def keep(it):  # noqa: ANN001, ANN202
        for pdf in it:
            yield pdf.loc[pdf["label"] == 3, ["vec_id"]]

    return table(s, d, "embeddings").select("vec_id", "label").mapInPandas(keep, "vec_id bigint")


@_q("udf_cogrouped", "SELECT n_nationkey AS k, (SELECT count(*) FROM customer WHERE c_nationkey = n_nationkey) AS customers, (SELECT count(*) FROM supplier WHERE s_nationkey = n_nationkey) AS suppliers FROM nation WHERE customers + suppliers > 0")
def cogrouped(s: SparkSession, d: str) -> DataFrame:
    def both(key, a, b):  # noqa: ANN001, ANN202
        import pandas as pd

        return pd.DataFrame({"k": [key[0]], "customers": [len(a)], "suppliers": [len(b)]})

    a = table(s, d, "customer").select(c("c_nationkey").cast("int").alias("k")).groupBy("k")
    return a.cogroup(table(s, d, "supplier").select(c("s_nationkey").cast("int").alias("k")).groupBy("k")).applyInPandas(both, "k int, customers bigint, suppliers bigint")


@_q("udtf_partitions", "SELECT n, n - 1 AS parts FROM (SELECT DISTINCT count(*) AS n FROM lineitem GROUP BY l_orderkey) WHERE n > 1")
def udtf_partitions(s: SparkSession, d: str) -> DataFrame:
    """A table function that lists the ways to cut a row of n line items in two, for each n that an order has."""

    @F.udtf(returnType="n bigint, at bigint")
    class Cuts:
        def eval(self, n: int):  # noqa: ANN202
            for at in range(1, n):
                yield n, at

    s.udtf.register("two_cuts", Cuts)
    name = f"r{uuid.uuid4().hex}"
    table(s, d, "lineitem").groupBy("l_orderkey").agg(F.count("*").alias("n")).select("n").distinct().createOrReplaceTempView(name)
    return s.sql(f"SELECT c.n, count(*) AS parts FROM {name} r, LATERAL two_cuts(r.n) c GROUP BY c.n")


@_q("udtf_topk", "SELECT o_custkey, o_orderkey FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 2")
def udtf_topk(s: SparkSession, d: str) -> DataFrame:
    """A table function over the sorted rows of each partition of its argument that keeps the first two."""

    @F.udtf(returnType="o_custkey bigint, o_orderkey bigint")
    class First:
        def __init__(self) -> None:
            self.n = 0

        def eval(self, row) -> object:  # noqa: ANN001
            self.n += 1
            if self.n <= 2:
                yield row["o_custkey"], row["o_orderkey"]

    s.udtf.register("first_two", First)
    name = f"o{uuid.uuid4().hex}"
    table(s, d, "orders").select("o_custkey", "o_orderkey", "o_totalprice").createOrReplaceTempView(name)
    return s.sql(f"SELECT * FROM first_two(TABLE({name}) PARTITION BY o_custkey ORDER BY (o_totalprice DESC, o_orderkey))")


# SQL surface
def sql(s: SparkSession, d: str, text: str, **args: object) -> DataFrame:
    """Run SQL over views of the given tables."""
    import re

    for name in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "labels"):
        if re.search(rf"\b{name}\b", text):
            table(s, d, name).createOrReplaceTempView(name)
    return s.sql(text, args=args or None)


for _n, _t in (
    ("sql_cte", "WITH big AS (SELECT o_custkey, sum(o_totalprice) AS t FROM orders GROUP BY o_custkey) SELECT o_custkey, round(t, 2) AS t FROM big WHERE t > 2000000"),
    ("sql_correlated", "SELECT c_custkey FROM customer WHERE (SELECT count(*) FROM orders WHERE o_custkey = c_custkey) > 11"),
    ("sql_exists", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)"),
    ("sql_lateral", "SELECT n_name, t.top FROM nation, LATERAL (SELECT max(s_acctbal) AS top FROM supplier WHERE s_nationkey = n_nationkey) t"),
):
    _q(_n, _t)(lambda s, d, t=_t: sql(s, d, t))
_q("sql_args", "SELECT p_partkey FROM part WHERE p_size > 45")(lambda s, d: sql(s, d, "SELECT p_partkey FROM part WHERE p_size > :least", least=45))


@_q("secure_view", "SELECT vec_id FROM embeddings WHERE vec_id % 3 = 0")
def secure_view(s: SparkSession, d: str) -> DataFrame:
    """A view that shows a role its vectors alone."""
    tags_of(s, d, "A").where(F.array_contains("roles", 2)).select("vec_id").createOrReplaceTempView("vectors_of_role")
    return s.sql("SELECT vec_id FROM vectors_of_role")

"""Top-k search under access control: exact, unit by unit, and coordinated in two stages with a bound.

Distances are squared L2. A result holds a vector once however many units hold it; ties go to the smaller id. Queries have qid, x,
roles, qclass and may have efs, a beam of their own.
"""

from __future__ import annotations

import math
from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from ..storage import kept, trim
from . import hnsw
from .layout import runs, small, spread_out

HITS = "qid bigint, vec_id bigint, dist double"
#: Vectors of a block that one task of exact search holds.
SCAN_ROWS = 50_000


def best(hits: DataFrame, k_of: DataFrame | None = None, k: int = 10) -> DataFrame:
    """qid, rank, vec_id, dist: the k nearest of each query. The rank filter reaches the map side, so k rows for each task and query are shuffled."""
    one = hits.groupBy("qid", "vec_id").agg(F.min("dist").alias("dist"))
    if k_of is not None:
        one = one.join(k_of.select("qid", "k"), "qid")
    else:
        one = one.withColumn("k", F.lit(k))
    nth = F.row_number().over(Window.partitionBy("qid").orderBy("dist", "vec_id"))
    return one.withColumn("rank", nth).where("rank <= k").select("qid", "rank", "vec_id", "dist")


def exact(queries: DataFrame, vectors: DataFrame, tags: DataFrame, blocks: DataFrame, k: int = 10, rows: int = SCAN_ROWS) -> DataFrame:
    """queries (qid, x, roles) against all vectors that share a role with them: block by block, a block in as many shards as its size asks for."""
    sized = blocks.select("block_id", "role_key", "roles", F.greatest(F.ceil(F.col("n") / rows), F.lit(1)).cast("int").alias("shards"))
    routed = queries.select("qid", "x", F.explode("roles").alias("role_id")).join(sized.select("block_id", "shards", F.explode("roles").alias("role_id")), "role_id").select("qid", "x", "block_id", "shards").dropDuplicates(["qid", "block_id"])
    spread = routed.select("qid", "x", "block_id", F.explode(F.sequence(F.lit(0), F.col("shards") - 1)).alias("shard"))
    block_of = tags.select("vec_id", "role_key").join(small(sized.select("role_key", "block_id", "shards")), "role_key")
    held = vectors.join(block_of, "vec_id").select("block_id", F.pmod(F.xxhash64("vec_id"), F.col("shards")).cast("int").alias("shard"), "vec_id", "embedding")

    def scan(qs, vs):  # noqa: ANN001, ANN202
        import numpy as np

        out = []
        if qs.num_rows and vs.num_rows:
            v, x, ids = matrix(vs["embedding"]), matrix(qs["x"]), vs["vec_id"].to_numpy()
            for q, one in zip(qs["qid"].to_pylist(), x, strict=True):
                d = ((v - one) ** 2).sum(1)
                near = np.flatnonzero(d <= np.partition(d, k - 1)[k - 1]) if len(d) > k else np.arange(len(d))
                top = near[np.lexsort((ids[near], d[near]))][:k]
                out.append((np.full(len(top), q), ids[top], d[top]))
        cols = [np.concatenate(c) for c in zip(*out, strict=True)] if out else [[], [], []]
        return pa.table([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int64(), pa.float64()), strict=True)], names=["qid", "vec_id", "dist"])

    held = held.select(*[F.col(x).alias(x) for x in held.columns])  # both sides stem from the blocks
    return best(spread.groupBy("block_id", "shard").cogroup(held.groupBy("block_id", "shard")).applyInArrow(scan, HITS), k=k)


def matrix(column):  # noqa: ANN001, ANN201
    """Lists of equal length as the rows of a matrix of doubles."""
    import numpy as np

    flat = column.combine_chunks().flatten()
    return np.asarray(flat.to_numpy(zero_copy_only=False), np.float64).reshape(len(column), -1)


def bind(queries: DataFrame, plan: DataFrame) -> DataFrame:
    """qid, x, roles, unit_id, kind, pure, lambda: each query with the units of its class (a column qclass on both)."""
    return queries.join(small(plan.select("qclass", "unit_id", "kind", "pure", "lambda")), "qclass")


STAGE = HITS + ", unit_id int, shard int, final boolean, kth double, probed int, spent int, inflated int, work bigint, seconds double, state binary"
_COLUMNS = [x.split()[0] for x in STAGE.split(", ")]


def frame(rows: list[tuple], names: list[str]):  # noqa: ANN201
    """Rows as pandas; ids stay whole numbers beside nulls."""
    import pandas as pd

    cols = list(zip(*rows, strict=True)) if rows else [[] for _ in names]
    return pd.DataFrame({n: pd.array(list(c), dtype="Int64") if n == "vec_id" else list(c) for n, c in zip(names, cols, strict=True)})


def _stage(spread: DataFrame, placed: DataFrame, graphs: DataFrame | None, roles_of: dict[int, frozenset[int]], k: int, mode: str) -> DataFrame:
    """Rows of hits, and one row without a hit for each (query, unit, shard) with its counters. spread: queries with unit_id, shard, kind, efs.

    mode first: pure units and leftovers in full, impure ones at the plain beam, with the k-th distance of all that was seen and
    the state of the search; full: every unit at its inflated beam; rest: impure ones from that state (column `state`) on,
    up to the distance in the column `bound`."""

    def run(key, qs, vs):  # noqa: ANN001, ANN202
        import time

        import numpy as np
        import pandas as pd

        g = vs if isinstance(vs, hnsw.Graph) else None
        if not len(qs) or g is None and not len(vs):
            return pd.DataFrame({c: [] for c in _COLUMNS})
        out = []
        if g is None:
            ids, blocks, v = vs["vec_id"].to_numpy(), vs["block_id"].to_numpy(), np.stack(vs["embedding"].to_list()).astype(float)
        else:
            ids, blocks = g.ids, g.blocks
        named, where = np.unique(blocks, return_inverse=True)
        for q in qs.itertuples():
            began, done, state = time.perf_counter(), g.work if g else 0, None
            mine, efs = frozenset(q.roles), int(q.efs)
            ok = np.array([bool(roles_of[b] & mine) for b in named.tolist()])[where]
            lam = float(len(ids) / ok.sum()) if ok.any() else 1.0
            pure = bool(ok.all())
            wide = min(max(len(ids), efs), math.ceil(math.ceil(lam) * efs))
            kth, probed, spent, final = math.inf, 0, 0, True
            if g is None:
                d = ((v - np.asarray(q.x, float)) ** 2).sum(1)
                order = np.lexsort((ids, d))
                if pure or q.kind == "leftover" or mode != "first":
                    take = order[ok[order]][:k]
                else:
                    take, final = order[:k], False
                    kth = float(d[take[-1]]) if len(take) == k else math.inf
                    take = take[ok[take]]
                    final = len(order) <= k
                got = [(float(d[i]), int(i)) for i in take]
                probed = len(ids)
            elif pure:
                got = hnsw.search(g, q.x, k, efs)
                probed = efs
            elif mode == "full":
                d, at = hnsw.found(g, q.x, wide)
                may = ok[at]
                got = list(zip(d[may][:k].tolist(), at[may][:k].tolist(), strict=True))
                probed = wide
            else:
                cursor = hnsw.Cursor(g, q.x, q.state if mode == "rest" else None)
                if mode == "rest":
                    spent = len(cursor.resume(wide - efs, q.bound))
                else:
                    cursor.resume(efs)
                    seen = cursor.nearest(k)
                    kth = seen[-1][0] if len(seen) >= k else math.inf
                    final, state = not cursor.todo, cursor.dump()
                got = [(d, i) for d, i in cursor.nearest(wide) if ok[i]][:k]
                probed = efs
            inflated = max(0, wide - efs) if not pure else 0
            took = time.perf_counter() - began
            work = g.work - done if g else len(ids)
            out.append((q.qid, None, None, key[0], key[1], final, kth, probed, spent, inflated, work, took, state))
            out += [(q.qid, int(ids[i]), d, key[0], key[1], final, kth, probed, spent, inflated, 0, 0.0, None) for d, i in got]
        return frame(out, _COLUMNS)

    both = []
    for kind in ("index", "leftover"):
        qs = spread.where(F.col("kind") == kind)
        if kind == "index" and graphs is not None:
            both.append(met(qs, graphs, F.col("efs") * F.ceil(F.coalesce("lambda", F.lit(1.0))), run, STAGE))
            continue
        rows = placed.where(F.col("kind") == kind).select("unit_id", "shard", "block_id", "vec_id", "embedding")
        rows = rows.select(*[F.col(c).alias(c) for c in rows.columns])  # both sides stem from the placed rows
        both.append(qs.groupBy("unit_id", "shard").cogroup(rows.groupBy("unit_id", "shard")).applyInPandas(run, STAGE))
    return both[0].union(both[1])


#: Visits of a shard's graph that are not worth a second copy of it.
PART_VISITS = 10
_PART = ["unit_id", "shard", "part"]


def dealt(queries: DataFrame, graphs: DataFrame, weight: F.Column):  # noqa: ANN201
    """Both sides of a cogroup of queries with their shards' graphs (unit_id, shard, ...), grouped by unit, shard and part."""
    one, two, wide = parted(queries, graphs, weight)
    return one.repartition(wide, *_PART).groupBy(*_PART), two.repartition(wide, *_PART).groupBy(*_PART)


def parted(queries: DataFrame, graphs: DataFrame, weight: F.Column) -> tuple[DataFrame, DataFrame, int]:
    """Queries and graphs with the part of their shard, and the partitions to hash unit, shard and part into.

    The queries of a shard that weighs more than a task's fair share are dealt to several tasks, and its graph is given to each. All
    together, no more graphs are added than the tasks that the cluster runs at once, twice over."""
    tasks = 2 * queries.sparkSession.sparkContext.defaultParallelism
    spent = queries.groupBy("unit_id", "shard").agg(F.sum(weight).alias("_w"), F.count("*").alias("_n"))
    share = F.ceil(tasks * F.col("_w") / F.sum("_w").over(Window.partitionBy()))
    parts = spent.select("unit_id", "shard", "_w", F.least(share, F.ceil(F.col("_n") / PART_VISITS)).cast("int").alias("_parts"))
    shards = [(r["unit_id"], r["shard"], float(r["_w"] or 0), r["_parts"]) for r in parts.collect()]  # a row for each shard
    part, wide = spread_out(queries.sparkSession, shards, max(tasks, int(queries.sparkSession.conf.get("spark.sql.shuffle.partitions"))))
    one = queries.join(part, ["unit_id", "shard"]).where("nth = pmod(xxhash64(qid), parts)").drop("nth", "parts")
    two = graphs.join(part.select("unit_id", "shard", "part"), ["unit_id", "shard"])
    return one, two.select(*[F.col(c).alias(c) for c in two.columns]), wide  # both sides may stem from the same rows


def met(queries: DataFrame, graphs: DataFrame, weight: F.Column, run: Callable, schema: str) -> DataFrame:
    """What run(key, queries, graph) makes of the queries and the graph of each part of a shard.

    A task reads one stream of rows: a part's graph, piece by piece, then its queries, of which few are held at once. So a worker holds
    one copy of one graph, and the JVM none."""
    one, two, wide = parted(queries, graphs, weight)
    asked = one.select(*_PART, F.lit((1 << 31) - 1).alias("nth"), F.lit(None).cast("binary").alias("graph"), F.struct(*queries.columns).alias("asked"))
    rows = asked.unionByName(two.select(*_PART, "nth", "graph"), allowMissingColumns=True).repartition(wide, *_PART).sortWithinPartitions(*_PART, "nth")
    kinds = to_arrow_schema(T._parse_datatype_string(schema))

    def each(batches):  # noqa: ANN001, ANN202
        now, joined, graph = None, None, None
        for key, some in runs(batches, 256):
            if key != now:
                now, graph = key, None  # the one before goes first
                joined = hnsw.Joined()
            pieces = some.num_rows - some.column(4).null_count
            for piece in some.column(4).slice(0, pieces):
                joined.add(piece.as_buffer())
            if pieces < some.num_rows:
                graph = graph or joined.graph()
                if graph is not None:
                    qs = pa.RecordBatch.from_struct_array(some.column(5).slice(pieces)).to_pandas()
                    yield pa.RecordBatch.from_pandas(run(key, qs, graph), kinds, preserve_index=False)
        joined = graph = None
        trim()

    return rows.mapInArrow(each, schema)


def with_beam(queries: DataFrame, efs: int) -> DataFrame:
    return queries if "efs" in queries.columns else queries.withColumn("efs", F.lit(efs))


def sharded(bound: DataFrame, placed: DataFrame) -> DataFrame:
    """Bound queries with each shard of their units."""
    return bound.join(small(placed.select("unit_id", "shard").distinct()), "unit_id")


def independent(queries: DataFrame, plan: DataFrame, placed: DataFrame, roles_of: dict[int, frozenset[int]], graphs: DataFrame | None = None, k: int = 10, efs: int = 100) -> DataFrame:
    """Every unit of the plan by itself (impure ones at the inflated beam), then one merge. Without graphs, units are scanned."""
    return best(visits(queries, plan, placed, roles_of, graphs, k, efs).where("vec_id is not null").select("qid", "vec_id", "dist"), k=k)


def visits(queries: DataFrame, plan: DataFrame, placed: DataFrame, roles_of: dict[int, frozenset[int]], graphs: DataFrame | None = None, k: int = 10, efs: int = 100) -> DataFrame:
    """Hits and counters of all visits of independent search."""
    return _stage(sharded(bind(with_beam(queries, efs), plan), placed), placed, graphs, roles_of, k, "full")


def coordinated(queries: DataFrame, plan: DataFrame, placed: DataFrame, roles_of: dict[int, frozenset[int]], graphs: DataFrame | None = None, k: int = 10, efs: int = 100) -> tuple[DataFrame, DataFrame]:
    """(results, counters by query).

    First leftovers, pure units, and a plain probe of impure ones. Their authorized hits give the k-th distance as a bound. An
    impure unit whose plain probe's unfiltered k-th distance is not below it is skipped; the others go on from where their
    probe ended, up to the bound. The first stage is written once, so that a lost executor costs no second probe."""
    spread = sharded(bind(with_beam(queries, efs), plan), placed)
    first = kept(_stage(spread, placed, graphs, roles_of, k, "first"))
    hits = first.where("vec_id is not null").select("qid", "vec_id", "dist")
    kth = best(hits, k=k).where(F.col("rank") == k).select("qid", F.col("dist").alias("bound"))
    open_ = first.where("vec_id is null and not final").join(kth, "qid", "left").withColumn("bound", F.coalesce("bound", F.lit(math.inf)))
    live = open_.where("bound > kth").select("qid", "unit_id", "shard", "bound", "state")
    again = spread.join(live, ["qid", "unit_id", "shard"])
    second = kept(_stage(again, placed, graphs, roles_of, k, "rest"))
    result = best(hits.union(second.where("vec_id is not null").select("qid", "vec_id", "dist")), k=k)
    total = first.where("vec_id is null").groupBy("qid").agg(F.sum("work").alias("work"), F.sum("seconds").alias("seconds"))
    seen = open_.groupBy("qid").agg(F.count("*").alias("impure"), F.sum(F.when(F.col("bound") <= F.col("kth"), 1).otherwise(0)).alias("skipped"), F.sum("inflated").alias("inflated"))
    more = second.where("vec_id is null").groupBy("qid").agg(F.sum("spent").alias("spent"), F.sum("work").alias("more_work"), F.sum("seconds").alias("more_seconds"))
    counters = total.join(seen, "qid", "left").join(more, "qid", "left").fillna(0)
    return result, counters.select("qid", "impure", "skipped", "inflated", "spent", (F.col("work") + F.col("more_work")).alias("work"), (F.col("seconds") + F.col("more_seconds")).alias("seconds"))


def leak_check(result: DataFrame, queries: DataFrame, tags: DataFrame) -> DataFrame:
    """Result rows that the query's roles do not allow (must be none)."""
    seen = result.join(queries.select("qid", F.col("roles").alias("_mine")), "qid").join(tags.select("vec_id", "roles"), "vec_id", "left")
    return seen.where("roles is null or not arrays_overlap(roles, _mine)").select("qid", "vec_id")

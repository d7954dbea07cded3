"""Searches over grids of methods, beams, budgets and query sets, on graphs: recall, work and rates.

A grid is one job: queries are repeated for each beam and method, and the units of all methods stand side by side under unit numbers
of their own. Rates are queries for each second that workers spent inside searches, which leaves out what scheduling costs;
`work`, the number of distances, does not depend on the machine.
"""

from __future__ import annotations

import time
from collections import Counter
from collections.abc import Callable, Iterable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import core_queries as cq
from .functions import cost as fc
from .functions.cost import CostModel
from .operators import hnsw
from .operators import metrics as om
from .operators import search as osr
from .operators.layout import graphs, place
from .plans import baselines, cover, sweep
from .plans.state import HELD, PLAN, Control, Layout, average_cost, control, lines, tables
from .sources import policy as sp
from .sources import workload as sw
from .storage import at_once, kept, local

Q: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}
M, EFS, K, EFC = cq.M, cq.EFS, cq.K, cq.EFC
METHODS = ("sweep", "rescoring", "mined", "rolepart", "global", "oracle")
#: Beams of the grid; filtered variants of the global graph: name, through barred neighbours, links.
BEAMS, FILTERED = (10, 50, 100, 300, 500, 1000), (("one_hop", True, 16), ("gamma", False, 12 * 16))
#: Room for a method's unit numbers, for beams and for query numbers in a composed one.
_UNITS, _BEAM, _QUERY = 1 << 20, 1 << 12, 1 << 20


def _q(name: str, sql: str | None = None):  # noqa: ANN202
    def add(f: Callable) -> Callable:
        Q[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def composed(method: int) -> F.Column:
    """One query number out of method, beam and query."""
    return (F.lit(method).cast("long") * _BEAM + F.col("efs")) * _QUERY + F.col("qid")


def split(hits: DataFrame, names: Iterable[str]) -> DataFrame:
    """method, efs and qid back from the composed number."""
    which = F.element_at(F.array(*[F.lit(n) for n in names]), (F.shiftright("qid", 32) + 1).cast("int"))
    return hits.withColumns({"method": which, "efs": F.shiftright("qid", 20).bitwiseAND(F.lit(_BEAM - 1)).cast("int"), "qid": F.col("qid").bitwiseAND(F.lit(_QUERY - 1))})


def layouts_side_by_side(s: SparkSession, c: Control, layouts: dict[str, Layout]) -> tuple[DataFrame, DataFrame]:
    """node_blocks and plan of all layouts, with unit numbers for all and class names for each. A unit that several layouts have is placed once, for all of them."""
    ids, held, plan = {}, [], []
    for m, layout in enumerate(layouts.values()):
        times, named = Counter(), {}
        for i, u in sorted(layout.units.items()):
            key = u.indexed, frozenset(u.blocks)
            times[key] += 1
            one = key, times[key]  # equal units of one layout stay apart
            if one not in ids:
                ids[one] = m * _UNITS + i
            named[i] = ids[one]
        mine, rows = lines(c, Layout({named[i]: u for i, u in layout.units.items()}, {q: tuple(named[i] for i in units) for q, units in layout.plans.items()}), f"{m}:")
        held += [x for x in mine if x[0] >= m * _UNITS]
        plan += rows
    return local(s, held, HELD), local(s, plan, PLAN)


def repeated(q: DataFrame, methods: int, beams: Iterable[int]) -> DataFrame:
    """Queries for each method and beam."""
    each = q.withColumn("efs", F.explode(F.array(*[F.lit(e) for e in beams])))
    out = None
    for m in range(methods):
        one = each.select(composed(m).alias("qid"), "x", "roles", F.concat(F.lit(f"{m}:"), "qclass").alias("qclass"), "efs")
        out = one if out is None else out.union(one)
    return out


def scored(hits: DataFrame, truth: DataFrame, names: Iterable[str], queries: int) -> DataFrame:
    """method, efs, recall, work and rate of hits with counters; truth: qid, vec_id."""
    got = split(osr.best(hits.where("vec_id is not null").select("qid", "vec_id", "dist"), k=K), names)
    hit = got.join(truth.select("qid", "vec_id", F.lit(1).alias("hit")), ["qid", "vec_id"], "left")
    per = hit.groupBy("method", "efs", "qid").agg(F.sum(F.coalesce("hit", F.lit(0))).alias("found"))
    of = truth.groupBy("qid").agg(F.count("*").alias("of"))
    recall = per.join(of, "qid").groupBy("method", "efs").agg((F.sum(F.col("found") / F.col("of")) / queries).alias("recall"))
    spent = split(hits.where("vec_id is null").select("qid", "work", "seconds"), names).groupBy("method", "efs").agg((F.sum("work") / queries).alias("work"), (queries / F.sum("seconds")).alias("rate"))
    return recall.join(spent, ["method", "efs"])


def grid(s: SparkSession, q: DataFrame, v: DataFrame, t: DataFrame, b: DataFrame, c: Control, layouts: dict[str, Layout], beams: Iterable[int] = BEAMS, truth: DataFrame | None = None) -> DataFrame:
    """Graph search of each layout at each beam."""
    held, plan = layouts_side_by_side(s, c, layouts)
    placed = kept(place(v, t, b, held))
    hits = kept(osr.visits(repeated(q, len(layouts), beams), plan, placed, c.roles, kept(graphs(placed, efc=EFC)), K))
    return scored(hits, kept(osr.exact(q, v, t, b)) if truth is None else truth, list(layouts), q.count())


def filtered_hits(q: DataFrame, v: DataFrame, t: DataFrame, b: DataFrame, c: Control, beams: Iterable[int], variants: Iterable[tuple[str, bool, int]] = FILTERED) -> DataFrame:
    """Hits and counters of filtering during traversal, the variants on graphs of all vectors."""
    roles, hits = c.roles, None
    held, _ = tables(q.sparkSession, c, baselines.global_index(c))
    placed = kept(place(v, t, b, held))
    made = [cq.graphs(placed, m=links, efc=EFC) for _, _, links in variants]
    built = at_once(*[lambda g=g: kept(g) for g in made])  # side by side; a union of them may be one task
    for m, ((_, two, _), g) in enumerate(zip(variants, built, strict=True)):
        each = q.withColumn("efs", F.explode(F.array(*[F.lit(e) for e in beams])))
        spread = osr.sharded(each.select(composed(m).alias("qid"), "x", "roles", "efs", F.lit(0).alias("unit_id")), placed)
        one = osr.met(spread, g, F.col("efs"), _filtered(roles, two), osr.HITS + ", work bigint, seconds double")
        hits = one if hits is None else hits.union(one)
    return hits


def _filtered(roles: dict[int, frozenset[int]], two: bool) -> Callable:
    def run(_, qs, graph):  # noqa: ANN001, ANN202
        import numpy as np

        names, rows = ["qid", "vec_id", "dist", "work", "seconds"], []
        named, where = np.unique(graph.blocks, return_inverse=True)
        for x in qs.itertuples():
            began, done, mine = time.perf_counter(), graph.work, frozenset(x.roles)
            ok = np.array([bool(roles[i] & mine) for i in named.tolist()])[where]
            got = hnsw.filtered(graph, x.x, ok, K, int(x.efs), two)
            rows.append((x.qid, None, None, graph.work - done, time.perf_counter() - began))
            rows += [(x.qid, int(graph.ids[i]), dist, 0, 0.0) for dist, i in got]
        return osr.frame(rows, names)

    return run


def filtered_grid(q: DataFrame, v: DataFrame, t: DataFrame, b: DataFrame, c: Control, beams: Iterable[int], truth: DataFrame) -> DataFrame:
    return scored(kept(filtered_hits(q, v, t, b, c, beams)), truth, [n for n, *_ in FILTERED], q.count())


def made(s: SparkSession, d: str, p: str, c: Control, methods: Iterable[str], budget: float = 1.1, past: Counter | None = None) -> dict[str, Layout]:
    history = past if past is not None else cq.past_of(s, d, p)
    return {m: cq.layout_of(c, m, budget, cq.THRESHOLD[p], history) for m in methods}


# rate against recall
def rates(s: SparkSession, d: str, p: str, beams: Iterable[int] = BEAMS) -> DataFrame:
    """method, efs, recall, work, rate of all compared methods, uniform single-role queries."""
    q, v, t, b = cq.role_queries(s, d, p)
    truth, c = kept(osr.exact(q, v, t, b)), control(b, M, EFS)
    return compared(s, d, p, q, v, t, b, c, beams, truth)


def compared(s: SparkSession, d: str, p: str, q: DataFrame, v: DataFrame, t: DataFrame, b: DataFrame, c: Control, beams: Iterable[int], truth: DataFrame) -> DataFrame:
    """All methods and the filtered variants, whose graphs of all vectors, the slowest to build, begin first."""
    more, one = at_once(lambda: filtered_grid(q, v, t, b, c, beams, truth), lambda: grid(s, q, v, t, b, c, made(s, d, p, c, METHODS), beams, truth))
    return one.union(more)


for _p in "AD":
    _q(f"e_rates_{_p}")(lambda s, d, p=_p: rates(s, d, p))
    _q(f"x_speedup_{_p}")(lambda s, d, p=_p: speedups(s, d, p))


def speedups(s: SparkSession, d: str, p: str) -> DataFrame:
    """method, speedup over mined sub-indices and over role partitions, mean over the beams."""
    runs = kept(rates(s, d, p))
    one = om.speedup(runs, "rate", "mined").withColumnRenamed("speedup", "over_mined")
    return one.join(om.speedup(runs, "rate", "rolepart").withColumnRenamed("speedup", "over_rolepart"), "method")


def weighted_queries(s: SparkSession, d: str, p: str) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame, Control]:
    """Roles as often as they may read, each with a vector of what it reads; the planners weigh roles alike."""
    q, v, t, b = cq.role_queries(s, d, p)
    own = q.select("x", "roles", "qclass", (F.row_number().over(Window.partitionBy("qclass").orderBy("qid")) - 1).alias("i"), F.count("*").over(Window.partitionBy("qclass")).alias("n"))
    drawn = sw.weighted_role(s, b).select("qid", F.col("role_id").cast("string").alias("qclass"))
    nth = (F.row_number().over(Window.partitionBy("qclass").orderBy("qid")) - 1).alias("j")
    w = drawn.select("qid", "qclass", nth).join(own, "qclass").where("j % n = i").select("qid", "x", "roles", "qclass")
    read = {r["role_id"]: r["n"] for r in cq.ob.authorized(b).collect()}  # a row for each role
    c = control(b, M, EFS)
    weights = [float(sum(read.get(r, 0) for r in k)) for k in c.classes]
    return kept(w), v, t, b, control(b, M, EFS, c.classes, weights)


def weighted(s: SparkSession, d: str, p: str) -> DataFrame:
    """As rates, for roles drawn by the size of what they may read."""
    q, v, t, b, c = weighted_queries(s, d, p)
    truth = kept(osr.exact(q, v, t, b))
    return compared(s, d, p, q, v, t, b, c, (10, 100, 500), truth)


def multi_queries(s: SparkSession, d: str, p: str, by_size: bool) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame, list[frozenset[int]]]:
    """Queries by sets of several roles, each with a vector of the block of that very set; and the sets."""
    t, v = cq.tags_of(s, d, p), sp.vectors(s, d, p)
    b = cq.blocks_of(s, d, p)
    w = sw.multi_role(s, b, cq._N, by_size).join(b.select("role_key", "roles", "n"), "role_key").withColumn("pos", (F.col("qid") * 7919) % F.col("n"))
    own = t.join(F.broadcast(w.select("role_key").distinct()), "role_key").withColumn("nth", F.row_number().over(Window.partitionBy("role_key").orderBy("vec_id")) - 1)
    q = w.join(own.select("role_key", "nth", "vec_id"), (w["pos"] == own["nth"]) & (w["role_key"] == own["role_key"])).select("qid", "vec_id", "roles", w["role_key"].alias("qclass"))
    q = cq.with_vectors(q, v)
    sets = sorted({frozenset(r["roles"]) for r in q.select("roles").distinct().collect()}, key=sorted)  # no more than queries
    return q, v, t, b, sets


def multi(s: SparkSession, d: str, p: str, by_size: bool) -> DataFrame:
    """Sets of roles: both optimizers plan for single roles at a budget of 1.1 and have one more global index, which takes sets that
    may read over 80 % by filtered traversal; the others get 2.1, so that all store as much."""
    q, v, t, b, sets = multi_queries(s, d, p, by_size)
    singles, c = control(b, M, EFS), control(b, M, EFS, sets)
    beams = (10, 100, 500)
    truth = kept(osr.exact(q, v, t, b))
    broad = [",".join(map(str, sorted(x))) for x in sets if cover.broad(c, x)]
    mine = {m: cover.plan_all(c, cq.layout_of(singles, m, 1.1, cq.THRESHOLD[p]).units) for m in ("sweep", "rescoring")}
    others = {"mined": baselines.mined(c, Counter(sets), 2.1), "rolepart": baselines.role_partitions(c, 2.1), "global": baselines.global_index(c), "oracle": baselines.oracle(c)}
    wide = q.where(F.col("qclass").isin(broad)) if broad else q.limit(0)
    rest = q.where(~F.col("qclass").isin(broad)) if broad else q

    def planned() -> DataFrame:
        held, plan = layouts_side_by_side(s, c, mine | others)
        placed = kept(place(v, t, b, held))
        both = repeated(rest, 2, beams).union(repeated(q, 6, beams).where(F.shiftright("qid", 32) >= 2))
        return kept(osr.visits(both, plan, placed, c.roles, kept(graphs(placed, efc=EFC)), K))

    def routed() -> DataFrame:
        return kept(filtered_hits(wide, v, t, b, c, beams, FILTERED[:1]))

    hits, *more = at_once(planned, *[routed] * bool(broad))
    names = [*mine, *others]
    for one in more:  # for both optimizers
        for m in range(2):
            hits = hits.unionByName(one.withColumn("qid", F.col("qid") + F.lit(m).cast("long") * _BEAM * _QUERY), allowMissingColumns=True)
    return scored(kept(hits.select("qid", "vec_id", "dist", "work", "seconds")), truth, names, q.count()).withColumn("broad_sets", F.lit(len(broad)))


for _p in "AD":
    _q(f"e_weighted_{_p}")(lambda s, d, p=_p: weighted(s, d, p))
    _q(f"e_multi_uniform_{_p}")(lambda s, d, p=_p: multi(s, d, p, False))
    _q(f"e_multi_weighted_{_p}")(lambda s, d, p=_p: multi(s, d, p, True))


# coordinated against independent search
def coordination(s: SparkSession, d: str, p: str, methods: Iterable[str] = ("rescoring", "sweep"), betas: Iterable[float] = (1.0, 1.1, 1.5)) -> DataFrame:
    """method, budget, skip rate, beam reduction, and recall and work of coordinated and independent search on graphs.

    All that is left after merging has a graph; the sweep merges below its threshold only, so it gets a high one for that phase."""
    q, v, t, b = cq.role_queries(s, d, p)
    c, n, layouts = control(b, M, EFS), q.count(), {}
    truth = kept(osr.exact(q, v, t, b))
    for method in methods:
        for beta in betas:
            layout = cq.layout_of(c, method, beta, 0 if method == "rescoring" else 5 * cq.THRESHOLD[p])
            for unit in layout.units.values():
                unit.indexed = True
            layouts[f"{method} {float(beta)}"] = layout
    held, plan = layouts_side_by_side(s, c, layouts)
    placed = kept(place(v, t, b, held))
    g, asked = kept(graphs(placed, efc=EFC)), kept(repeated(q, len(layouts), (EFS,)))
    (result, counters), alone = at_once(lambda: osr.coordinated(asked, plan, placed, c.roles, g, K, EFS), lambda: kept(osr.visits(asked, plan, placed, c.roles, g, K, EFS)))
    found = alone.where("vec_id is not null").select("qid", "vec_id", "dist")
    counters = kept(split(counters, layouts))
    both = om.coordination(counters, "method").join(recalls(result, truth, layouts, "recall_coordinated"), "method").join(recalls(osr.best(found, k=K), truth, layouts, "recall_independent"), "method")
    both = both.join(counters.groupBy("method").agg((F.sum("work") / n).alias("work_coordinated")), "method").join(split(alone, layouts).groupBy("method").agg((F.sum("work") / n).alias("work_independent")), "method")
    name = F.split("method", " ")
    return both.select(name[0].alias("method"), name[1].cast("double").alias("budget"), "skip_rate", "beam_reduction", "recall_coordinated", "recall_independent", "work_coordinated", "work_independent")


def recalls(result: DataFrame, truth: DataFrame, names: Iterable[str], column: str) -> DataFrame:
    """method, recall of results under composed query numbers: the mean over all queries with a truth."""
    hit = split(result, names).join(truth.select("qid", "vec_id"), ["qid", "vec_id"]).groupBy("method", "qid").agg(F.count("*").alias("found"))
    of = truth.groupBy("qid").agg(F.count("*").alias("of")).withColumn("method", F.explode(F.array(*[F.lit(x) for x in names])))
    return of.join(hit, ["method", "qid"], "left").groupBy("method").agg(F.avg(F.coalesce("found", F.lit(0)) / F.col("of")).alias(column))


for _p in "AD":
    _q(f"search_coordination_{_p}")(lambda s, d, p=_p: coordination(s, d, p))


# queries from outside what a role may read
def outside(q: DataFrame, v: DataFrame, t: DataFrame) -> DataFrame:
    """qid, x, roles, qclass: for each query a vector that its role may not read, by position among all such (a role that reads all has none)."""
    role = q.select("roles", "qclass").distinct()
    barred = v.select("vec_id").join(t.select("vec_id", F.col("roles").alias("held")), "vec_id", "left").crossJoin(F.broadcast(role)).where("held IS NULL OR NOT arrays_overlap(roles, held)")
    w = Window.partitionBy("qclass")
    barred = barred.select("qclass", "vec_id", (F.row_number().over(w.orderBy("vec_id")) - 1).alias("pos"), F.count("*").over(w).alias("n"))
    return q.select("qid", "roles", "qclass").join(barred, "qclass").where((F.col("qid") * 104729 + 7) % F.col("n") == F.col("pos")).join(v, "vec_id").select("qid", F.col("embedding").alias("x"), "roles", "qclass")


@_q("e_sensitivity_A")
def sensitivity(s: SparkSession, d: str) -> DataFrame:
    """share, method, recall: query vectors drawn from what the role may read in that share, else from the rest; all methods."""
    q, v, t, b = cq.role_queries(s, d, "A")
    c, other, n = control(b, M, EFS), outside(q, v, t), 100
    shares = (0.0, 0.25, 0.5, 0.75, 1.0)
    mixed = None
    for i, share in enumerate(shares):
        inside = F.pmod(F.col("qid") * 7919, F.lit(n)) < int(share * n)
        one = q.where(inside).unionByName(other.where(~inside)).withColumn("qid", F.col("qid") + i * n)
        mixed = one if mixed is None else mixed.union(one)
    mixed = kept(mixed)
    truth = kept(osr.exact(mixed, v, t, b))
    layouts = made(s, d, "A", c, METHODS)
    held, plan = layouts_side_by_side(s, c, layouts)
    placed = kept(place(v, t, b, held))
    visits = lambda: kept(osr.visits(repeated(mixed, len(layouts), (EFS,)), plan, placed, c.roles, kept(graphs(placed, efc=EFC)), K).select("qid", "vec_id", "dist", "work", "seconds"))
    # the filtered variants follow as further methods
    more, hits = at_once(lambda: kept(filtered_hits(mixed, v, t, b, c, (EFS,)).withColumn("qid", F.col("qid") + F.lit(len(layouts)).cast("long") * _BEAM * _QUERY)), visits)
    names = [*layouts, *[x for x, *_ in FILTERED]]
    got = split(osr.best(hits.union(more).where("vec_id is not null").select("qid", "vec_id", "dist"), k=K), names)
    hit = got.join(truth.select("qid", "vec_id", F.lit(1).alias("hit")), ["qid", "vec_id"], "left")
    share_of = F.element_at(F.array(*[F.lit(x) for x in shares]), (F.floor(F.col("qid") / n) + 1).cast("int"))
    per = hit.groupBy("method", "qid").agg(F.sum(F.coalesce("hit", F.lit(0))).alias("found")).join(truth.groupBy("qid").agg(F.count("*").alias("of")), "qid")
    return per.groupBy("method", share_of.alias("share")).agg((F.sum(F.col("found") / F.col("of")) / n).alias("recall"))


@_q("b_filtered_recall_A")
def filtered_recall(s: SparkSession, d: str) -> DataFrame:
    """variant, recall of filtering during traversal on one global graph."""
    q, v, t, b = cq.role_queries(s, d, "A")
    got = filtered_grid(q, v, t, b, control(b, M, EFS), (EFS,), kept(osr.exact(q, v, t, b)))
    return got.select(F.col("method").alias("variant"), "recall")


# graph against scan, and the cost model from measurements
def measured(s: SparkSession, d: str, sizes: Iterable[int] = (64, 128, 256, 512, 1024, 2048), beams: Iterable[int] = (10, 30, 100, 200), repeats: int = 10) -> DataFrame:
    """n, efs, seconds and work of one graph search and of one scan, on sets of n vectors made of the table's (turned a little where it has fewer)."""
    beams = list(beams)

    def run(key, pdf):  # noqa: ANN001, ANN202
        import numpy as np
        import pandas as pd

        n = int(key[0])
        pdf = pdf.sort_values("vec_id")
        base = np.stack(pdf["embedding"].to_list()).astype(float)
        x = np.concatenate([np.roll(base, k, axis=1) for k in range(-(-n // len(base)))])[:n]
        g = hnsw.build(np.arange(n), x, efc=100)
        out = []
        for e in beams:
            for i in range(repeats):
                q = x[(i * 7919) % n] + 0.01
                began, done = time.perf_counter(), g.work
                hnsw.search(g, q, K, e)
                out.append((n, e, time.perf_counter() - began, g.work - done, "graph"))
        for i in range(repeats):
            began = time.perf_counter()
            dist = ((x - x[(i * 7919) % n]) ** 2).sum(1)
            np.argpartition(dist, min(K, n) - 1)
            out.append((n, 0, time.perf_counter() - began, n, "scan"))
        return pd.DataFrame(out, columns=["n", "efs", "seconds", "work", "kind"])

    base = cq.sp.vectors(s, d, "A").orderBy("vec_id").limit(2048)  # the size of the largest set
    each = base.withColumn("n", F.explode(F.array(*[F.lit(x) for x in sizes])))
    return each.groupBy("n").applyInPandas(run, "n bigint, efs bigint, seconds double, work bigint, kind string")


def fitted(rows: DataFrame) -> tuple[CostModel, dict[str, float]]:
    """The cost model whose graph part and scan part are both fitted to measurements (seconds)."""
    # a beam that is not small against the set sees all of it and says nothing on either form
    model, r2 = fc.calibrate(rows.where("kind = 'graph' and 4 * efs <= n"))
    scan = rows.where("kind = 'scan'").agg(F.regr_slope("seconds", "n").alias("s"), F.regr_intercept("seconds", "n").alias("s0")).first()
    return CostModel(model.a, model.b, model.c, max(scan["s"] or 0.0, 1e-12), max(scan["s0"] or 0.0, 0.0)), r2


@_q("e_crossover")
def crossover(s: SparkSession, d: str) -> DataFrame:
    """n, seconds and work of a graph search (beam 100) and of a scan."""
    rows = measured(s, d)
    mean = lambda kind, of, name: F.avg(F.when(F.col("kind") == kind, F.col(of))).alias(name)
    return rows.where("efs in (0, 100)").groupBy("n").agg(mean("graph", "seconds", "graph_seconds"), mean("scan", "seconds", "scan_seconds"), mean("graph", "work", "graph_work"), mean("scan", "work", "scan_work"))


@_q("m_calibrate_measured")
def calibrated(s: SparkSession, d: str) -> DataFrame:
    """The fitted cost model, the fit of both of its forms, and the size from which a graph pays, by time and by work."""
    rows = kept(measured(s, d))
    model, r2 = fitted(rows)
    by_work, r2w = fitted(rows.withColumn("seconds", F.col("work").cast("double")))
    cols = "unit string, a double, b double, c double, s double, s0 double, r2_linear double, r2_comparison double, crossover bigint"
    line = lambda unit, m, r: (unit, m.a, m.b, m.c, m.s, m.s0, float(r["linear"]), float(r["comparison"]), m.crossover(EFS))
    return s.createDataFrame([line("seconds", model, r2), line("distances", by_work, r2w)], cols)


@_q("m_crossover_A", f"SELECT block_id, CAST(n AS BIGINT) AS n, {M.a} * log2(n) + {M.b} * {EFS} + {M.c} <= {M.s} * n + {M.s0} AS graph_pays FROM blocks")
def crossover_blocks(s: SparkSession, d: str) -> DataFrame:
    """Per block whether a graph is no dearer than a scan, by the crossover size of the cost model."""
    return cq.blocks_of(s, d, "A").select("block_id", "n", (F.col("n") >= M.crossover(EFS)).alias("graph_pays"))


SQL["m_crossover_A"] = cq._with("A") + SQL["m_crossover_A"]


# thresholds, leftovers, build times
@_q("e_threshold_rates_D")
def threshold_rates(s: SparkSession, d: str) -> DataFrame:
    """threshold, recall, work, rate of the sweep layout at a budget of 1.1, and the worst rate over the best."""
    q, v, t, b = cq.role_queries(s, d, "D")
    c, grid_ = control(b, M, EFS), (0, 20, 40, 80, 160)
    layouts = {str(x): sweep.run(c, 1.1, x) for x in grid_}
    runs = kept(grid(s, q, v, t, b, c, layouts, (EFS,)))
    return runs.crossJoin(om.robustness(runs, "rate")).select(F.col("method").cast("int").alias("threshold"), "recall", "work", "rate", "worst_over_best")


@_q("e_leftovers_D")
def leftovers(s: SparkSession, d: str) -> DataFrame:
    """Scanning what is below the threshold against a graph on everything: recall, work, rate."""
    q, v, t, b = cq.role_queries(s, d, "D")
    c = control(b, M, EFS)
    return grid(s, q, v, t, b, c, {"scanned": sweep.run(c, 1.1, cq.THRESHOLD["D"]), "indexed": sweep.run(c, 1.1, 0)}, (EFS,)).select(F.col("method").alias("leftovers"), "recall", "work", "rate")


def build_times(s: SparkSession, d: str, p: str, methods: Iterable[str] = ("sweep", "rescoring", "mined", "rolepart"), budgets: Iterable[float] = (1.1, 2.0), repeats: int = 3) -> DataFrame:
    """method, budget, seconds to partition (mean of three) and to place and index the vectors."""
    t, v = cq.tags_of(s, d, p), sp.vectors(s, d, p)
    b = cq.blocks_of(s, d, p)
    c, past, rows = control(b, M, EFS), cq.past_of(s, d, p), []
    for method in methods:
        for beta in budgets:
            began = time.perf_counter()
            for _ in range(repeats):
                layout = cq.layout_of(c, method, beta, cq.THRESHOLD[p], past)
            middle = time.perf_counter()
            held, _ = tables(s, c, layout)
            graphs(place(v, t, b, held)).select("n").write.format("noop").mode("overwrite").save()
            rows.append((method, beta, (middle - began) / repeats, time.perf_counter() - middle))
    return s.createDataFrame(rows, "method string, budget double, partition_seconds double, index_seconds double")


_q("x_build_times_D")(lambda s, d: build_times(s, d, "D"))


# budgets: all methods, datasets and measures
def budgets(s: SparkSession, d: str, p: str, methods: Iterable[str], betas: Iterable[float] = cq.BETAS) -> DataFrame:
    """method, budget and all measures of its layout; mined also with a beam of 500."""
    b = cq.blocks_of(s, d, p)
    past, rows = cq.past_of(s, d, p), []
    for efs in (EFS, 500):
        c = control(b, M, efs)
        base = average_cost(c, baselines.oracle(c))
        for method in methods if efs == EFS else [m for m in methods if m == "mined"]:
            for beta in betas:
                layout = cq.layout_of(c, method, beta, cq.THRESHOLD[p], past)
                assert cover.covers(c, layout)
                rows.append((method, efs, float(beta), *[round(float(x), 6) for x in cq.measures(c, layout, base).values()]))
    names = ["sa", "avg_cost", "qa", "purity", "indices_per_query", "leftovers_per_query", "indices", "indexed_vectors", "leftover_vectors"]
    return s.createDataFrame(rows, "method string, efs int, budget double, " + ", ".join(f"{n} double" for n in names))


for _p in "ABCDE":
    _q(f"e_budgets_sweep_{_p}")(lambda s, d, p=_p: budgets(s, d, p, ("sweep",)))
    _q(f"e_budgets_baselines_{_p}")(lambda s, d, p=_p: budgets(s, d, p, ("mined", "rolepart", "global", "oracle", "exclusive")))
for _p in "AD":
    _q(f"e_budgets_rescoring_{_p}")(lambda s, d, p=_p: budgets(s, d, p, ("rescoring",), (1.0, 1.1, 1.5, 3.0)))


# changed grants
def changes(s: SparkSession, d: str) -> DataFrame:
    """vec_id, old_key, new_key: every eleventh vector of policy A loses its first role if it has several, every thirteenth gains role 9."""
    t = cq.tags_of(s, d, "A")
    lose = (F.col("vec_id") % 11 == 0) & (F.col("layer") > 1)
    new = F.when(lose, F.slice("roles", 2, 64)).otherwise(F.col("roles"))
    new = F.when(F.col("vec_id") % 13 == 0, F.sort_array(F.array_union(new, F.array(F.lit(9))))).otherwise(new)
    key = F.array_join(F.transform(new, lambda r: r.cast("string")), ",")
    return t.select("vec_id", F.col("role_key").alias("old_key"), key.alias("new_key")).where("old_key <> new_key")


def resized(blocks: DataFrame, delta: DataFrame) -> DataFrame:
    """role_key, n, grown, shrunk: block sizes after changed tags, by one aggregate of the changes and a full join; blocks that empty go."""
    moved = delta.select(F.col("old_key").alias("role_key"), F.lit(0).alias("in"), F.lit(1).alias("out")).union(delta.select("new_key", F.lit(1), F.lit(0)))
    net = moved.groupBy("role_key").agg(F.sum("in").alias("grown"), F.sum("out").alias("shrunk"))
    out = blocks.select("role_key", "n").join(net, "role_key", "full").fillna(0)
    return out.select("role_key", (F.col("n") + F.col("grown") - F.col("shrunk")).alias("n"), "grown", "shrunk").where("n > 0 or grown > 0 or shrunk > 0")


_q("m_maintain_blocks_A", cq._with("A") + """, d AS (SELECT vec_id, role_key AS old_key, list_sort(list_distinct(list_concat(CASE WHEN vec_id % 11 = 0 AND layer > 1 THEN roles[2:] ELSE roles END, CASE WHEN vec_id % 13 = 0 THEN [9] ELSE [] END))) AS r FROM tags),
 n AS (SELECT vec_id, old_key, array_to_string(r, ',') AS new_key FROM d), c AS (SELECT * FROM n WHERE old_key <> new_key),
 m AS (SELECT role_key, sum(i) AS grown, sum(o) AS shrunk FROM (SELECT old_key AS role_key, 0 AS i, 1 AS o FROM c UNION ALL SELECT new_key, 1, 0 FROM c) GROUP BY role_key)
 SELECT role_key, CAST(coalesce(n, 0) + coalesce(grown, 0) - coalesce(shrunk, 0) AS BIGINT) AS n, CAST(coalesce(grown, 0) AS BIGINT) AS grown, CAST(coalesce(shrunk, 0) AS BIGINT) AS shrunk FROM blocks FULL JOIN m USING (role_key)""")(lambda s, d: resized(cq.blocks_of(s, d, "A"), changes(s, d)))


def rebuilt(s: SparkSession, d: str, p: str = "A") -> DataFrame:
    """unit_id, dirty, vectors: the sweep layout's units after the changes, of which only dirty ones are placed anew. Blocks that are new join the unit of the
    least superset of their label, else they are scanned as units of their own, until the next full plan."""
    b, delta = cq.blocks_of(s, d, p), kept(changes(s, d))
    c = control(b, M, EFS)
    layout = sweep.run(c, 1.1, cq.THRESHOLD[p])
    key = {",".join(map(str, sorted(r))): i for i, r in c.roles.items()}
    after = {r["role_key"]: (r["n"], r["grown"] + r["shrunk"]) for r in resized(b, delta).collect()}  # a row for each block
    rows = []
    for i, u in sorted(layout.units.items()):
        mine = [k for k, x in key.items() if x in u.blocks]
        rows.append((i, any(after[k][1] for k in mine), sum(after[k][0] for k in mine)))
    fresh = sorted(k for k in after if k not in key and after[k][0])
    rows += [(len(layout.units) + j, True, after[k][0]) for j, k in enumerate(fresh)]
    return s.createDataFrame(rows, "unit_id int, dirty boolean, vectors bigint")


_q("m_maintain_units_A")(lambda s, d: rebuilt(s, d))

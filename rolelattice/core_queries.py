"""Queries of the methods, baselines, measures and workloads, with DuckDB counterparts where SQL can express them."""

from __future__ import annotations

from collections import Counter
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions import cost as fc
from .functions import vectors as fv
from .functions.cost import CostModel
from .operators import blocks as ob
from .operators import lattice as ol
from .operators import metrics as om
from .operators import search as osr
from .operators.layout import graphs, place, small
from .plans import baselines, rescoring, sweep
from .plans.state import Control, Layout, average_cost, control, tables
from .sources import policy as sp
from .sources import workload as sw
from .sources.tables import table
from .storage import kept

Q: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}
#: The cost model of the tests; efs and k of all planned queries.
M, EFS, K = CostModel(1.0, 0.01, 0.5, 0.0005, 0.05), 100, 10
#: Beam of the build of all graphs that queries search; no less than the links of the densest.
EFC = 200
#: Index thresholds that fit the tables' sizes.
THRESHOLD = {"A": 40, "B": 500, "C": 50, "D": 40, "E": 500}


def _q(name: str, sql: str | None = None):  # noqa: ANN202
    def add(f: Callable) -> Callable:
        Q[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def tags_of(spark: SparkSession, d: str, p: str) -> DataFrame:
    return ob.named(sp.tags(spark, d, p))


def blocks_of(spark: SparkSession, d: str, p: str) -> DataFrame:
    """The block table, worked out once: whoever joins it with itself reads the written rows."""
    return kept(ob.exclusive_blocks(tags_of(spark, d, p)))


def _with(p: str) -> str:
    return f"""WITH grants AS MATERIALIZED ({sp.grants_sql(p)}),
 tags AS MATERIALIZED (SELECT vec_id, list_sort(list(role_id)) AS roles, array_to_string(list_sort(list(role_id)), ',') AS role_key, count(*) AS layer FROM grants GROUP BY vec_id),
 blocks AS MATERIALIZED (SELECT CAST(row_number() OVER (ORDER BY layer, role_key) - 1 AS INTEGER) AS block_id, role_key, roles, CAST(layer AS INTEGER) AS layer, n FROM (SELECT role_key, any_value(roles) AS roles, any_value(layer) AS layer, count(*) AS n FROM tags GROUP BY role_key))
"""


_OVER = ", ov AS MATERIALIZED (SELECT a.block_id AS a, b.block_id AS b, a.layer AS la, b.layer AS lb, a.n AS na, b.n AS nb, len(list_intersect(a.roles, b.roles)) AS common FROM blocks a JOIN blocks b ON a.block_id <> b.block_id AND len(list_intersect(a.roles, b.roles)) > 0), pairs AS MATERIALIZED (SELECT b AS descendant, a AS ancestor FROM ov WHERE common = la AND la < lb)\n"


def _beam(n: str, efs: str = str(EFS)) -> str:
    return f"({M.a} * log2({n}) + {M.b} * {efs} + {M.c})"


# blocks and lattice
for _p in "ABCDE":
    _q(f"m_blocks_{_p}", _with(_p) + "SELECT block_id, role_key, layer, n FROM blocks")(lambda s, d, p=_p: ob.exclusive_blocks(tags_of(s, d, p)).drop("roles"))
    _q(f"m_authorized_{_p}", _with(_p) + "SELECT role_id, count(*) AS n FROM grants GROUP BY role_id")(lambda s, d, p=_p: ob.authorized(blocks_of(s, d, p)))
    _q(f"x_oracle_sa_{_p}", _with(_p) + "SELECT round(sum(n * layer) / sum(n), 6) AS oracle_sa FROM blocks")(lambda s, d, p=_p: ob.oracle_sa(blocks_of(s, d, p)).select(F.round("oracle_sa", 6).alias("oracle_sa")))
    _q(f"x_selectivity_{_p}", _with(_p) + "SELECT role_id, round(count(*) / (SELECT sum(n) FROM blocks), 6) AS share FROM grants GROUP BY role_id")(lambda s, d, p=_p: ob.selectivity(blocks_of(s, d, p)).select("role_id", F.round("share", 6).alias("share")))
    _q(f"m_layers_{_p}", _with(_p) + "SELECT coalesce(layer, 0) AS layer, count(*) AS blocks, CAST(sum(n) AS BIGINT) AS vectors FROM blocks GROUP BY ROLLUP (layer)")(lambda s, d, p=_p: ol.layers(blocks_of(s, d, p)).fillna(0, ["layer"]))
    _q(f"m_partition_{_p}", _with(_p) + "SELECT (SELECT count(*) FROM tags) AS vectors, 0 AS empty_tags, CAST(sum(n) AS BIGINT) AS in_blocks, count(*) AS blocks, count(DISTINCT role_key) AS keys, 0 AS left_over FROM blocks")(lambda s, d, p=_p: ob.check_partition(tags_of(s, d, p), blocks_of(s, d, p)).select("vectors", F.col("empty_tags").cast("int"), "in_blocks", "blocks", "keys", F.col("left_over").cast("int")))
for _p in "ACDE":
    _q(f"m_pairs_{_p}", _with(_p) + _OVER + "SELECT descendant, ancestor FROM pairs")(lambda s, d, p=_p: ol.descendant_ancestor(blocks_of(s, d, p)))
    _q(f"m_edges_{_p}", _with(_p) + _OVER + "SELECT ancestor AS parent_id, descendant AS child_id FROM pairs x WHERE NOT EXISTS (SELECT 1 FROM pairs u JOIN pairs v ON u.descendant = v.ancestor WHERE u.ancestor = x.ancestor AND v.descendant = x.descendant)")(lambda s, d, p=_p: ol.edges(blocks_of(s, d, p)))
    _q(f"m_related_{_p}", _with(_p) + _OVER + "SELECT a, b, CASE WHEN common = lb AND lb < la THEN 'ancestor' WHEN common = la AND la < lb THEN 'descendant' ELSE 'sibling' END AS kind FROM ov")(lambda s, d, p=_p: ol.related(blocks_of(s, d, p)))
_q("m_related_same_layer_D", _with("D") + _OVER + "SELECT a, b, CASE WHEN common = lb AND lb < la THEN 'ancestor' WHEN common = la AND la < lb THEN 'descendant' ELSE 'sibling' END AS kind FROM ov WHERE la = lb OR common = lb AND lb < la OR common = la AND la < lb")(lambda s, d: ol.related(blocks_of(s, d, "D"), "same_layer"))
_q("m_access_tags_A", _with("A") + "SELECT vec_id, role_key, CAST(layer AS INTEGER) AS layer FROM tags")(lambda s, d: ob.access_tags(sp.tags(s, d, "A").select("vec_id", F.explode("roles").alias("role_id"))).drop("roles"))
_q("m_authorized_sets_D", _with("D") + "SELECT q.role_key AS qclass, CAST(sum(b.n) AS BIGINT) AS n FROM blocks q JOIN blocks b ON len(list_intersect(q.roles, b.roles)) > 0 WHERE q.layer > 1 GROUP BY q.role_key")(lambda s, d: ob.authorized_sets(b := blocks_of(s, d, "D"), b.where("layer > 1").select(F.col("role_key").alias("qclass"), "roles")))


@_q("m_route_global_D", _with("D") + "SELECT q.role_key AS qclass, CAST(sum(b.n) AS BIGINT) > 0.8 * (SELECT sum(n) FROM blocks) AS global_route FROM blocks q JOIN blocks b ON len(list_intersect(q.roles, b.roles)) > 0 WHERE q.layer > 1 GROUP BY q.role_key")
def route_global(s: SparkSession, d: str) -> DataFrame:
    b = blocks_of(s, d, "D")
    n = ob.authorized_sets(b, b.where("layer > 1").select(F.col("role_key").alias("qclass"), "roles"))
    return n.crossJoin(b.agg(F.sum("n").alias("total"))).select("qclass", (F.col("n") > 0.8 * F.col("total")).alias("global_route"))


# cost
@_q("m_cost_forms_A", _with("A") + f"SELECT block_id, efs, round({M.a} * log2(n) + {M.b} * efs * log2(efs) + {M.c}, 6) AS comparison, round({_beam('n', 'efs')}, 6) AS beam, round({M.s} * n + {M.s0}, 6) AS scan FROM blocks, (SELECT unnest([10, 50, 100, 300, 500, 1000]) AS efs)")
def cost_forms(s: SparkSession, d: str) -> DataFrame:
    b = blocks_of(s, d, "A").withColumn("efs", F.explode(F.array(*[F.lit(x) for x in (10, 50, 100, 300, 500, 1000)])))
    n, e = F.col("n"), F.col("efs")
    return b.select("block_id", "efs", F.round(fc.comparison_cost(n, e, M), 6).alias("comparison"), F.round(fc.beam_cost(n, e, M), 6).alias("beam"), F.round(fc.scan_cost(n, M), 6).alias("scan"))


def quarter_nodes(b: DataFrame) -> DataFrame:
    """A stand-in layout: four nodes of every fourth block."""
    return b.select((F.col("block_id") % 4).alias("unit_id"), F.lit("index").alias("kind"), "block_id")


def node_role(nb: DataFrame, b: DataFrame) -> DataFrame:
    """unit_id, role_id, n, pure: node sizes and what each role may read of them."""
    held = nb.join(b, "block_id")
    size = held.groupBy("unit_id").agg(F.sum("n").alias("size"))
    return held.select("unit_id", F.col("n").alias("m"), F.explode("roles").alias("role_id")).groupBy("unit_id", "role_id").agg(F.sum("m").alias("pure")).join(size, "unit_id").select("unit_id", "role_id", F.col("size").alias("n"), "pure")


_NODE_ROLE = ", nr AS (SELECT u AS unit_id, r AS role_id, CAST(sum(CASE WHEN list_contains(roles, r) THEN n ELSE 0 END) AS BIGINT) AS pure, CAST(sum(n) AS BIGINT) AS n FROM (SELECT block_id % 4 AS u, roles, n FROM blocks), (SELECT DISTINCT role_id AS r FROM grants) GROUP BY u, r HAVING pure > 0)\n"
for _p in "AD":
    _q(f"m_inflation_{_p}", _with(_p) + _NODE_ROLE + "SELECT unit_id, role_id, n = pure AS pure, ceil(n / pure) AS lambda FROM nr")(lambda s, d, p=_p: node_role(quarter_nodes(b := blocks_of(s, d, p)), b).select("unit_id", "role_id", (F.col("n") == F.col("pure")).alias("pure"), fc.inflation(F.col("n"), F.col("pure")).alias("lambda")))
    _q(f"m_node_cost_{_p}", _with(_p) + _NODE_ROLE + f"SELECT unit_id, role_id, round(CASE WHEN n = pure THEN {_beam('n')} ELSE {_beam('n', f'least(ceil(ceil(n / pure) * {EFS}), greatest(n, {EFS}))')} END, 6) AS cost FROM nr")(lambda s, d, p=_p: node_role(quarter_nodes(b := blocks_of(s, d, p)), b).select("unit_id", "role_id", F.round(fc.access_cost(F.col("n"), F.col("pure"), EFS, M), 6).alias("cost")))
    _q(f"x_avg_cost_exclusive_{_p}", _with(_p) + f"SELECT round(avg(c), 6) AS avg_cost, round(sum(c * n) / sum(n), 6) AS weighted_cost FROM (SELECT r AS role_id, sum({_beam('n')}) AS c, sum(n) AS n FROM (SELECT unnest(roles) AS r, n FROM blocks) GROUP BY r)")(lambda s, d, p=_p: blocks_of(s, d, p).select(F.explode("roles").alias("r"), "n").groupBy("r").agg(F.sum(fc.beam_cost(F.col("n"), F.lit(EFS), M)).alias("c"), F.sum("n").alias("n")).agg(F.round(F.avg("c"), 6).alias("avg_cost"), F.round(F.sum(F.col("c") * F.col("n")) / F.sum("n"), 6).alias("weighted_cost")))
    _q(f"x_qa_exclusive_{_p}", _with(_p) + f", r AS (SELECT unnest(roles) AS r, n FROM blocks), c AS (SELECT r, sum({_beam('n')}) AS c, {_beam('sum(n)')} AS o FROM r GROUP BY r) SELECT round(avg(c) / avg(o), 6) AS qa, round(avg(c / o), 6) AS qa_mean_ratio FROM c")(lambda s, d, p=_p: blocks_of(s, d, p).select(F.explode("roles").alias("r"), "n").groupBy("r").agg(F.sum(fc.beam_cost(F.col("n"), F.lit(EFS), M)).alias("c"), F.sum("n").alias("n")).withColumn("o", fc.beam_cost(F.col("n"), F.lit(EFS), M)).agg(F.round(F.avg("c") / F.avg("o"), 6).alias("qa"), F.round(F.avg(F.col("c") / F.col("o")), 6).alias("qa_mean_ratio")))
    _q(f"x_lambda_profile_{_p}", _with(_p) + _NODE_ROLE + "SELECT round(min(n / pure), 6) AS least, round(median(n / pure), 6) AS median, round(max(n / pure), 6) AS most, round(avg(n / pure), 6) AS mean FROM nr")(lambda s, d, p=_p: (lambda x: x.select(*[F.round(c, 6).alias(c) for c in x.columns]))(om.lambda_profile(node_role(quarter_nodes(b := blocks_of(s, d, p)), b).select((F.col("n") / F.col("pure")).alias("lambda")))))
    _q(f"m_super_impure_{_p}", _with(_p) + _NODE_ROLE + "SELECT unit_id, role_id, round(n / pure, 6) AS lambda, row_number() OVER (ORDER BY n / pure DESC, role_id, unit_id) AS nth FROM nr WHERE n / pure >= 2")(lambda s, d, p=_p: node_role(quarter_nodes(b := blocks_of(s, d, p)), b).withColumn("l", F.col("n") / F.col("pure")).where("l >= 2").select("unit_id", "role_id", F.round("l", 6).alias("lambda"), F.row_number().over(Window.orderBy(F.desc("l"), "role_id", "unit_id")).alias("nth")))
    _q(f"m_scaled_efs_{_p}", _with(_p) + f"SELECT block_id, CAST(greatest(ceil({EFS} * log2(n) / log2((SELECT sum(n) FROM blocks))), {K}) AS INTEGER) AS efs FROM blocks")(lambda s, d, p=_p: (b := blocks_of(s, d, p)).crossJoin(b.agg(F.sum("n").alias("total"))).select("block_id", fc.scaled_efs(EFS, F.col("n"), F.col("total"), K).alias("efs")))
    _q(f"m_assign_{_p}", _with(_p) + f"SELECT CASE WHEN n >= {THRESHOLD[_p]} THEN 'index' ELSE 'leftover' END AS kind, count(*) AS units, CAST(sum(n) AS BIGINT) AS vectors FROM blocks GROUP BY 1")(lambda s, d, p=_p: blocks_of(s, d, p).groupBy(F.when(F.col("n") >= THRESHOLD[p], "index").otherwise("leftover").alias("kind")).agg(F.count("*").alias("units"), F.sum("n").alias("vectors")))


@_q("m_calibrate_r2", "WITH t AS (SELECT (l_orderkey % 97 + 3) AS n, l_linenumber * 10 AS efs FROM lineitem), y AS (SELECT efs, 0.3 * log2(n) + 0.02 * efs + 0.001 * (n % 7) AS s FROM t) SELECT round(regr_r2(s, efs), 6) AS linear, round(regr_r2(s, efs * log2(efs)), 6) AS comparison FROM y")
def calibrate_r2(s: SparkSession, d: str) -> DataFrame:
    t = table(s, d, "lineitem").select((F.col("l_orderkey") % 97 + 3).alias("n"), (F.col("l_linenumber") * 10).alias("efs"))
    y = t.withColumn("s", 0.3 * F.log2("n") + 0.02 * F.col("efs") + 0.001 * (F.col("n") % 7))
    return y.agg(F.round(F.regr_r2("s", "efs"), 6).alias("linear"), F.round(F.regr_r2("s", F.col("efs") * F.log2("efs")), 6).alias("comparison"))


# first steps of the optimizers, scored by the cluster
def _pairs_sized(b: DataFrame) -> DataFrame:
    n = b.select("block_id", "n", "layer")
    return ol.descendant_ancestor(b).join(n.select(F.col("block_id").alias("descendant"), F.col("n").alias("nd"), F.col("layer").alias("ld")), "descendant").join(n.select(F.col("block_id").alias("ancestor"), F.col("n").alias("na"), F.col("layer").alias("la")), "ancestor")


def _gain(nd: str, na: str) -> F.Column:
    return fc.beam_cost(F.col(na), F.lit(EFS), M) + fc.beam_cost(F.col(nd), F.lit(EFS), M) - fc.beam_cost(F.col(na) + F.col(nd), F.lit(EFS), M)


for _p in "ADE":
    _q(f"m_copy_scores_{_p}", _with(_p) + _OVER + f"SELECT descendant, ancestor, round(x.layer * ({_beam('x.n')} + {_beam('y.n')} - {_beam('(x.n + y.n)')}) / (SELECT count(DISTINCT role_id) FROM grants) / (y.n + 1), 9) AS benefit FROM pairs JOIN blocks x ON ancestor = x.block_id JOIN blocks y ON descendant = y.block_id")(lambda s, d, p=_p: _pairs_sized(blocks_of(s, d, p)).select("descendant", "ancestor", F.round(F.col("la") * _gain("nd", "na") / len(sp.ROLES[p]) / (F.col("nd") + 1), 9).alias("benefit")))
    _q(f"m_merge_scores_{_p}", _with(_p) + _OVER + f""", h AS (SELECT a, b, na, nb, la, lb, common, la * ({M.a} * log2(na + 1) + {M.b} * {EFS} + {M.c}) + lb * ({M.a} * log2(nb + 1) + {M.b} * {EFS} + {M.c})
     - ((la + lb - common) * ({M.a} * log2(na + nb + 1) + {M.c}) + {M.b} * {EFS} * (common + (la - common) * (na + nb) / na + (lb - common) * (na + nb) / nb)) AS g FROM ov WHERE a < b) SELECT a, b, round(g, 6) AS gain FROM h""")(lambda s, d, p=_p: merge_scores(blocks_of(s, d, p)))


def merge_scores(b: DataFrame) -> DataFrame:
    """Gain of merging two blocks: the routed roles' costs apart, less those on the union with inherited inflation."""
    n = b.select("block_id", "n")
    o = ol.overlaps(b).where("a < b").join(n.select(F.col("block_id").alias("a"), F.col("n").alias("na")), "a").join(n.select(F.col("block_id").alias("b"), F.col("n").alias("nb")), "b")
    c, la, lb, na, nb = (F.col(x) for x in ("common", "la", "lb", "na", "nb"))
    apart = la * (M.a * F.log2(na + 1) + M.b * EFS + M.c) + lb * (M.a * F.log2(nb + 1) + M.b * EFS + M.c)
    union = (la + lb - c) * (M.a * F.log2(na + nb + 1) + M.c) + M.b * EFS * (c + (la - c) * (na + nb) / na + (lb - c) * (na + nb) / nb)
    return o.select("a", "b", F.round(apart - union, 6).alias("gain"))


@_q("m_two_way_best_A", _with("A") + _OVER + f""", w AS (SELECT c.block_id AS child, x.block_id AS one, y.block_id AS two, (x.layer * ({_beam('x.n')} + {_beam('c.n')} - {_beam('(x.n + c.n)')}) + y.layer * ({_beam('y.n')} + {_beam('c.n')} - {_beam('(y.n + c.n)')})) / c.n AS f
 FROM pairs p JOIN blocks c ON descendant = c.block_id JOIN blocks x ON ancestor = x.block_id JOIN blocks y ON y.layer + x.layer = c.layer AND len(list_intersect(x.roles, y.roles)) = 0 AND len(list_intersect(c.roles, y.roles)) = y.layer AND x.block_id < y.block_id)
 SELECT child, one, two, round(f, 9) AS f FROM (SELECT *, row_number() OVER (PARTITION BY child ORDER BY f DESC, one) AS r FROM w) WHERE r = 1""")
def two_way_best(s: SparkSession, d: str) -> DataFrame:
    """For each block the pair of complementary ancestors with the highest copy benefit; complements meet by their key, an equi-join."""
    b = blocks_of(s, d, "A")
    x = _pairs_sized(b).join(b.select(F.col("block_id").alias("descendant"), F.col("roles").alias("rd")), "descendant").join(b.select(F.col("block_id").alias("ancestor"), F.col("roles").alias("ra")), "ancestor")
    rest = F.array_join(F.transform(F.sort_array(F.array_except("rd", "ra")), lambda r: r.cast("string")), ",")
    other = b.select(F.col("role_key").alias("rest"), F.col("block_id").alias("two"), F.col("n").alias("n2"), F.col("layer").alias("l2"))
    w = x.withColumn("rest", rest).join(other, "rest").where("ancestor < two").withColumn("f", (F.col("la") * _gain("nd", "na") + F.col("l2") * _gain("nd", "n2")) / F.col("nd"))
    top = F.row_number().over(Window.partitionBy("descendant").orderBy(F.desc("f"), "ancestor"))
    return w.withColumn("r", top).where("r = 1").select(F.col("descendant").alias("child"), F.col("ancestor").alias("one"), "two", F.round("f", 9).alias("f"))


# plans
def containing(b: DataFrame) -> DataFrame:
    """A stand-in layout with repeated blocks: each block's node also holds its descendants."""
    return ol.descendant_ancestor(b).select(F.col("ancestor").alias("unit_id"), F.col("descendant").alias("block_id")).union(b.select("block_id", F.col("block_id").alias("b"))).withColumn("kind", F.lit("index"))


_CONTAIN = ", nb AS (SELECT ancestor AS unit_id, descendant AS block_id FROM pairs UNION ALL SELECT block_id, block_id FROM blocks)\n"
_q("m_locations_D", _with("D") + _OVER + _CONTAIN + "SELECT block_id, array_to_string(list_sort(list(unit_id)), ',') AS units FROM nb GROUP BY block_id")(lambda s, d: containing(blocks_of(s, d, "D")).groupBy("block_id").agg(F.array_join(F.transform(F.sort_array(F.collect_set("unit_id")), lambda u: u.cast("string")), ",").alias("units")))
_q("m_mandatory_D", _with("D") + _OVER + _CONTAIN + ", one AS (SELECT block_id, min(unit_id) AS unit_id FROM nb GROUP BY block_id HAVING count(*) = 1) SELECT DISTINCT r AS role_id, unit_id FROM one JOIN (SELECT block_id, unnest(roles) AS r FROM blocks) USING (block_id)")(lambda s, d: containing(b := blocks_of(s, d, "D")).groupBy("block_id").agg(F.min("unit_id").alias("unit_id"), F.count("*").alias("c")).where("c = 1").join(b.select("block_id", F.explode("roles").alias("role_id")), "block_id").select("role_id", "unit_id").distinct())
_q("m_plan_exclusive_D", _with("D") + "SELECT unnest(roles) AS role_id, block_id AS unit_id FROM blocks")(lambda s, d: blocks_of(s, d, "D").select(F.explode("roles").alias("role_id"), F.col("block_id").alias("unit_id")))
_q("x_sa_containing_D", _with("D") + _OVER + _CONTAIN + "SELECT round((SELECT sum(n) FROM nb JOIN blocks USING (block_id)) / (SELECT sum(n) FROM blocks), 6) AS sa")(lambda s, d: om.sa(containing(b := blocks_of(s, d, "D")), b).select(F.round("sa", 6).alias("sa")))
_q("b_global_A", _with("A") + "SELECT role_id, ceil((SELECT sum(n) FROM blocks) / count(*)) AS lambda FROM grants GROUP BY role_id")(lambda s, d: ob.authorized(b := blocks_of(s, d, "A")).crossJoin(b.agg(F.sum("n").alias("t"))).select("role_id", fc.inflation(F.col("t"), F.col("n")).alias("lambda")))
_q("b_oracle_A", _with("A") + f"SELECT role_id, count(*) AS n, round({_beam('count(*)')}, 6) AS cost FROM grants GROUP BY role_id")(lambda s, d: ob.authorized(blocks_of(s, d, "A")).select("role_id", "n", F.round(fc.beam_cost(F.col("n"), F.lit(EFS), M), 6).alias("cost")))
_q("b_filtered_routing_E", _with("E") + "SELECT role_id, count(*) < (SELECT sum(n) FROM blocks) / 12.0 AS scan FROM grants GROUP BY role_id")(lambda s, d: ob.selectivity(blocks_of(s, d, "E")).select("role_id", (F.col("share") < 1 / 12).alias("scan")))


def past_of(s: SparkSession, d: str, p: str) -> Counter:
    """How often each role asked in the held-out history, a row for each role."""
    return Counter({frozenset((r.role_id,)): r.past for r in sw.history(s, d, list(sp.ROLES[p])).collect() if r.role_id is not None and r.past})


def layout_of(c: Control, method: str, budget: float, threshold: int, history: Counter | None = None) -> Layout:
    if method == "sweep":
        return sweep.run(c, budget, threshold)
    if method == "rescoring":
        return rescoring.run(c, budget, threshold)
    if method == "mined":
        return baselines.mined(c, history or list(c.classes), budget)
    if method == "rolepart":
        return baselines.role_partitions(c, budget)
    return {"global": baselines.global_index, "oracle": baselines.oracle, "exclusive": baselines.exclusive}[method](c)


def measures(c: Control, layout: Layout, base: float) -> dict[str, float]:
    cost = average_cost(c, layout)
    touched, pure, units, leftover = [], [], [], []
    for q in c.classes:
        want = c.want(q)
        n = sum(c.n(layout.units[i].blocks) for i in layout.plans[q])
        touched.append(n)
        pure.append(c.n(want) / n if n else 1.0)
        units.append(sum(layout.units[i].indexed for i in layout.plans[q]))
        leftover.append(sum(not layout.units[i].indexed for i in layout.plans[q]))
    k = max(len(c.classes), 1)
    return {
        "sa": layout.sa(c), "avg_cost": cost, "qa": cost / base, "purity": sum(pure) / k, "indices_per_query": sum(units) / k, "leftovers_per_query": sum(leftover) / k,
        "indices": float(sum(u.indexed for u in layout.units.values())), "indexed_vectors": float(sum(c.n(u.blocks) for u in layout.units.values() if u.indexed)), "leftover_vectors": float(sum(c.n(u.blocks) for u in layout.units.values() if not u.indexed)),
    }


BETAS = (1.0, 1.1, 1.3, 1.5, 2.0, 3.0)


@_q("e_threshold_D")
def threshold_grid(s: SparkSession, d: str) -> DataFrame:
    """Cost and indices over a grid of index thresholds."""
    c = control(blocks_of(s, d, "D"), M, EFS)
    rows = []
    for b in (1.1, 1.3, 1.5):
        for t in (0, 20, 40, 80, 160, 320, 1 << 30):
            x = sweep.run(c, b, t)
            rows.append((b, t, round(average_cost(c, x), 6), sum(u.indexed for u in x.units.values())))
    return s.createDataFrame(rows, "budget double, threshold bigint, avg_cost double, indices int")


# blocks are named by bits: 1, 2 and 4 for the roles 1, 2 and 3
@_q("m_toy_layouts", f"""WITH sizes AS MATERIALIZED (SELECT (l_orderkey % 2 = 0)::INT + 2 * (l_orderkey % 3 = 0)::INT + 4 * (l_orderkey % 5 = 0)::INT AS block, count(*) AS n FROM lineitem GROUP BY 1 HAVING block > 0),
 held AS (SELECT layout, unit, unnest(blocks) AS block FROM (VALUES ('global', 0, [1, 2, 3, 4, 5, 6, 7]), ('oracle', 1, [1, 3, 5, 7]), ('oracle', 2, [2, 3, 6, 7]), ('oracle', 3, [4, 5, 6, 7]),
  ('exclusive', 1, [1]), ('exclusive', 2, [2]), ('exclusive', 3, [3]), ('exclusive', 4, [4]), ('exclusive', 5, [5]), ('exclusive', 6, [6]), ('exclusive', 7, [7]),
  ('merge', 0, [1, 3]), ('merge', 1, [5, 7]), ('merge', 2, [2]), ('merge', 3, [4]), ('merge', 4, [6]), ('copy', 0, [1, 3]), ('copy', 1, [3]), ('copy', 2, [5, 7]), ('copy', 3, [7]), ('copy', 4, [2]), ('copy', 5, [4]), ('copy', 6, [6])) AS t(layout, unit, blocks)),
 plans AS (SELECT layout, role, unnest(units) AS unit FROM (VALUES ('global', 1, [0]), ('global', 2, [0]), ('global', 3, [0]), ('oracle', 1, [1]), ('oracle', 2, [2]), ('oracle', 3, [3]), ('exclusive', 1, [1, 3, 5, 7]), ('exclusive', 2, [2, 3, 6, 7]), ('exclusive', 3, [4, 5, 6, 7]),
  ('merge', 1, [0, 1]), ('merge', 2, [0, 1, 2, 4]), ('merge', 3, [1, 3, 4]), ('copy', 1, [0, 2]), ('copy', 2, [1, 3, 4, 6]), ('copy', 3, [2, 5, 6])) AS t(layout, role, units)),
 visits AS (SELECT layout, role, unit, sum(n) AS n, sum(CASE WHEN block & (1 << (role - 1)) > 0 THEN n ELSE 0 END) AS pure FROM plans JOIN held USING (layout, unit) JOIN sizes USING (block) GROUP BY ALL),
 cost AS (SELECT layout, sum({_beam('n', f'least(ceil(n / pure) * {EFS}, greatest(n, {EFS}))')}) / 3 AS c FROM visits GROUP BY layout),
 stored AS (SELECT layout, sum(n) / (SELECT sum(n) FROM sizes) AS sa FROM held JOIN sizes USING (block) GROUP BY layout)
 SELECT layout, round(sa, 4) AS sa, round(c, 4) AS avg_cost FROM cost JOIN stored USING (layout)""")
def toy(s: SparkSession, d: str) -> DataFrame:
    """The running example's five layouts of three roles, over the line items that each may read."""
    key = F.col("l_orderkey")
    roles = F.array_compact(F.array(*[F.when(key % by == 0, F.lit(r)) for r, by in ((1, 2), (2, 3), (3, 5))]))
    sizes = table(s, d, "lineitem").groupBy(roles.alias("roles")).agg(F.count("*").alias("n")).where(F.size("roles") > 0)
    c = toy_control({frozenset(r["roles"]): r["n"] for r in sizes.collect()})  # seven rows
    groups = {"merge": [[0, 3], [4, 6], [1], [2], [5]], "copy": [[0, 3], [3], [4, 6], [6], [1], [2], [5]]}
    made = {"global": baselines.global_index(c), "oracle": baselines.oracle(c), "exclusive": baselines.exclusive(c)} | {k: baselines.from_groups(c, g) for k, g in groups.items()}
    return s.createDataFrame([(k, round(v.sa(c), 4), round(average_cost(c, v), 4)) for k, v in sorted(made.items())], "layout string, sa double, avg_cost double")


def toy_control(sizes: dict[frozenset[int], int] | None = None) -> Control:
    """The example's seven blocks, by default in the sizes of its text."""
    f = frozenset
    sets = [f([1]), f([2]), f([3]), f([1, 2]), f([1, 3]), f([2, 3]), f([1, 2, 3])]
    size = {0: 10000, 1: 20000, 2: 30000, 3: 10000, 4: 10000, 5: 10000, 6: 10000} if sizes is None else {i: sizes[x] for i, x in enumerate(sets)}
    return Control(dict(enumerate(sets)), size, M, EFS, (f([1]), f([2]), f([3])), (1.0, 1.0, 1.0))


# workloads
_N = 100
for _p in "ABCDE":
    _roles = list(sp.ROLES[_p])
    _q(f"w_single_{_p}", _with(_p) + f""", pos AS (SELECT role_id, vec_id, row_number() OVER (PARTITION BY role_id ORDER BY vec_id % {sw.SLICES}, vec_id) - 1 AS pos, count(*) OVER (PARTITION BY role_id) AS c FROM grants), q AS (SELECT range AS qid, {_roles}[CAST(range % {len(_roles)} AS INTEGER) + 1] AS role_id FROM range({_N}))
     SELECT qid, role_id, vec_id FROM q JOIN pos USING (role_id) WHERE pos = (qid * 7919) % c""")(lambda s, d, p=_p: sw.single_role(s, t := tags_of(s, d, p), ob.exclusive_blocks(t), list(sp.ROLES[p]), _N))
    _q(f"w_weighted_{_p}", _with(_p) + f", z AS (SELECT role_id, n, sum(n) OVER (ORDER BY role_id) AS hi, sum(n) OVER () AS t FROM (SELECT role_id, count(*) AS n FROM grants GROUP BY role_id)) SELECT range AS qid, role_id FROM range({_N}) JOIN z ON ((range * 7919 + 13) % 10007) * t >= (hi - n) * 10007 AND ((range * 7919 + 13) % 10007) * t < hi * 10007")(lambda s, d, p=_p: sw.weighted_role(s, blocks_of(s, d, p), _N))
    _q(f"w_multi_{_p}", _with(_p) + f", m AS (SELECT role_key, row_number() OVER (ORDER BY block_id) - 1 AS i, count(*) OVER () AS c FROM blocks WHERE layer > 1) SELECT range AS qid, role_key FROM range({_N}) JOIN m ON range % c = i")(lambda s, d, p=_p: sw.multi_role(s, blocks_of(s, d, p), _N))
    _q(f"w_multi_weighted_{_p}", _with(_p) + f", m AS (SELECT role_key, n, sum(n) OVER (ORDER BY block_id) AS hi, sum(n) OVER () AS t FROM blocks WHERE layer > 1) SELECT range AS qid, role_key FROM range({_N}) JOIN m ON ((range * 7919 + 13) % 10007) * t >= (hi - n) * 10007 AND ((range * 7919 + 13) % 10007) * t < hi * 10007")(lambda s, d, p=_p: sw.multi_role(s, blocks_of(s, d, p), _N, True))
    _q(f"w_history_{_p}", f"SELECT {_roles}[CAST(user_id % {len(_roles)} AS INTEGER) + 1] AS role_id, CAST(sum(CASE WHEN ts < TIMESTAMP '2024-01-21' THEN 1 ELSE 0 END) AS BIGINT) AS past, CAST(sum(CASE WHEN ts >= TIMESTAMP '2024-01-21' THEN 1 ELSE 0 END) AS BIGINT) AS future FROM events GROUP BY 1")(lambda s, d, p=_p: sw.history(s, d, list(sp.ROLES[p])))


# search
def role_queries(s: SparkSession, d: str, p: str, n: int = _N) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame]:
    """queries (qid, x, roles, qclass), vectors, tags, blocks."""
    t, v = tags_of(s, d, p), sp.vectors(s, d, p)
    b = blocks_of(s, d, p)
    w = sw.single_role(s, t, b, list(sp.ROLES[p]), n).select("qid", "vec_id", F.array("role_id").alias("roles"), F.col("role_id").cast("string").alias("qclass"))
    return with_vectors(w, v), v, t, b


def with_vectors(queries: DataFrame, v: DataFrame) -> DataFrame:
    """qid, x, roles, qclass of queries by vec_id; written, since searches and their truth read them again and again."""
    return kept(v.join(small(queries), "vec_id").select("qid", F.col("embedding").alias("x"), "roles", "qclass"))


def search_with(s: SparkSession, d: str, p: str, method: str = "sweep", budget: float = 1.1, coordinated: bool = False, hnsw: bool = False) -> tuple[DataFrame, DataFrame | None]:
    q, v, t, b = role_queries(s, d, p)
    c = control(b, M, EFS)
    held, plan = tables(s, c, layout_of(c, method, budget, THRESHOLD[p], past_of(s, d, p) if method == "mined" else None))
    placed = place(v, t, b, held)
    g = kept(graphs(placed, efc=EFC)) if hnsw else None
    if coordinated:
        return osr.coordinated(q, plan, placed, c.roles, g, K, EFS)
    return osr.independent(q, plan, placed, c.roles, g, K, EFS), None


def topk_sql(p: str) -> str:
    return SQL[f"w_single_{p}"].rstrip().replace("SELECT qid, role_id, vec_id FROM q JOIN pos", ", w AS (SELECT qid, role_id, vec_id FROM q JOIN pos").replace("% c", "% c)") + f"""
     , vectors AS MATERIALIZED ({sp.vectors_sql(p)})
     , d AS (SELECT qid, g.vec_id, list_sum(list_transform(list_zip(x.embedding, y.embedding), lambda p: (CAST(p[1] AS DOUBLE) - CAST(p[2] AS DOUBLE)) * (CAST(p[1] AS DOUBLE) - CAST(p[2] AS DOUBLE)))) AS dist
      FROM w JOIN grants g USING (role_id) JOIN vectors x ON x.vec_id = w.vec_id JOIN vectors y ON y.vec_id = g.vec_id)
     SELECT qid, CAST(rank AS INTEGER) AS rank, vec_id, round(dist, 6) AS dist FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY round(dist, 12), vec_id) AS rank FROM d) WHERE rank <= 10"""


def _rounded(x: DataFrame) -> DataFrame:
    return x.select("qid", "rank", "vec_id", F.round("dist", 6).alias("dist"))


for _p in "ABCDE":
    _q(f"search_exact_{_p}", topk_sql(_p))(lambda s, d, p=_p: _rounded(osr.exact(*role_queries(s, d, p))))
    for _m in ("sweep", "exclusive", "rolepart", "global", "oracle", "mined") if _p in "AD" else ("sweep", "mined"):
        _q(f"search_units_{_m}_{_p}", topk_sql(_p))(lambda s, d, p=_p, m=_m: _rounded(search_with(s, d, p, m)[0]))
    _q(f"search_coordinated_{_p}", topk_sql(_p))(lambda s, d, p=_p: _rounded(search_with(s, d, p, coordinated=True)[0]))
for _p in "AD":
    _q(f"search_leaks_{_p}", "SELECT CAST(NULL AS BIGINT) AS qid, CAST(NULL AS BIGINT) AS vec_id WHERE false")(lambda s, d, p=_p: osr.leak_check(search_with(s, d, p, hnsw=True, coordinated=True)[0], role_queries(s, d, p)[0], tags_of(s, d, p)))
_q("search_sql_twin_A", topk_sql("A"))(lambda s, d: sql_twin(s, d, "A"))


def sql_twin(s: SparkSession, d: str, p: str) -> DataFrame:
    """Exact search as joins and column expressions only."""
    q, v, t, b = role_queries(s, d, p)
    near = q.select("qid", "x", F.explode("roles").alias("role_id")).join(b.select("role_key", F.explode("roles").alias("role_id")), "role_id").select("qid", "x", "role_key").dropDuplicates(["qid", "role_key"])
    pairs = near.join(t.select("vec_id", "role_key"), "role_key").join(v, "vec_id")
    return _rounded(osr.best(pairs.select("qid", "vec_id", fv.l2_squared(F.col("x"), F.col("embedding")).alias("dist")), k=K))


@_q("search_recall_hnsw_A")
def recall_hnsw(s: SparkSession, d: str) -> DataFrame:
    """Recall of graph search, unit by unit and coordinated."""
    truth = osr.exact(*role_queries(s, d, "A"))
    out = None
    for name, on in (("independent", False), ("coordinated", True)):
        r = om.recall(search_with(s, d, "A", hnsw=True, coordinated=on)[0], truth).withColumn("mode", F.lit(name))
        out = r if out is None else out.union(r)
    return out

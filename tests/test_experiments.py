"""The experiments run on all queries, beams and methods, and show what the methods promise."""

import pytest
from pyspark.sql import functions as F

from rolelattice import core_queries as cq
from rolelattice import experiments as ex
from rolelattice.operators import search as osr
from rolelattice.plans.state import control, tables

SF = "/root/testdata/sf0.001"
ALL = {*ex.METHODS, "one_hop", "gamma"}


def test_every_query_keeps_a_vector_outside_its_role(spark):
    q, v, t, _ = cq.role_queries(spark, SF, "A")
    got = ex.outside(q, v, t)
    assert {r.qid for r in got.select("qid").collect()} == set(range(100)) and got.count() == 100
    seen = got.select("qid", "roles", F.col("x").alias("embedding")).join(v, "embedding").join(t.select("vec_id", F.col("roles").alias("held")), "vec_id")
    assert seen.where("arrays_overlap(roles, held)").count() == 0


def test_rates_of_all_methods(spark):
    got = {(r.method, r.efs): r for r in ex.rates(spark, SF, "A", (10, 100)).collect()}
    assert set(got) == {(m, e) for m in ALL for e in (10, 100)}
    assert all(r.rate > 0 and r.work > 0 for r in got.values())
    for m in ex.METHODS:
        assert got[m, 100].recall >= got[m, 10].recall - 0.02 and got[m, 100].recall >= 0.9
        assert got[m, 100].work >= got[m, 10].work
    # more pure data touched: less work than one index for all
    assert got["sweep", 100].work < got["global", 100].work and got["oracle", 100].work < got["global", 100].work


@pytest.mark.parametrize("by_size", [False, True])
def test_role_sets(spark, by_size):
    rows = ex.multi(spark, SF, "A", by_size).collect()
    assert {r.method for r in rows} == set(ex.METHODS)
    assert all(r.recall >= 0.85 for r in rows if r.efs >= 100 and r.method != "global")


def test_weighted_roles_keep_all_queries(spark):
    q, *_, c = ex.weighted_queries(spark, SF, "A")
    assert q.count() == 100 and q.select("qid").distinct().count() == 100
    assert len(set(c.weights)) > 1


def test_coordination_saves_visits_and_keeps_recall(spark):
    (r,) = ex.coordination(spark, SF, "A", ("rescoring",), (1.0,)).collect()
    assert r.recall_coordinated >= 0.9 and r.recall_coordinated >= r.recall_independent - 0.03
    assert 0 <= r.skip_rate <= 1 and r.work_coordinated <= r.work_independent * 1.05


def test_layouts_are_coordinated_in_one_job(spark, monkeypatch):
    """Each layout's row is what it has alone, and all layouts are searched together."""
    alone = {(r.method, r.budget): r for m, b in (("rescoring", 1.0), ("sweep", 1.5)) for r in ex.coordination(spark, SF, "A", (m,), (b,)).collect()}
    calls, real = [], osr.coordinated
    monkeypatch.setattr(osr, "coordinated", lambda *a, **k: calls.append(1) or real(*a, **k))
    got = {(r.method, r.budget): r for r in ex.coordination(spark, SF, "A", ("rescoring", "sweep"), (1.0, 1.5)).collect()}
    assert len(got) == 4 and len(calls) == 1
    for key, r in alone.items():
        assert list(got[key]) == pytest.approx(list(r)) if None not in r else list(got[key]) == list(r)


def test_units_of_several_layouts_are_placed_once(spark):
    b = cq.blocks_of(spark, SF, "A")
    c = control(b, cq.M, cq.EFS)
    one = cq.layout_of(c, "oracle", 1.1, 40)
    held, plan = ex.layouts_side_by_side(spark, c, {"x": one, "y": one, "z": cq.layout_of(c, "global", 1.1, 40)})
    alone, mine = tables(spark, c, one)
    assert held.count() == alone.count() + b.count()
    want = sorted((r.qclass, r.unit_id, r.kind, r.pure, r.n) for r in mine.collect())
    for m in (0, 1):
        rows = plan.where(F.col("qclass").startswith(f"{m}:")).collect()
        assert sorted((r.qclass[2:], r.unit_id, r.kind, r.pure, r.n) for r in rows) == want


def test_a_beam_in_arrays_finds_what_single_steps_find(spark):
    import numpy as np

    from rolelattice.operators import hnsw

    v = np.random.default_rng(2).normal(size=(900, 10))
    g = hnsw.build(np.arange(900), v, m=8, efc=48)
    allowed = np.arange(900) % 3 > 0
    for x in v[:12] + 0.05:
        near = np.argsort(((v - x) ** 2).sum(1))
        start = hnsw._entry(g, x)
        one, done = hnsw._beam(g, x, start, 900, 0), g.work
        d, at = hnsw._wide(g, x, start[0], 900)
        # room for all: the same places and distances, and no distance more
        assert at.tolist() == [i for _, i in one] and d.tolist() == [y for y, _ in one] and g.work - done == len(at) - 1
        assert [i for _, i in hnsw.search(g, x, 10, 100)] == near[:10].tolist()
        for two in (True, False):
            got = hnsw.filtered(g, x, allowed, 10, 200, two)
            assert all(allowed[i] for _, i in got) and len({i for _, i in got}) == 10
        assert [i for _, i in hnsw.filtered(g, x, allowed, 10, 200, True)] == near[allowed[near]][:10].tolist()


def test_shards_lie_in_partitions_of_their_own(spark):
    from rolelattice.operators.layout import spread_out

    part, wide = spread_out(spark, [(i << 20 | 3, i % 2, float(i + 1), 1 + i % 3) for i in range(20)], 200)
    rows = part.select("unit_id", "shard", "part", F.expr(f"pmod(hash(unit_id, shard, part), {wide})").alias("p")).collect()
    assert wide == len(rows) == 39 and {r.p for r in rows} == set(range(39)) and len({r[:3] for r in rows}) == 39


def test_role_sets_build_no_graph_that_no_query_reads(spark, monkeypatch):
    made, real = [], cq.graphs
    monkeypatch.setattr(cq, "graphs", lambda placed, m=16, efc=64, seed=1: made.append(m) or real(placed, m, efc, seed))
    monkeypatch.setattr(ex.cover, "broad", lambda c, x: True)
    rows = ex.multi(spark, SF, "A", False).collect()
    assert made == [16] and {r.method for r in rows} == set(ex.METHODS)


def test_resumed_search_equals_one_that_never_stopped(spark):
    import numpy as np

    from rolelattice.operators import hnsw

    v = np.random.default_rng(1).normal(size=(500, 12))
    g = hnsw.build(np.arange(500), v, m=8, efc=48)
    for x in v[:10] + 0.05:
        whole, first = hnsw.Cursor(g, x), hnsw.Cursor(g, x)
        whole.resume(60)
        first.resume(25)
        second = hnsw.Cursor(g, x, first.dump())
        second.resume(35)
        assert second.nearest(20) == whole.nearest(20)


def test_registered_graphs_are_built_in_full(spark, monkeypatch):
    made = []
    real = cq.graphs
    monkeypatch.setattr(cq, "graphs", lambda placed, m=16, efc=64, seed=1: made.append((m, efc)) or real(placed, m, efc, seed))
    got = ex.filtered_recall(spark, SF)
    cq.search_with(spark, SF, "A", hnsw=True)
    assert made == [(16, 200), (192, 200), (16, 200)]
    assert {r.variant for r in got.select("variant").collect()} == {"one_hop", "gamma"}


def test_mined_gets_the_history(spark, monkeypatch):
    seen = []
    real = cq.baselines.mined
    monkeypatch.setattr(cq.baselines, "mined", lambda c, history, budget: seen.append(history) or real(c, history, budget))
    cq.search_with(spark, SF, "A", "mined")
    past = {frozenset((r.role_id,)): r.past for r in cq.Q["w_history_A"](spark, SF).collect() if r.past}
    assert [dict(h) for h in seen] == [past] and len(set(past.values())) > 1


def test_searches_read_shards_of_bounded_size(spark):
    """Units spread over many shards give what one shard gives."""
    from rolelattice.operators.layout import place

    q, v, t, b = cq.role_queries(spark, SF, "A")
    c = control(b, cq.M, cq.EFS)
    held, plan = tables(spark, c, cq.layout_of(c, "sweep", 1.1, 40))
    want = osr.exact(q, v, t, b).select("qid", "rank", "vec_id").collect()
    assert sorted(osr.exact(q, v, t, b, rows=20).select("qid", "rank", "vec_id").collect()) == sorted(want)
    many = place(v, t, b, held, shard_rows=30)
    assert many.select("shard").distinct().count() > 3
    assert sorted(osr.independent(q, plan, many, c.roles).select("qid", "rank", "vec_id").collect()) == sorted(want)


def test_cost_model_from_measurements(spark):
    rows = {r.unit: r for r in ex.calibrated(spark, SF).collect()}
    assert rows["distances"].r2_linear > 0.8 and rows["distances"].b > 0
    assert rows["seconds"].crossover > 1


def test_changed_grants_touch_some_units_only(spark):
    rows = ex.rebuilt(spark, SF).collect()
    assert sum(r.vectors for r in rows) >= cq.blocks_of(spark, SF, "A").agg(F.sum("n")).first()[0]
    assert any(r.dirty for r in rows)


def test_heavy_shards_are_dealt_to_several_tasks(spark, monkeypatch):
    """Each query meets its shard's graph once, in one of several tasks, and finds what it finds in one task."""
    q, v, t, b = cq.role_queries(spark, SF, "A")
    c = control(b, cq.M, cq.EFS)
    held, plan = tables(spark, c, cq.layout_of(c, "global", 1.1, 40))
    placed = ex.kept(ex.place(v, t, b, held))
    g = ex.kept(ex.graphs(placed))
    bound = osr.sharded(osr.bind(osr.with_beam(q, 50), plan), placed)
    one, two = osr.dealt(bound, g, F.col("efs"))
    met = one.cogroup(two).applyInPandas(lambda key, qs, gs: qs[["qid"]].assign(part=key[2], graphs=len(gs)), "qid bigint, part int, graphs int").collect()
    assert sorted(r.qid for r in met) == list(range(100)) and all(r.graphs == 1 for r in met)
    assert 1 < len({r.part for r in met}) <= 2 * spark.sparkContext.defaultParallelism + 1
    hits = lambda: sorted(osr.independent(q, plan, placed, c.roles, g, 10, 50).select("qid", "rank", "vec_id").collect())
    many = hits()
    monkeypatch.setattr(osr, "PART_VISITS", 1 << 30)
    assert hits() == many


def test_no_row_holds_a_whole_graph(spark):
    """A graph passes through Spark in pieces of bounded size, and is searched as it was built."""
    import numpy as np

    from rolelattice.operators import hnsw

    d = "/root/testdata/sf0.1"
    q, v, t, b = cq.role_queries(spark, d, "A")
    c = control(b, cq.M, cq.EFS)
    held, plan = tables(spark, c, cq.layout_of(c, "global", 1.1, 40))
    placed = ex.kept(ex.place(v, t, b, held))
    g = ex.kept(ex.graphs(placed, efc=64))
    rows = g.select("nth", "graph").orderBy("nth").collect()
    assert len(rows) > 1 and [r.nth for r in rows] == list(range(len(rows))) and max(len(r.graph) for r in rows) <= hnsw.PIECE
    whole = hnsw.Graph.load(b"".join(bytes(r.graph) for r in rows))
    all_ = spark.createDataFrame([(i, whole.vectors[i].tolist(), sorted(set().union(*c.roles.values())), "every") for i in range(0, 200, 10)], "qid bigint, x array<float>, roles array<int>, qclass string")
    one = plan.limit(1).withColumn("qclass", F.lit("every"))
    got = {(r.qid, r["rank"]): r.vec_id for r in osr.independent(all_, one, placed, c.roles, g, 10, 60).collect()}
    for i in range(0, 200, 10):
        assert [got[i, r + 1] for r in range(10)] == [int(whole.ids[at]) for _, at in hnsw.search(whole, np.float32(whole.vectors[i]), 10, 60)]

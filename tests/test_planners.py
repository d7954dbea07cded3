"""The running example's arithmetic, and the properties that the planners promise, on seeded random lattices."""

import random
import time

import numpy as np
import pytest

from rolelattice.core_queries import toy_control
from rolelattice.functions.cost import CostModel
from rolelattice.operators import hnsw
from rolelattice.plans import baselines, brute, cover, rescoring, sweep
from rolelattice.plans.state import Control, average_cost, plan_cost


def lattice(seed, roles=5, blocks=10):
    r = random.Random(seed)
    sets = set()
    while len(sets) < blocks:
        sets.add(frozenset(r.sample(range(roles), r.randint(1, min(4, roles)))))
    sets = dict(enumerate(sorted(sets, key=sorted)))
    classes = tuple(frozenset([x]) for x in sorted(set().union(*sets.values())))
    return Control(sets, {b: r.randint(5, 400) for b in sets}, CostModel(1, 0.01, 0.5), 100, classes, (1.0,) * len(classes))


def test_toy_costs():
    c = toy_control()
    got = {n: round(average_cost(c, x), 4) for n, x in (("global", baselines.global_index(c)), ("oracle", baselines.oracle(c)), ("exclusive", baselines.exclusive(c)))}
    assert got == {"global": 19.443, "oracle": 17.09, "exclusive": 60.0125}
    assert baselines.oracle(c).sa(c) == 1.5


def test_toy_partition_and_merge_gain():
    c = toy_control()
    s = sweep.Sweep(c, 1.2)
    parts, left, f = s.best_partition(frozenset([1, 2, 3]))
    assert set(parts) == {frozenset([1, 2]), frozenset([3])} and not left
    assert f == pytest.approx(0.00419481, abs=1e-8)
    m = sweep.Merger(c, {frozenset([2, 3]): frozenset([5]), frozenset([3]): frozenset([2, 6])})
    assert m.gain(0, 1) == pytest.approx(8.144123, abs=1e-6)


@pytest.mark.parametrize("seed", range(12))
def test_sweep_copies_keep_purity_and_partition(seed):
    c = lattice(seed)
    for budget in (1.0, 1.2, 1.6, 3.0):
        s, routed = sweep.routed(c, budget)
        for label, blocks in s.nodes.items():
            assert all(label <= c.roles[b] for b in blocks)
        for q in c.classes:
            held = [b for i in routed.plans[q] for b in routed.units[i].blocks]
            assert sorted(held) == sorted(c.want(q))
        assert routed.stored(c) <= budget * c.total + 1e-6


@pytest.mark.parametrize("seed", range(8))
@pytest.mark.parametrize("optimizer", [sweep, rescoring])
def test_layouts_cover_within_budget(seed, optimizer):
    c = lattice(seed, blocks=8)
    for budget in (1.0, 1.3, 2.0):
        x = optimizer.run(c, budget, 100)
        assert cover.covers(c, x)
        assert x.sa(c) <= budget + 1e-9


@pytest.mark.parametrize("seed", range(6))
def test_copies_never_cost_and_merges_save(seed):
    c = lattice(seed, blocks=7)
    s = rescoring.Rescoring(c, 1.5)
    before = s.average()
    s.copy_phase()
    assert s.average() <= before + 1e-9
    before, stored = s.average(), sum(c.n(u.blocks) for u in s.units.values())
    if s.merge_phase():
        assert s.average() < before
    assert sum(c.n(u.blocks) for u in s.units.values()) <= stored


@pytest.mark.parametrize("seed", range(6))
def test_inherited_inflation_is_not_below_the_true_one(seed):
    c = lattice(seed)
    s = sweep.Sweep(c, 1.5)
    s.copy_phase()
    m = sweep.Merger(c, s.nodes)
    m.merge_phase(300)
    for atoms in m.nodes.values():
        blocks = m.blocks(atoms)
        for r, lam in m.inherited(atoms).items():
            assert lam >= c.n(blocks) / c.n(blocks & c.want(frozenset([r]))) - 1e-9


@pytest.mark.parametrize("seed", range(6))
def test_exact_plan_is_no_dearer_than_greedy(seed):
    c = lattice(seed)
    units = sweep.run(c, 1.4, 100).units
    for q in c.classes:
        want = c.want(q)
        assert plan_cost(c, units, cover.exact(c, units, want), want) <= plan_cost(c, units, cover.greedy(c, units, want), want) + 1e-9


def test_brute_layout_bounds_the_optimizers():
    c = lattice(3, roles=3, blocks=4)
    best = average_cost(c, brute.best_layout(c, 1.3, 3))
    assert best <= average_cost(c, brute.best_layout(c, 1.0, 3)) + 1e-9


def test_valid_partitions():
    f = frozenset
    assert sweep.valid_partitions(f([1, 2, 3]), [f([1]), f([2]), f([3]), f([1, 2])]) == [(f([3]), f([1, 2])), (f([1]), f([2]), f([3]))]


def test_edge_lattices():
    one = Control({0: frozenset([1])}, {0: 10}, CostModel(), 100, (frozenset([1]),), (1.0,))
    for o in (sweep, rescoring):
        for t in (0, 5, 1000):
            assert cover.covers(one, o.run(one, 1.0, t))
    wide = Control({i: frozenset(range(i, i + 3)) for i in range(70)}, dict.fromkeys(range(70), 5), CostModel(), 100, tuple(frozenset([r]) for r in range(72)), (1.0,) * 72)
    assert cover.covers(wide, sweep.run(wide, 1.2, 20))


def test_mined_may_overshoot_by_one_index_and_rolepart_keeps_roles_whole():
    c = lattice(1)
    x = baselines.mined(c, list(c.classes) * 3, 1.2)
    assert cover.covers(c, x)
    last = max(c.n(u.blocks) for u in x.units.values())
    assert x.stored(c) <= 1.2 * c.total + last
    y = baselines.role_partitions(c, 1.5)
    assert cover.covers(c, y) and y.sa(c) <= 1.5
    assert all(len(p) == 1 for p in y.plans.values())


def test_graph_recall_resume_and_seed():
    v = np.random.default_rng(3).normal(size=(600, 16))
    g = hnsw.build(np.arange(600), v, m=8, efc=48)
    again = hnsw.build(np.arange(600), v, m=8, efc=48)
    assert g.dump() == again.dump()
    hit = 0
    for x in v[:40] + 0.01:
        d = ((v - x) ** 2).sum(1)
        truth = set(np.argsort(d)[:10].tolist())
        hit += len(truth & {i for _, i in hnsw.search(g, x, 10, 80)})
        cur = hnsw.Cursor(g, x)
        first = cur.resume(20)
        more = cur.resume(20, bound=first[-1][0])
        assert all(a < first[-1][0] for a, _ in more)
    assert hit >= 380


def test_links_are_thinned_as_one_by_one():
    """Side by side as by the plain rule for each row, with fewer neighbours than links, too."""
    r = np.random.default_rng(11)
    for wide, m in ((40, 8), (12, 16), (60, 60)):
        near = r.normal(size=(30, wide, 6)) + 0.4
        near = np.take_along_axis(near, np.argsort((near**2).sum(2), axis=1)[:, :, None], 1)
        d = (near**2).sum(2)
        d[:5, wide // 2 :] = np.inf
        for row, dist, got in zip(near, d, hnsw.thinned(near, d, m).tolist(), strict=True):
            kept, rest = [], []
            for j in np.flatnonzero(np.isfinite(dist)).tolist():
                if len(kept) < m:
                    (kept if all(((row[j] - row[i]) ** 2).sum() >= dist[j] for i in kept) else rest).append(j)
            assert [x for x in got if x >= 0] == kept + rest[: m - len(kept)]


def test_graph_of_many_rows_is_built_in_blocks():
    """8,000 rows in seconds, few and many links: all rows are found again, no place has more links than it may."""
    v = np.random.default_rng(12).normal(size=(8000, 48))
    for m, most_seconds in ((16, 30), (192, 60)):
        began = time.perf_counter()
        g = hnsw.build(np.arange(8000) * 3, v, m=m, efc=200)
        assert time.perf_counter() - began < most_seconds
        assert np.diff(g.levels[0][0]).max() <= 2 * m and all(np.diff(at).max() <= m for at, _ in g.levels[1:])
        hit = 0
        for x in v[:50] + 0.02:
            truth = set(np.argsort(((v - x) ** 2).sum(1))[:10].tolist())
            hit += len(truth & {i for _, i in hnsw.search(g, x, 10, 300)})
        assert hit >= 450


def test_copies_of_a_vector_do_not_close_the_graph():
    """A third of the rows is one vector, the entry's among them: others are still found from it."""
    v = np.random.default_rng(13).normal(size=(900, 12))
    top = max(range(900), key=lambda i: (hnsw.level_of(i, 16, 1), -i))
    v[np.arange(top % 3, 900, 3)] = v[top]
    g = hnsw.build(np.arange(900), v)
    assert g.entry == top
    hit = 0
    for i in range((top + 1) % 3, 150, 3):
        truth = set(np.argsort(((v - v[i] - 0.01) ** 2).sum(1))[:10].tolist())
        hit += len(truth & {j for _, j in hnsw.search(g, v[i] + 0.01, 10, 100)})
    assert hit >= 450


def test_thinning_leaves_closed_neighbours_alone(monkeypatch):
    """Products shrink with what is still open, and the links are those of the plain rule."""
    from rolelattice.operators import hnsw

    v = np.random.default_rng(3).normal(size=(900, 16))
    near = v[None, 1:301] - v[600:900, None]
    d = np.einsum("ijk,ijk->ij", near, near)
    order = np.argsort(d, axis=1)
    near, d = np.take_along_axis(near, order[:, :, None], 1), np.take_along_axis(d, order, 1)
    want = []
    for a, dist in zip(near, d, strict=True):
        kept = []
        for j in range(len(a)):
            if len(kept) < 96 and all(2 * a[j] @ a[i] <= dist[i] for i in kept):
                kept.append(j)
        want.append(kept + [j for j in range(len(a)) if j not in kept][: 96 - len(kept)])
    seen = []
    real = np.matmul
    monkeypatch.setattr(hnsw.np, "matmul", lambda a, b: seen.append(a.size) or real(a, b))
    got = hnsw.thinned(near.copy(), d.copy(), 96)
    assert got.tolist() == want
    assert sum(seen) < 7 * near.size  # 10 with whole arrays each time


def test_build_holds_little_beside_the_graph():
    """Links are dealt to their places by blocks; pieces of a graph make up the same graph."""
    import tracemalloc

    v = np.random.default_rng(5).normal(size=(8000, 8)).astype(np.float32)
    tracemalloc.start()
    g = hnsw.build(np.arange(8000), v, m=192, efc=200)
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert most < 80e6 + 4 * len(g.dump())  # 80 MB for blocks of bounded size
    made = hnsw.Joined()
    for piece in g.pieces(1 << 16):
        assert len(piece) <= 1 << 16 and made.graph() is None
        made.add(piece)
    assert made.graph().dump() == g.dump() and g.vectors.dtype == np.float32

"""Last phase of both optimizers: what is too small for an index is scanned by block, and very impure reads get pure parts of their own."""

from __future__ import annotations

from .cover import greedy, locations, plan_all
from .state import Control, Layout, Unit, average_cost, plan_cost


def finalize(c: Control, units: dict[int, Unit], threshold: int, budget: float, min_lambda: float = 2.0, split: bool = True) -> Layout:
    """Units below the threshold fall apart into single blocks, each kept once; blocks that no class needs to scan and that an
    index holds are not kept; regained storage buys pure parts, highest inflation first; classes are planned on the result."""
    kept = {i: u for i, u in units.items() if c.n(u.blocks) >= threshold}
    loose = sorted({b for i, u in units.items() if i not in kept for b in u.blocks})
    nxt = max(units, default=-1) + 1
    out = dict(kept)
    for b in loose:
        out[nxt] = Unit(frozenset([b]), c.size[b] >= threshold and threshold > 0, c.roles[b])
        nxt += 1
    layout = plan_all(c, out)
    indexed = frozenset().union(*[u.blocks for u in kept.values()]) if kept else frozenset()
    used = {i for p in layout.plans.values() for i in p}
    for i in [i for i, u in out.items() if i not in kept and i not in used and u.blocks <= indexed]:
        del out[i]
    layout = plan_all(c, out)
    if not split:
        return layout
    room = budget * c.total - layout.stored(c)
    ranked = []
    for q in c.classes:
        want = c.want(q)
        for i in layout.plans[q]:
            pure = c.n(out[i].blocks & want)
            if pure and c.n(out[i].blocks) / pure >= min_lambda:
                ranked.append((-c.n(out[i].blocks) / pure, sorted(q), i, q))
    held = {u.blocks for u in out.values()}
    for _, _, i, q in sorted(ranked, key=lambda x: x[:3]):
        if i not in layout.plans[q]:
            continue
        want = c.want(q)
        missing = [frozenset([b]) for b in sorted(out[i].blocks & want) if frozenset([b]) not in held]
        need = sum(c.n(m) for m in missing)
        if need > room:
            continue
        trial = dict(out)
        for m in missing:
            trial[nxt] = Unit(m, c.n(m) >= threshold and threshold > 0, c.roles[next(iter(m))])
            nxt += 1
        plan = greedy(c, trial, want, locations(trial))
        if plan_cost(c, trial, plan, want) < plan_cost(c, out, layout.plans[q], want) - 1e-12:
            out, room = trial, room - need
            held |= set(missing)
            layout.plans[q] = plan
            layout.units = out
    again = plan_all(c, out)
    for q in c.classes:  # a class keeps the cheaper of its plans
        want = c.want(q)
        if plan_cost(c, out, again.plans[q], want) < plan_cost(c, out, layout.plans[q], want):
            layout.plans[q] = again.plans[q]
    layout.units = out
    assert average_cost(c, layout) <= average_cost(c, again) + 1e-9
    return layout


def super_impure(c: Control, layout: Layout, min_lambda: float = 2.0) -> list[tuple[frozenset[int], int, float]]:
    """(class, unit, inflation), most inflated first."""
    out = []
    for q in c.classes:
        want = c.want(q)
        for i in layout.plans[q]:
            pure = c.n(layout.units[i].blocks & want)
            if pure and c.n(layout.units[i].blocks) / pure >= min_lambda:
                out.append((q, i, c.n(layout.units[i].blocks) / pure))
    return sorted(out, key=lambda x: (-x[2], sorted(x[0]), x[1]))

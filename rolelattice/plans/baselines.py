"""Layouts to compare with: one global index, one index for each class, plain blocks, mined sub-indices, and role partitions."""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterable

from .cover import plan_all
from .state import Control, Layout, Unit


def global_index(c: Control) -> Layout:
    return plan_all(c, {0: Unit(frozenset(c.roles))})


def oracle(c: Control) -> Layout:
    """A pure index for each query class."""
    units = {i: Unit(c.want(q), True, q) for i, q in enumerate(c.classes)}
    return Layout(units, {q: (i,) for i, q in enumerate(c.classes)})


def exclusive(c: Control) -> Layout:
    """Each block its own unit; a class reads all of its blocks."""
    return Layout({b: Unit(frozenset([b]), True, c.roles[b]) for b in c.roles}, {q: tuple(sorted(c.want(q))) for q in c.classes})


def from_groups(c: Control, groups: Iterable[Iterable[int]]) -> Layout:
    """Given groups of blocks, planned."""
    return plan_all(c, {i: Unit(frozenset(g)) for i, g in enumerate(groups)})


def mined(c: Control, history: Iterable[Iterable[int]] | Counter, budget: float, brute_bound: float = 1 / 12) -> Layout:
    """Sub-indices for the role sets of past queries, by saved cost and frequency for each stored vector.

    The global index counts as one; a sub-index is admitted while what was stored before it is within the budget, so the last
    one may overshoot. A class reads the smallest admitted superset; very selective ones are scanned."""
    counts = history if isinstance(history, Counter) else Counter(frozenset(h) for h in history)
    every = frozenset(c.roles)
    units = {0: Unit(every)}
    stored = c.total
    value = {}
    for q, k in counts.items():
        want = c.want(q)
        if want and want != every:
            value[q] = k * (c.model.node(c.total, c.n(want), c.efs) - c.model.beam(c.n(want), c.efs)) / c.n(want)
    for q in sorted(value, key=lambda q: (-value[q], sorted(q))):
        if stored >= budget * c.total or value[q] <= 0:
            break
        want = c.want(q)
        if any(u.blocks == want for u in units.values()):
            continue
        units[len(units)] = Unit(want, True, q)
        stored += c.n(want)
    plans = {}
    for q in c.classes:
        want = c.want(q)
        plans[q] = (min((i for i, u in units.items() if want <= u.blocks), key=lambda i: (c.n(units[i].blocks), i)),)
    layout = Layout(units, plans)
    layout.brute = {q for q in c.classes if c.n(c.want(q)) < brute_bound * c.total and layout.plans[q] == (0,)}  # type: ignore[attr-defined]
    return layout


def role_partitions(c: Control, budget: float) -> Layout:
    """Every role's vectors lie whole in one partition. From one partition for all, move the role with the best drop of cost for
    each vector of added storage, to a partition of its own or another one, while the budget lasts."""
    roles = sorted(set().union(*c.roles.values())) if c.roles else []
    own = {r: c.want(frozenset([r])) for r in roles}
    place = dict.fromkeys(roles, 0)

    def content(p: dict[int, int]) -> dict[int, frozenset[int]]:
        out: dict[int, frozenset[int]] = {}
        for r, i in p.items():
            out[i] = out.get(i, frozenset()) | own[r]
        return out

    def cost(p: dict[int, int], parts: dict[int, frozenset[int]]) -> float:
        total = 0.0
        for q, w in zip(c.classes, c.weights, strict=True):
            want = c.want(q)
            total += w * sum(c.model.node(c.n(parts[i]), max(1, c.n(parts[i] & want)), c.efs) for i in {p[r] for r in q if r in p})
        return total / sum(c.weights)

    parts = content(place)
    now, stored = cost(place, parts), sum(map(c.n, parts.values()))
    while roles:
        best = None
        for r in roles:
            for to in [*sorted(set(place.values())), max(place.values()) + 1]:
                if to == place[r]:
                    continue
                trial = place | {r: to}
                t = content(trial)
                s = sum(map(c.n, t.values()))
                if s > budget * c.total:
                    continue
                drop = now - cost(trial, t)
                score = drop / max(s - stored, 1)
                if drop > 1e-12 and (best is None or score > best[0] + 1e-15):
                    best = score, trial, t, s
        if best is None:
            break
        _, place, parts, stored = best
        now = cost(place, parts)
    names = {i: k for k, i in enumerate(sorted(parts))}
    units = {names[i]: Unit(b) for i, b in parts.items()}
    return Layout(units, {q: tuple(sorted({names[place[r]] for r in q if r in place})) for q in c.classes})

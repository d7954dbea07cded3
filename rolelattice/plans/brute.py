"""Exact layout choice for tiny lattices: every way to put blocks into nodes, for tests."""

from __future__ import annotations

from itertools import combinations

from .cover import exact
from .state import Control, Layout, Unit, average_cost


def best_layout(c: Control, budget: float, max_nodes: int = 4) -> Layout:
    ids = sorted(c.roles)
    if len(ids) > 5:
        raise ValueError("at most five blocks")
    subsets = [frozenset(s) for k in range(1, len(ids) + 1) for s in combinations(ids, k)]
    best: tuple[float, Layout] | None = None
    for k in range(1, max_nodes + 1):
        for nodes in combinations(subsets, k):
            if frozenset().union(*nodes) != frozenset(ids) or sum(c.n(n) for n in nodes) > budget * c.total + 1e-9:
                continue
            units = {i: Unit(n) for i, n in enumerate(nodes)}
            layout = Layout(units, {q: exact(c, units, c.want(q)) for q in c.classes})
            if best is None or average_cost(c, layout) < best[0]:
                best = average_cost(c, layout), layout
    return best[1]

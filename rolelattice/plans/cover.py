"""Query plans: units that together hold every block that a class may read."""

from __future__ import annotations

from collections.abc import Iterable

from .state import Control, Layout, Unit, unit_cost


def locations(units: dict[int, Unit]) -> dict[int, list[int]]:
    """block -> units that hold it."""
    out: dict[int, list[int]] = {}
    for i in sorted(units):
        for b in units[i].blocks:
            out.setdefault(b, []).append(i)
    return out


def mandatory(where: dict[int, list[int]], want: Iterable[int]) -> set[int]:
    """Units that alone hold some block of the class."""
    return {where[b][0] for b in want if len(where[b]) == 1}


def _prune(units: dict[int, Unit], chosen: list[int], want: frozenset[int], cost: dict[int, float]) -> tuple[int, ...]:
    """Drop units whose blocks the others hold, dearest first."""
    for i in sorted(chosen, key=lambda i: (-cost[i], i)):
        rest = frozenset().union(*[units[j].blocks for j in chosen if j != i]) if len(chosen) > 1 else frozenset()
        if units[i].blocks & want <= rest:
            chosen = [j for j in chosen if j != i]
    return tuple(sorted(chosen))


def greedy(c: Control, units: dict[int, Unit], want: frozenset[int], where: dict[int, list[int]] | None = None) -> tuple[int, ...]:
    """Mandatory units, then the unit with most blocks still uncovered (ties: cheaper, then lower id); the same with most
    blocks for its cost; the cheaper plan of the two."""
    if not want:
        return ()
    where = where or locations(units)
    forced = mandatory(where, want)
    near = sorted({i for b in want for i in where[b]})
    cost = {i: unit_cost(c, units[i], want) for i in near}
    best: tuple[float, tuple[int, ...]] | None = None
    for by_cost in (False, True):
        chosen = sorted(forced)
        left = want - frozenset().union(*[units[i].blocks for i in chosen]) if chosen else want
        while left:
            def rank(i: int) -> tuple:
                k = len(units[i].blocks & left)  # noqa: B023
                return (cost[i] / k if k else float("inf"), i) if by_cost else (-k, cost[i], i)  # noqa: B023

            pick = min((i for i in near if units[i].blocks & left), key=rank)
            chosen.append(pick)
            left = left - units[pick].blocks
        plan = _prune(units, chosen, want, cost)
        total = sum(cost[i] for i in plan)
        if best is None or total < best[0] - 1e-12:
            best = total, plan
    return best[1]


def exact(c: Control, units: dict[int, Unit], want: frozenset[int], limit: int = 200_000) -> tuple[int, ...]:
    """The cheapest plan, by branching on the block with fewest places left; at most `limit` branches, else the greedy plan stands."""
    if not want:
        return ()
    where = locations(units)
    cost = {i: unit_cost(c, units[i], want) for b in want for i in where[b]}
    best = greedy(c, units, want, where)
    state = {"best": sum(cost[i] for i in best), "plan": best, "steps": 0}

    def go(chosen: tuple[int, ...], spent: float, left: frozenset[int]) -> None:
        state["steps"] += 1
        if state["steps"] > limit or spent >= state["best"] - 1e-12:
            return
        if not left:
            state["best"], state["plan"] = spent, tuple(sorted(chosen))
            return
        b = min(left, key=lambda b: (len(where[b]), b))
        for i in sorted(where[b], key=lambda i: (cost[i], i)):
            go((*chosen, i), spent + cost[i], left - units[i].blocks)

    go((), 0.0, want)
    return state["plan"]


def plan_all(c: Control, units: dict[int, Unit], best: bool = False) -> Layout:
    where = locations(units)
    return Layout(units, {q: exact(c, units, c.want(q)) if best else greedy(c, units, c.want(q), where) for q in c.classes})


def covers(c: Control, layout: Layout) -> bool:
    return all(c.want(q) <= frozenset().union(*[layout.units[i].blocks for i in p]) if p else not c.want(q) for q, p in layout.plans.items())


def broad(c: Control, qclass: frozenset[int], threshold: float = 0.8) -> bool:
    """Whether a class reads so much that one filtered search of a global index serves it best."""
    return c.n(c.want(qclass)) > threshold * c.total

"""The rescoring optimizer: copies and merges one at a time, each the best by what re-planning would save."""

from __future__ import annotations

from .cover import greedy, locations
from .finalize import finalize
from .state import Control, Layout, Unit, plan_cost


class Rescoring:
    """Every node starts as one block, its home. Pairs are (descendant, ancestor) by strict inclusion of home role sets."""

    def __init__(self, c: Control, budget: float, max_blocks: int = 1500, full: bool = False) -> None:
        if len(c.roles) > max_blocks:
            raise ValueError("too many blocks for the rescoring optimizer; use the sweep")
        self.c, self.budget, self.full = c, budget, full
        self.units = {b: Unit(frozenset([b]), True, c.roles[b]) for b in c.roles}
        self.wants = {q: c.want(q) for q in c.classes}
        where = locations(self.units)
        self.plans = {q: greedy(c, self.units, w, where) for q, w in self.wants.items()}
        self.costs = {q: plan_cost(c, self.units, self.plans[q], w) for q, w in self.wants.items()}
        self.weight = dict(zip(c.classes, c.weights, strict=True))
        self.pairs = [(d, a) for d in c.roles for a in c.roles if c.roles[a] < c.roles[d]]
        self.steps: list[tuple[str, int, int, float]] = []

    @property
    def room(self) -> float:
        return self.budget * self.c.total - sum(self.c.n(u.blocks) for u in self.units.values())

    def average(self) -> float:
        return sum(self.weight[q] * self.costs[q] for q in self.c.classes) / sum(self.weight.values())

    def _after(self, units: dict[int, Unit], touched: frozenset[int], gone: int | None = None, into: int | None = None) -> tuple[float, dict]:
        """Average cost with these units, and changed plans: only classes that may read a touched block plan again, and a plan that stays valid is kept when cheaper."""
        where = locations(units)
        saved, new = 0.0, {}
        for q, want in self.wants.items():
            if not want & touched:
                continue
            old = tuple(sorted({into if i == gone else i for i in self.plans[q]})) if gone is not None else self.plans[q]
            options = [(plan_cost(self.c, units, p, want), p) for p in (old, greedy(self.c, units, want, where))]
            best = min(options, key=lambda x: x[0])
            new[q] = best[::-1]
            saved += self.weight[q] * (self.costs[q] - best[0])
        return saved / sum(self.weight.values()), new

    def try_copy(self, d: int, a: int) -> tuple[float, int, dict, dict] | None:
        """(benefit, growth, units, plans) of copying the descendant's home block into the ancestor's node."""
        if d in self.units[a].blocks:
            return None
        units = dict(self.units)
        units[a] = Unit(self.units[a].blocks | {d}, True, self.units[a].label)
        saved, new = self._after(units, units[a].blocks)
        growth = self.c.size[d]
        return saved / (growth + 1), growth, units, new

    def try_merge(self, d: int, a: int) -> tuple[float, int, dict, dict]:
        units = dict(self.units)
        gone = units.pop(d)
        units[a] = Unit(self.units[a].blocks | gone.blocks, True, self.units[a].label | gone.label)
        saved, new = self._after(units, units[a].blocks, d, a)
        return saved, 0, units, new

    def _commit(self, kind: str, d: int, a: int, got: tuple) -> None:
        f, _, self.units, new = got
        for q, (plan, cost) in new.items():
            self.plans[q], self.costs[q] = plan, cost
        self.steps.append((kind, d, a, f))

    def copy_phase(self) -> bool:
        """Copy while the best pair does not cost and some pair fits the room."""
        scores: dict[tuple[int, int], float] = {}
        live = [p for p in self.pairs if p[0] in self.units and p[1] in self.units]
        for p in live:
            got = self.try_copy(*p)
            if got:
                scores[p] = got[0]
        changed = False
        while scores and self.room > 0:
            ranked = sorted(scores, key=lambda p: (-scores[p], self.c.size[p[0]], p))
            if scores[ranked[0]] < 0:
                break
            room = self.room
            pick = next((p for p in ranked if scores[p] >= 0 and self.c.size[p[0]] <= room), None)
            if pick is None:
                break
            got = self.try_copy(*pick)
            if got[0] < 0:  # a score that others' copies have outdated
                scores[pick] = got[0]
                continue
            self._commit("copy", *pick, got)
            changed = True
            del scores[pick]
            for p in list(scores):
                if self.full or p[1] == pick[1]:
                    scores[p] = self.try_copy(*p)[0]
        return changed

    def merge_phase(self) -> bool:
        changed = False
        live = lambda: [p for p in self.pairs if p[0] in self.units and p[1] in self.units]
        scores = {p: self.try_merge(*p)[0] for p in live()}
        while scores:
            pick = min(scores, key=lambda p: (-scores[p], p))
            got = self.try_merge(*pick)
            if scores[pick] <= 1e-12:
                break
            if got[0] <= 1e-12:
                scores[pick] = got[0]
                continue
            self._commit("merge", *pick, got)
            changed = True
            for p in list(scores):
                if p[0] not in self.units or p[1] not in self.units:
                    del scores[p]
                elif self.full or pick[1] in p:
                    scores[p] = self.try_merge(*p)[0]
        return changed


def run(c: Control, budget: float, threshold: int, copy: bool = True, merge: bool = True, full: bool = False, min_lambda: float = 2.0) -> Layout:
    """Copies, then merges, until neither changes anything; then the final phase."""
    state = Rescoring(c, budget, full=full)
    for _ in range(len(c.roles) + 1):
        changed = state.copy_phase() if copy else False
        changed = (state.merge_phase() if merge else False) or changed
        if not changed:
            break
    return finalize(c, state.units, threshold, budget, min_lambda)


def choose(n_blocks: int, changes_a_day: float = 0.0) -> str:
    """The sweep for many role sets or policies that change often, else the rescoring optimizer."""
    return "sweep" if n_blocks > 300 or changes_a_day > 1 else "rescoring"

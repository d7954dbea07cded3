"""The sweep optimizer: one pass of copies from the deepest layer up, scored in closed form, then one pass of merges."""

from __future__ import annotations

import math
from itertools import combinations

from .cover import plan_all
from .finalize import finalize
from .state import Control, Layout, Unit, average_cost

Roles = frozenset


def copy_gain(c: Control, child: int, ancestor: int) -> float:
    """What each role of the ancestor saves when the child's vectors join it."""
    return c.model.beam(ancestor, c.efs) + c.model.beam(child, c.efs) - c.model.beam(ancestor + child, c.efs)


def valid_partitions(roles: Roles, ancestors: list[Roles], max_parts: int = 3) -> list[tuple[Roles, ...]]:
    """Sets of disjoint ancestors that tile the role set (exhaustive; for tests and small lattices)."""
    fit = [a for a in ancestors if a < roles]
    return [p for k in range(2, max_parts + 1) for p in combinations(fit, k) if sum(map(len, p)) == len(roles) and frozenset().union(*p) == roles]


class Sweep:
    """Nodes by label. Each node is pure for its label, and the nodes whose labels hold a role partition what it may read."""

    def __init__(self, c: Control, budget: float) -> None:
        self.c = c
        self.nodes: dict[Roles, frozenset[int]] = {c.roles[b]: frozenset([b]) for b in c.roles}
        self.room = round((budget - 1) * c.total, 6)
        self.commits: list[tuple[Roles, tuple[Roles, ...], float]] = []

    def size(self, label: Roles) -> int:
        return self.c.n(self.nodes[label])

    def best_partition(self, label: Roles, max_parts: int = 2) -> tuple[tuple[Roles, ...], Roles, float] | None:
        """(ancestors, residual roles, benefit for each vector copied) by complements first, else a seed and disjoint further ancestors."""
        n = self.size(label)
        near = sorted((a for a in self.nodes if a < label), key=lambda a: (-len(a), sorted(a)))
        if not near or not n:
            return None
        gain = {a: len(a) * copy_gain(self.c, n, self.size(a)) for a in near}
        best = None
        for a in near:
            other = label - a
            parts = (a, other) if other in gain else (a,)
            # a residual counts as a member, so one ancestor and its residual are one copy
            score = sum(gain[p] for p in parts) / n
            if best is None or score > best[1] + 1e-15:
                best = parts, score
        parts, left = list(best[0]), label - frozenset().union(*best[0])
        if left:
            for a in near:
                copies = len(parts) + (left != a)  # members, residual included, less one
                if a <= left and n * copies <= self.room:
                    parts.append(a)
                    left = left - a
        members = len(parts) + bool(left)
        return tuple(parts), left, sum(gain[p] for p in parts) / (n * (members - 1))

    def copy_phase(self) -> None:
        if self.room <= 0:
            return
        for layer in range(max(map(len, self.nodes), default=0), 1, -1):
            found = []
            for label in sorted((x for x in self.nodes if len(x) == layer), key=sorted):
                if self.size(label) <= self.room and (got := self.best_partition(label)):
                    found.append((label, *got))
            for label, parts, left, f in sorted(found, key=lambda x: (-x[3], sorted(x[0]))):
                extra = self.size(label) * (len(parts) + bool(left) - 1)
                if extra > self.room:
                    continue
                content = self.nodes.pop(label)
                for p in [*parts, left] if left else parts:
                    self.nodes[p] = self.nodes.get(p, frozenset()) | content
                self.room -= extra
                self.commits.append((label, parts, f))


class Merger:
    """Frozen nodes are atoms; a current node is a set of atoms, routed to all roles of their labels."""

    def __init__(self, c: Control, atoms: dict[Roles, frozenset[int]]) -> None:
        self.c, self.atoms = c, atoms
        self.nodes: dict[int, frozenset[Roles]] = {i: frozenset([a]) for i, a in enumerate(sorted(atoms, key=sorted))}
        self.cost: dict[frozenset, float] = {}

    def blocks(self, atoms: frozenset[Roles]) -> frozenset[int]:
        return frozenset().union(*[self.atoms[a] for a in atoms])

    def inherited(self, atoms: frozenset[Roles]) -> dict[int, float]:
        """Inflation of each routed role: real size over the sizes of the atoms with the role in their label."""
        n = self.c.n(self.blocks(atoms))
        pure: dict[int, int] = {}
        for a in atoms:
            for r in a:
                pure[r] = pure.get(r, 0) + self.c.n(self.atoms[a])
        return {r: n / p for r, p in pure.items() if p}

    def h(self, atoms: frozenset[Roles]) -> float:
        """Cost over all routed roles."""
        if atoms not in self.cost:
            m, n = self.c.model, self.c.n(self.blocks(atoms))
            self.cost[atoms] = sum(m.a * math.log2(n + 1) + m.b * lam * self.c.efs + m.c for lam in self.inherited(atoms).values())
        return self.cost[atoms]

    def gain(self, a: int, b: int) -> float:
        return self.h(self.nodes[a]) + self.h(self.nodes[b]) - self.h(self.nodes[a] | self.nodes[b])

    def merge_phase(self, threshold: int) -> None:
        """Largest unindexable nodes first; each takes related nodes by falling gain until it is indexable or gains end."""
        size = lambda i: self.c.n(self.blocks(self.nodes[i]))
        for a in sorted(self.nodes, key=lambda i: (-size(i), i)):
            if a not in self.nodes or size(a) >= threshold:
                continue
            while size(a) < threshold:
                mine = frozenset().union(*self.nodes[a])
                near = [(self.gain(a, b), b) for b in self.nodes if b != a and mine & frozenset().union(*self.nodes[b])]
                merged = False
                for k, (g, b) in enumerate(sorted(near, key=lambda x: (-x[0], x[1]))):
                    if g <= 0 or size(a) >= threshold:
                        break
                    if k and self.gain(a, b) <= 0:  # later candidates were scored before the node grew
                        continue
                    self.nodes[a] |= self.nodes.pop(b)
                    merged = True
                if not merged:
                    break

    def units(self) -> dict[int, Unit]:
        return {i: Unit(self.blocks(x), True, frozenset().union(*x)) for i, x in self.nodes.items()}


def run(c: Control, budget: float, threshold: int, copy: bool = True, merge: bool = True, min_lambda: float = 2.0) -> Layout:
    sweep = Sweep(c, budget)
    if copy:
        sweep.copy_phase()
    merger = Merger(c, sweep.nodes)
    if merge:
        merger.merge_phase(threshold)
    return finalize(c, merger.units(), threshold, budget, min_lambda)


def routed(c: Control, budget: float) -> tuple[Sweep, Layout]:
    """The lattice after copying, each class reading the nodes whose label holds one of its roles."""
    s = Sweep(c, budget)
    s.copy_phase()
    labels = sorted(s.nodes, key=sorted)
    return s, Layout({i: Unit(s.nodes[x], True, x) for i, x in enumerate(labels)}, {q: tuple(i for i, x in enumerate(labels) if x & q) for q in c.classes})


def replanned(c: Control, layout: Layout) -> float:
    return average_cost(c, plan_all(c, layout.units))

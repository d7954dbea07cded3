"""Control-plane tables collected from the cluster, layouts over them, and what queries on them cost."""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

from ..functions.cost import CostModel
from ..storage import local

#: More distinct role sets than this are refused: the planners hold all blocks on the driver.
MAX_BLOCKS = 100_000


@dataclass(frozen=True)
class Control:
    """Blocks (id -> roles, size), the query classes (role sets) with weights, and the cost model."""

    roles: dict[int, frozenset[int]]
    size: dict[int, int]
    model: CostModel
    efs: int = 100
    classes: tuple[frozenset[int], ...] = ()
    weights: tuple[float, ...] = ()

    @property
    def total(self) -> int:
        return sum(self.size.values())

    def want(self, qclass: frozenset[int]) -> frozenset[int]:
        return frozenset(b for b, r in self.roles.items() if r & qclass)

    def n(self, blocks: Iterable[int]) -> int:
        return sum(self.size[b] for b in blocks)


def control(blocks: DataFrame, model: CostModel | None = None, efs: int = 100, classes: Iterable[Iterable[int]] | None = None, weights: Iterable[float] | None = None) -> Control:
    """Collect (block_id, roles, n); without classes, one query class for each role, all alike."""
    rows = blocks.select("block_id", "roles", "n").limit(MAX_BLOCKS + 1).collect()
    if len(rows) > MAX_BLOCKS:
        raise ValueError(f"more than {MAX_BLOCKS} role sets; group roles before planning")
    roles = {r["block_id"]: frozenset(r["roles"]) for r in sorted(rows, key=lambda r: r["block_id"])}
    every = sorted(set().union(*roles.values())) if roles else []
    cls = tuple(frozenset(c) for c in classes) if classes is not None else tuple(frozenset([r]) for r in every)
    return Control(roles, {r["block_id"]: r["n"] for r in rows}, model or CostModel(), efs, cls, tuple(weights) if weights is not None else (1.0,) * len(cls))


@dataclass
class Unit:
    """What a query reads as a whole: an index over blocks, or one leftover block that is scanned."""

    blocks: frozenset[int]
    indexed: bool = True
    label: frozenset[int] = frozenset()


@dataclass
class Layout:
    units: dict[int, Unit]
    plans: dict[frozenset[int], tuple[int, ...]] = field(default_factory=dict)

    def stored(self, c: Control) -> int:
        return sum(c.n(u.blocks) for u in self.units.values())

    def sa(self, c: Control) -> float:
        return self.stored(c) / max(c.total, 1)


def unit_cost(c: Control, u: Unit, want: frozenset[int]) -> float:
    if not u.indexed:
        return c.model.scan(c.n(u.blocks)) if u.blocks & want else float("inf")
    return c.model.node(c.n(u.blocks), c.n(u.blocks & want), c.efs)


def plan_cost(c: Control, units: dict[int, Unit], plan: Iterable[int], want: frozenset[int]) -> float:
    return sum(unit_cost(c, units[i], want) for i in plan)


def average_cost(c: Control, layout: Layout) -> float:
    """Weighted mean over the query classes of the summed costs of their plans."""
    total = sum(c.weights)
    return sum(w * plan_cost(c, layout.units, layout.plans[q], c.want(q)) for q, w in zip(c.classes, c.weights, strict=True)) / total if total else 0.0


def tables(spark: SparkSession, c: Control, layout: Layout) -> tuple[DataFrame, DataFrame]:
    """node_blocks (unit_id, kind, block_id) and plan (qclass, unit_id, kind, pure, lambda, n) as DataFrames."""
    held, rows = lines(c, layout)
    return local(spark, held, HELD), local(spark, rows, PLAN)


HELD = "unit_id int, kind string, block_id int"
PLAN = "qclass string, unit_id int, kind string, pure boolean, lambda double, n bigint"


def lines(c: Control, layout: Layout, prefix: str = "") -> tuple[list[tuple], list[tuple]]:
    """The rows of both tables; the names of the query classes begin with prefix."""
    kind = lambda u: "index" if u.indexed else "leftover"
    held = [(i, kind(u), b) for i, u in sorted(layout.units.items()) for b in sorted(u.blocks)]
    rows = []
    for q in c.classes:
        want = c.want(q)
        for i in layout.plans.get(q, ()):
            u = layout.units[i]
            n, pure = c.n(u.blocks), c.n(u.blocks & want)
            rows.append((prefix + ",".join(map(str, sorted(q))), i, kind(u), n == pure, n / pure if pure else None, n))
    return held, rows

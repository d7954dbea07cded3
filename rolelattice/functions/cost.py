"""Cost of a graph search and of a scan, as column expressions and as plain numbers (logarithms to base two)."""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class CostModel:
    """a weighs the upper layers, b the base-layer beam, c a query's fixed part; s, s0 the scan of a vector and its start.

    shard_rows bounds what one graph holds: a larger node is as many searches as it has shards (infinite: one graph)."""

    a: float = 1.0
    b: float = 0.01
    c: float = 0.5
    s: float = 0.0005
    s0: float = 0.05
    shard_rows: float = math.inf

    def beam(self, n: float, efs: float) -> float:
        shards = max(1, math.ceil(n / self.shard_rows)) if math.isfinite(self.shard_rows) else 1
        return shards * (self.a * math.log2(max(min(n, self.shard_rows), 1)) + self.b * efs + self.c)

    def comparison(self, n: float, efs: float) -> float:
        return self.a * math.log2(max(n, 1)) + self.b * efs * math.log2(max(efs, 1)) + self.c

    def node(self, n: float, pure: float, efs: float, ceil: bool = True) -> float:
        """Search of a node of which `pure` vectors are authorized: the beam widens by the inflation factor, up to a full scan."""
        if pure <= 0:
            return math.inf
        lam = math.ceil(n / pure) if ceil else n / pure
        return self.beam(n, min(math.ceil(lam * efs) if lam > 1 else efs, max(n, efs)))

    def scan(self, n: float) -> float:
        return self.s * n + self.s0

    def crossover(self, efs: float, most: int = 1 << 40) -> int:
        """The smallest size from which the graph is no dearer than the scan."""
        low, high = 2, most
        while low < high:
            mid = (low + high) // 2
            if self.beam(mid, efs) <= self.scan(mid):
                high = mid
            else:
                low = mid + 1
        return low


def beam_cost(n: Column, efs: Column, m: CostModel) -> Column:
    return F.lit(m.a) * F.log2(F.greatest(n, F.lit(1))) + F.lit(m.b) * efs + F.lit(m.c)


def comparison_cost(n: Column, efs: Column, m: CostModel) -> Column:
    return F.lit(m.a) * F.log2(F.greatest(n, F.lit(1))) + F.lit(m.b) * efs * F.log2(efs) + F.lit(m.c)


def scan_cost(n: Column, m: CostModel) -> Column:
    return F.lit(m.s) * n + F.lit(m.s0)


def inflation(n: Column, pure: Column, ceil: bool = True) -> Column:
    """Null where nothing is authorized."""
    ratio = n / F.when(pure > 0, pure)
    return F.ceil(ratio).cast("double") if ceil else ratio


def access_cost(n: Column, pure: Column, efs: int, m: CostModel) -> Column:
    lam = inflation(n, pure)
    beam = F.least(F.ceil(lam * efs), F.greatest(n, F.lit(efs)).cast("long"))
    return F.when(n == pure, beam_cost(n, F.lit(efs), m)).otherwise(beam_cost(n, beam, m))


def scaled_efs(efs: int, n: Column, total: Column, k: int) -> Column:
    """The beam of a smaller index for the same effort: in proportion to the logarithms of the sizes, at least k."""
    return F.greatest(F.ceil(F.lit(efs) * F.log2(n) / F.log2(total)), F.lit(k)).cast("int")


def calibrate(measured: DataFrame) -> tuple[CostModel, dict[str, float]]:
    """Least squares of seconds over (size, efs): the model and R^2 of the linear and of the comparison form.

    The sums of the normal equations are one aggregate; no measurement reaches the driver."""
    out, fit = {}, None
    for name, x2 in (("linear", F.col("efs").cast("double")), ("comparison", F.col("efs") * F.log2("efs"))):
        x = [F.log2("n"), x2, F.lit(1.0)]
        y = F.col("seconds")
        sums = measured.agg(*[F.sum(x[i] * x[j]).alias(f"x{i}{j}") for i in range(3) for j in range(i, 3)], *[F.sum(x[i] * y).alias(f"y{i}") for i in range(3)], F.sum(y * y).alias("yy"), F.count("*").alias("n")).first()
        g = np.array([[sums[f"x{min(i, j)}{max(i, j)}"] for j in range(3)] for i in range(3)], float)
        v = np.array([sums[f"y{i}"] for i in range(3)], float)
        t = np.linalg.lstsq(g, v, rcond=None)[0]
        out[name] = 1 - (sums["yy"] - 2 * t @ v + t @ g @ t) / max(sums["yy"] - v[2] ** 2 / sums["n"], 1e-300)
        fit = fit or CostModel(*[float(z) for z in t])
    return fit, out

"""Privacy budgets: how they are split over steps and levels, what is left on a path, and a ledger that adds up."""

from __future__ import annotations

import math
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Budget:
    """Total budget and the parts for the height and for splits (per level or in all); counts get the rest."""

    eps_tot: float
    eps_height: float = 1e-4
    per_level: float | None = None
    eps_prt: float | None = None

    def __post_init__(self):
        if self.eps_tot <= 0 or self.eps_height < 0:
            raise ValueError("budgets must be positive")
        if (self.per_level is None) == (self.eps_prt is None):
            raise ValueError("give the partition budget per level or in all")

    def level(self, height: int) -> float:
        if self.per_level is not None:
            return self.per_level
        return self.eps_prt / max(height, 1)

    def data(self, height: int) -> float:
        left = self.eps_tot - self.eps_height - (self.level(height) * height if height else 0.0)
        if left <= 0:
            raise ValueError(f"nothing left for counts: {left}")
        return left


def estimated_height(noisy_count: float, eps_tot: float, c0: float = 10.0, cells: int | None = None) -> int:
    """Floor of the logarithm of noisy_count * eps_tot / c0, from 0 to that of the number of cells."""
    x = noisy_count * eps_tot / c0
    h = int(math.floor(math.log2(x))) if x >= 1 else 0
    return min(h, int(math.log2(cells))) if cells else h


def geometric(eps: float, h: int, growth: float = 2.0) -> list[float]:
    """Budgets of heights 0 (leaves) to h (root); each level below gets the cube root of `growth` more. They sum to eps."""
    w = [growth ** ((h - i) / 3) for i in range(h + 1)]
    return [eps * x / sum(w) for x in w]


def uniform(eps: float, h: int) -> list[float]:
    return [eps / (h + 1)] * (h + 1)


def levels(eps: float, h: int, allocation: str = "geo", growth: float = 2.0) -> list[float]:
    return geometric(eps, h, growth) if allocation == "geo" else uniform(eps, h)


def remaining(parts: list[float], height: int) -> float:
    """What a path that stops at `height` has left after its decisions down to there."""
    return sum(parts[:height])


def path_variance(parts: list[float], growth: float = 2.0) -> float:
    """Sum over heights of growth^(h-i) / eps_i^2, the quantity that geometric() makes smallest."""
    h = len(parts) - 1
    return sum(growth ** (h - i) / e**2 for i, e in enumerate(parts))


def level_array(parts: list[float]) -> Column:
    return F.array(*(F.lit(float(x)) for x in parts))


def geometric_column(eps: Column, h: Column, height: Column, growth: float = 2.0) -> Column:
    """Closed form of geometric() for columns."""
    root = growth ** (1 / 3)
    return F.pow(F.lit(root), h - height) * eps * (root - 1) / (F.pow(F.lit(root), h + 1) - 1)


def remaining_column(eps: Column, h: Column, height: Column, growth: float = 2.0) -> Column:
    """Closed form of remaining() for geometric levels: the sum of heights 0 to height-1."""
    root = growth ** (1 / 3)
    return eps * (F.pow(F.lit(root), h + 1) - F.pow(F.lit(root), h - height + 1)) / (F.pow(F.lit(root), h + 1) - 1)


@dataclass
class Ledger:
    """Spendings of one release. Scope 'path' adds up along a path, 'disjoint' counts once at its largest."""

    rows: list[tuple] = field(default_factory=list)

    def spend(self, stage: str, eps: float, scope: str = "path", height: int | None = None, tree_id: str = "") -> Ledger:
        if eps < 0 or scope not in ("path", "disjoint"):
            raise ValueError((eps, scope))
        self.rows.append((tree_id, stage, height, float(eps), scope))
        return self

    def total(self) -> float:
        groups: dict = {}
        out = 0.0
        for tree, stage, height, eps, scope in self.rows:
            if scope == "path":
                out += eps
            else:
                groups[tree, stage, height] = max(groups.get((tree, stage, height), 0.0), eps)
        return out + sum(groups.values())

    def check(self, eps_tot: float) -> None:
        if self.total() > eps_tot * (1 + 1e-9):
            raise ValueError(f"spent {self.total()} of {eps_tot}")

    def frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows or [], "tree_id string, stage string, height int, eps double, scope string")

    @staticmethod
    def summary(frame: DataFrame) -> DataFrame:
        """Budget by tree and stage: disjoint spendings at their largest for each height, path ones added."""
        per = frame.groupBy("tree_id", "stage", "height", "scope").agg(F.sum("eps").alias("added"), F.max("eps").alias("most"))
        return per.groupBy("tree_id", "stage").agg(F.sum(F.when(F.col("scope") == "path", F.col("added")).otherwise(F.col("most"))).alias("eps"))

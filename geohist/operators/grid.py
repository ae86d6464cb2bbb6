"""Points to cells to counts: the frequency matrix and what is derived from it."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


@dataclass(frozen=True)
class GridSpec:
    """A public domain and its cells; never taken from the data."""

    x_lo: float
    x_hi: float
    y_lo: float
    y_hi: float
    nx: int = 1024
    ny: int = 1024

    def __post_init__(self):
        if self.nx < 1 or self.ny < 1 or self.x_hi <= self.x_lo or self.y_hi <= self.y_lo:
            raise ValueError("empty domain")

    @property
    def cells(self) -> int:
        return self.nx * self.ny

    def resized(self, nx: int, ny: int) -> GridSpec:
        return GridSpec(self.x_lo, self.x_hi, self.y_lo, self.y_hi, nx, ny)


def index_of(value: Column, lo: float, hi: float, n: int) -> Column:
    return F.floor((value - lo) * n / (hi - lo)).cast("int")


def cell_of(points: DataFrame, spec: GridSpec, outside: str = "clamp") -> DataFrame:
    """points with cx, cy. Points outside the domain go to its border ('clamp') or away ('drop'); null and NaN always go."""
    x, y = F.col("px"), F.col("py")
    real = x.isNotNull() & y.isNotNull() & ~F.isnan(x) & ~F.isnan(y)
    inside = (x >= spec.x_lo) & (x < spec.x_hi) & (y >= spec.y_lo) & (y < spec.y_hi)
    kept = points.where(real & inside if outside == "drop" else real)
    held = lambda v, lo, hi: F.greatest(F.lit(lo), F.least(F.lit(hi), v))  # noqa: E731  infinities meet the border
    cx = F.least(F.lit(spec.nx - 1), index_of(held(x, spec.x_lo, spec.x_hi), spec.x_lo, spec.x_hi, spec.nx))
    cy = F.least(F.lit(spec.ny - 1), index_of(held(y, spec.y_lo, spec.y_hi), spec.y_lo, spec.y_hi, spec.ny))
    return kept.withColumn("cx", cx.cast("int")).withColumn("cy", cy.cast("int"))


def frequency_matrix(points: DataFrame, spec: GridSpec, outside: str = "clamp", by: tuple[str, ...] = ()) -> DataFrame:
    """(by..., cx, cy, cnt): one pass over the points; the shuffle holds at most a row for each cell and task."""
    return cell_of(points, spec, outside).groupBy(*by, "cx", "cy").agg(F.count(F.lit(1)).alias("cnt"))


def all_cells(spark, spec: GridSpec) -> DataFrame:
    n = F.col("id")
    return spark.range(spec.cells).select((n % spec.nx).cast("int").alias("cx"), F.floor(n / spec.nx).cast("int").alias("cy"))


def densify(fm: DataFrame, spec: GridSpec) -> DataFrame:
    """Every cell, zero where the sparse matrix has none."""
    return all_cells(fm.sparkSession, spec).join(fm.select("cx", "cy", "cnt"), ["cx", "cy"], "left").select("cx", "cy", F.coalesce("cnt", F.lit(0)).alias("cnt"))


def prefix_sums(fm: DataFrame, spec: GridSpec, value: str = "cnt") -> DataFrame:
    """(cx, cy, total): sum of `value` over all cells from the origin to this one, both included."""
    dense = all_cells(fm.sparkSession, spec).join(fm.select("cx", "cy", F.col(value).alias("v")), ["cx", "cy"], "left").select("cx", "cy", F.coalesce("v", F.lit(0)).alias("v"))
    along = lambda part, order: W.partitionBy(part).orderBy(order).rowsBetween(W.unboundedPreceding, W.currentRow)
    rows = dense.withColumn("row", F.sum("v").over(along("cy", "cx")))
    return rows.select("cx", "cy", F.sum("row").over(along("cx", "cy")).alias("total"))


def coarser(fm: DataFrame, spec: GridSpec, mx: int, my: int) -> DataFrame:
    """Counts of an mx by my grid over the same domain: cell i goes to floor(i * m / n)."""
    gx, gy = F.floor(F.col("cx") * mx / spec.nx).cast("int"), F.floor(F.col("cy") * my / spec.ny).cast("int")
    return fm.groupBy(gx.alias("gx"), gy.alias("gy")).agg(F.sum("cnt").alias("cnt"))


def block_bounds(g: Column, m: int, n: int) -> tuple[Column, Column]:
    """First cell of block g of m blocks over n cells, and the cell after its last."""
    return F.ceil(g * n / m).cast("int"), F.ceil((g + 1) * n / m).cast("int")

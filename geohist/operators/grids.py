"""Grid baselines: noise on every cell, one noisy total, a uniform grid, an adaptive two-level grid."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from geohist.functions import noise
from geohist.operators.grid import GridSpec, all_cells, block_bounds, coarser, densify

#: Rows that a method may make by design before it refuses, unless told otherwise.
MOST_CELLS = 1 << 24


#: Blocks of the first level that are sent to all tasks; more are shuffled. Their number is known before.
BROADCAST_BLOCKS = 100_000


def _rows(frame: DataFrame, spec: GridSpec, mx, my, leaf: Column, value: Column, tree_id: str) -> DataFrame:
    """Release rows of blocks (gx, gy) of an mx by my grid; mx, my may be columns."""
    x0, x1 = block_bounds(F.col("gx"), mx, spec.nx)
    y0, y1 = block_bounds(F.col("gy"), my, spec.ny)
    out = frame.select(F.lit(tree_id).alias("tree_id"), leaf.cast("long").alias("leaf_id"), x0.alias("x0"), x1.alias("x1"), y0.alias("y0"), y1.alias("y1"), value.alias("ncount"))
    return out.select("tree_id", "leaf_id", "x0", "x1", "y0", "y1", ((F.col("x1") - F.col("x0")).cast("long") * (F.col("y1") - F.col("y0"))).alias("cells"), "ncount")


def singular(fm: DataFrame, spec: GridSpec, eps: float, secret: str | None = None, tree_id: str = "singular", most_cells: int = MOST_CELLS) -> DataFrame:
    """Noise on every cell, empty ones too."""
    if spec.cells > most_cells:
        raise ValueError(f"{spec.cells} dense cells; raise most_cells to allow them")
    cells = densify(fm, spec).withColumnsRenamed({"cx": "gx", "cy": "gy"})
    leaf = F.col("gx").cast("long") * spec.ny + F.col("gy")
    return _rows(cells, spec, spec.nx, spec.ny, leaf, noise.laplace(F.col("cnt"), 1 / eps, secret, tree_id, "cell", F.col("gx"), F.col("gy")), tree_id)


def total_uniform(fm: DataFrame, spec: GridSpec, eps: float, secret: str | None = None, tree_id: str = "uniform") -> DataFrame:
    """One noisy total over the whole domain."""
    n = fm.agg(F.coalesce(F.sum("cnt"), F.lit(0)).alias("cnt")).select(F.lit(0).alias("gx"), F.lit(0).alias("gy"), "cnt")
    return _rows(n, spec, 1, 1, F.lit(1), noise.laplace(F.col("cnt"), 1 / eps, secret, tree_id, "total"), tree_id)


def noisy_total(fm: DataFrame, eps_n: float, secret: str, tree_id: str) -> float:
    """The noisy number of records; one number for the driver."""
    return fm.agg(noise.laplace(F.coalesce(F.sum("cnt"), F.lit(0)).cast("double"), 1 / eps_n, secret, tree_id, "total").alias("n")).first()["n"]


def grid_side(noisy_count: float, eps: float, c0: float = 10.0, most: int = 1 << 15) -> int:
    """Rows of the uniform grid: the root of noisy_count * eps / c0, rounded, at least one."""
    return max(1, min(most, round(math.sqrt(max(noisy_count, 0.0) * eps / c0))))


def _dense_blocks(fm: DataFrame, spec: GridSpec, m: int) -> DataFrame:
    blocks = all_cells(fm.sparkSession, spec.resized(m, m)).withColumnsRenamed({"cx": "gx", "cy": "gy"})
    return blocks.join(coarser(fm, spec, m, m), ["gx", "gy"], "left").select("gx", "gy", F.coalesce("cnt", F.lit(0)).alias("cnt"))


def uniform_grid(fm: DataFrame, spec: GridSpec, eps: float, c0: float = 10.0, eps_n: float = 1e-4, secret: str | None = None, tree_id: str = "ug", side: int | None = None) -> DataFrame:
    """An m by m grid whose side follows the noisy number of records; eps_n of the total pays for that number."""
    m = side or min(spec.nx, spec.ny, grid_side(noisy_total(fm, eps_n, secret, tree_id), eps, c0))
    blocks = _dense_blocks(fm, spec, m)
    leaf = F.col("gx").cast("long") * m + F.col("gy")
    return _rows(blocks, spec, m, m, leaf, noise.laplace(F.col("cnt"), 1 / (eps - eps_n), secret, tree_id, "cell", F.col("gx"), F.col("gy")), tree_id)


def adaptive_sides(noisy_count: float, eps: float) -> int:
    """Rows of the first level."""
    return max(10, math.ceil(math.sqrt(max(noisy_count, 0.0) * eps / 10) / 4))


def adaptive_grid(fm: DataFrame, spec: GridSpec, eps: float, alpha: float = 0.5, eps_n: float = 1e-4, secret: str | None = None, tree_id: str = "ag", side: int | None = None) -> DataFrame:
    """Coarse blocks with noisy counts, each cut finer by its own count; both levels then made consistent.

    alpha of the budget pays for the first level. Blocks are cells of the base grid, so a second level is never finer than it.
    """
    m = side or min(spec.nx, spec.ny, adaptive_sides(noisy_total(fm, eps_n, secret, tree_id), eps))
    e1, e2 = alpha * (eps - eps_n), (1 - alpha) * (eps - eps_n)
    first = _dense_blocks(fm, spec, m).withColumn("n1", noise.laplace(F.col("cnt"), 1 / e1, secret, tree_id, "coarse", F.col("gx"), F.col("gy"))).drop("cnt")
    bx0, bx1 = block_bounds(F.col("gx"), m, spec.nx)
    by0, by1 = block_bounds(F.col("gy"), m, spec.ny)
    want = F.ceil(F.sqrt(F.greatest(F.col("n1"), F.lit(0.0)) * e2 / 5)).cast("int")
    first = first.withColumn("bx0", bx0).withColumn("bx1", bx1).withColumn("by0", by0).withColumn("by1", by1)
    first = first.withColumn("m2", F.greatest(F.lit(1), F.least(want, F.col("bx1") - F.col("bx0"), F.col("by1") - F.col("by0"))))
    sub = first.withColumn("i", F.explode(F.sequence(F.lit(0), F.col("m2") - 1))).withColumn("j", F.explode(F.sequence(F.lit(0), F.col("m2") - 1)))
    cells = fm.withColumn("gx", F.floor(F.col("cx") * m / spec.nx).cast("int")).withColumn("gy", F.floor(F.col("cy") * m / spec.ny).cast("int"))
    placed = cells.join(F.broadcast(first) if m * m <= BROADCAST_BLOCKS else first, ["gx", "gy"])
    i = F.floor((F.col("cx") - F.col("bx0")) * F.col("m2") / (F.col("bx1") - F.col("bx0"))).cast("int")
    j = F.floor((F.col("cy") - F.col("by0")) * F.col("m2") / (F.col("by1") - F.col("by0"))).cast("int")
    counted = placed.groupBy("gx", "gy", i.alias("i"), j.alias("j")).agg(F.sum("cnt").alias("cnt"))
    second = sub.join(counted, ["gx", "gy", "i", "j"], "left").withColumn("cnt", F.coalesce("cnt", F.lit(0)))
    second = second.withColumn("n2", noise.laplace(F.col("cnt"), 1 / e2, secret, tree_id, "fine", F.col("gx"), F.col("gy"), F.col("i"), F.col("j")))
    # Two-level least squares: the block's best estimate, its surplus shared evenly by its cells.
    sums = second.groupBy("gx", "gy").agg(F.sum("n2").alias("s2"), F.count(F.lit(1)).alias("c"))
    v1, v2 = 2 / e1**2, F.col("c") * (2 / e2**2)
    best = (F.col("n1") / v1 + F.col("s2") / v2) / (1 / v1 + 1 / v2)
    out = second.join(sums, ["gx", "gy"]).withColumn("ncount", F.col("n2") + (best - F.col("s2")) / F.col("c"))
    w, h = F.col("bx1") - F.col("bx0"), F.col("by1") - F.col("by0")
    x0, x1 = F.col("bx0") + F.ceil(F.col("i") * w / F.col("m2")).cast("int"), F.col("bx0") + F.ceil((F.col("i") + 1) * w / F.col("m2")).cast("int")
    y0, y1 = F.col("by0") + F.ceil(F.col("j") * h / F.col("m2")).cast("int"), F.col("by0") + F.ceil((F.col("j") + 1) * h / F.col("m2")).cast("int")
    leaf = (F.col("gx").cast("long") * m + F.col("gy")) * (1 << 24) + F.col("i") * F.col("m2") + F.col("j")
    out = out.select(F.lit(tree_id).alias("tree_id"), leaf.cast("long").alias("leaf_id"), x0.alias("x0"), x1.alias("x1"), y0.alias("y0"), y1.alias("y1"), "ncount")
    return out.select("tree_id", "leaf_id", "x0", "x1", "y0", "y1", ((F.col("x1") - F.col("x0")).cast("long") * (F.col("y1") - F.col("y0"))).alias("cells"), "ncount")

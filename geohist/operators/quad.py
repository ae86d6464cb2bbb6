"""Quadtrees and midpoint space partitions: all levels from one pass over the cells, keyed by Morton code."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from geohist.functions import budget, noise
from geohist.operators import consistency
from geohist.operators.grid import GridSpec


def morton(cx: Column, cy: Column, bits: int) -> Column:
    """Bits of both indices interleaved, x above y."""
    out = F.lit(0).cast("long")
    for b in range(bits):
        out = out + F.shiftleft(F.shiftright(cx, b).bitwiseAND(1).cast("long"), 2 * b + 1) + F.shiftleft(F.shiftright(cy, b).bitwiseAND(1).cast("long"), 2 * b)
    return out


def bits_of(spec: GridSpec) -> int:
    return max(spec.nx - 1, spec.ny - 1).bit_length()


def quad_counts(fm: DataFrame, spec: GridSpec, depth: int, tree_id: str = "quad") -> DataFrame:
    """(tree_id, node_id, height, qx, qy, side, cnt) of every quadrant of every level, empty ones too; the domain is padded to a power of two.

    The leaf level is aggregated once from cells; levels above come from its rows.
    """
    bits = bits_of(spec)
    depth = min(depth, bits)
    spark = fm.sparkSession
    code = F.shiftright(morton(F.col("cx"), F.col("cy"), bits), 2 * (bits - depth))
    leaf = fm.groupBy(code.alias("q")).agg(F.sum("cnt").alias("cnt"))
    every = leaf.select(F.explode(F.sequence(F.lit(0), F.lit(depth))).alias("height"), "q", "cnt").select("height", F.expr("shiftright(q, 2 * height)").alias("q"), "cnt").groupBy("height", "q").agg(F.sum("cnt").alias("cnt"))
    # Level with height h has 4^(depth - h) quadrants; numbers before it in heap order: (4^(depth - h) - 1) / 3.
    total = (4 ** (depth + 1) - 1) // 3
    grid = None
    for h in range(depth, -1, -1):
        part = spark.range(4 ** (depth - h)).select(F.lit(h).alias("height"), F.col("id").alias("q"))
        grid = part if grid is None else grid.unionByName(part)
    assert total > 0
    first = F.element_at(F.array(*(F.lit((4 ** (depth - h) - 1) // 3 + 1).cast("long") for h in range(depth + 1))), F.col("height") + 1)
    out = grid.join(every, ["height", "q"], "left")
    side = F.expr(f"shiftleft(1, {bits - depth} + height)")
    digits = lambda odd: sum((F.shiftleft(F.shiftright(F.col("q"), 2 * b + odd).bitwiseAND(1), b) for b in range(max(depth, 1))), F.lit(0))
    return out.select(F.lit(tree_id).alias("tree_id"), (first + F.col("q")).cast("long").alias("node_id"), "height", digits(1).cast("int").alias("qx"), digits(0).cast("int").alias("qy"), side.alias("side"), F.coalesce("cnt", F.lit(0)).cast("long").alias("cnt"))


def rectangles(nodes: DataFrame, spec: GridSpec) -> DataFrame:
    """Release rows of quadrants, cut at the domain; those outside go."""
    x0, y0 = F.col("qx") * F.col("side"), F.col("qy") * F.col("side")
    out = nodes.withColumn("x0", x0).withColumn("x1", F.least(x0 + F.col("side"), F.lit(spec.nx))).withColumn("y0", y0).withColumn("y1", F.least(y0 + F.col("side"), F.lit(spec.ny)))
    out = out.where((F.col("x0") < spec.nx) & (F.col("y0") < spec.ny))
    return out.select("tree_id", F.col("node_id").alias("leaf_id"), *(F.col(c).cast("int").alias(c) for c in ("x0", "x1", "y0", "y1")), ((F.col("x1") - F.col("x0")).cast("long") * (F.col("y1") - F.col("y0"))).alias("cells"), "ncount")


def noisy_counts(fm: DataFrame, spec: GridSpec, depth: int, eps: float, allocation: str = "geo", growth: float = 2.0, secret: str | None = None, tree_id: str = "quad") -> tuple[DataFrame, list[float]]:
    depth = min(depth, bits_of(spec))
    parts = budget.levels(eps, depth, allocation, growth)
    nodes = quad_counts(fm, spec, depth, tree_id)
    level = F.element_at(budget.level_array(parts), F.col("height") + 1)
    return nodes.withColumn("ncount", noise.laplace(F.col("cnt"), 1 / level, secret, F.col("tree_id"), "decide", F.col("node_id"))), parts


def publish(fm: DataFrame, spec: GridSpec, depth: int, eps: float, allocation: str = "geo", growth: float = 2.0, smoothing: bool = True, secret: str | None = None, tree_id: str = "quad", step=lambda df: df) -> DataFrame:
    """Leaf quadrants of a quadtree of `depth` levels below the root; the whole budget goes to counts."""
    nodes, parts = noisy_counts(fm, spec, depth, eps, allocation, growth, secret, tree_id)
    depth = len(parts) - 1
    if smoothing:
        level = F.element_at(budget.level_array(parts), F.col("height") + 1)
        nodes = consistency.smooth(nodes, depth, 2 / (level * level), 4, step).withColumn("ncount", F.col("smooth"))
    return rectangles(nodes.where("height = 0"), spec)

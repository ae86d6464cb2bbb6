"""Query workloads: rectangles with uniform centres, keyed so that any engine can replay them."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from geohist.functions.noise import keyed_uniform
from geohist.operators.grid import GridSpec


def _cell(u: Column, n: int) -> Column:
    return F.floor(u * n).cast("int")


def _clipped(q: DataFrame, workload: str, spec: GridSpec) -> DataFrame:
    """Rectangles of width w and height h around the cell (mx, my), cut at the domain."""
    x0, y0 = F.col("mx") - F.floor(F.col("w") / 2), F.col("my") - F.floor(F.col("h") / 2)
    out = q.select(
        F.lit(workload).alias("workload"), F.col("id").alias("qid"),
        F.greatest(F.lit(0), x0).cast("int").alias("x0"), F.least(F.lit(spec.nx), x0 + F.col("w")).cast("int").alias("x1"),
        F.greatest(F.lit(0), y0).cast("int").alias("y0"), F.least(F.lit(spec.ny), y0 + F.col("h")).cast("int").alias("y1"),
    )
    return out


def _centres(spark: SparkSession, spec: GridSpec, n: int | None, seed: str, workload: str, ids: DataFrame | None = None) -> DataFrame:
    """n uniform centres, or one for each row of ids (id)."""
    u = lambda f: keyed_uniform(seed, "query", workload, F.col("id"), f)
    rows = ids if ids is not None else spark.range(n)
    return rows.withColumn("mx", _cell(u("x"), spec.nx)).withColumn("my", _cell(u("y"), spec.ny)).withColumn("uw", u("w")).withColumn("uh", u("h"))


def random_rects(spark: SparkSession, spec: GridSpec, n: int | None = 2000, seed: str = "q", workload: str = "random", ids: DataFrame | None = None) -> DataFrame:
    """Any shape and size: width and height uniform from one cell to the whole domain. With ids, one for each of them."""
    q = _centres(spark, spec, n, seed, workload, ids)
    return _clipped(q.withColumn("w", 1 + _cell(F.col("uw"), spec.nx)).withColumn("h", 1 + _cell(F.col("uh"), spec.ny)), workload, spec)


def side_of(spec: GridSpec, share: float) -> int:
    return max(1, round(math.sqrt(share * spec.cells)))


def squares(spark: SparkSession, spec: GridSpec, share: float, n: int = 2000, seed: str = "q") -> DataFrame:
    """Squares that cover `share` of the domain (before they are cut at its border)."""
    name, side = f"square_{round(share * 100)}", side_of(spec, share)
    return _clipped(_centres(spark, spec, n, seed, name).withColumn("w", F.lit(side)).withColumn("h", F.lit(side)), name, spec)


def mixed(spark: SparkSession, spec: GridSpec, n: int | None = 2000, seed: str = "q", ids: DataFrame | None = None) -> DataFrame:
    """A quarter each of random rectangles and squares of 2, 6 and 10 percent. With ids, one for each of them, by the remainder of the id."""
    q = _centres(spark, spec, n, seed, "mixed", ids)
    sides = F.element_at(F.array(*(F.lit(side_of(spec, s)) for s in (0.02, 0.06, 0.10))), F.greatest(F.lit(1), (F.col("id") % 4).cast("int")))
    free = F.col("id") % 4 == 0
    return _clipped(q.withColumn("w", F.when(free, 1 + _cell(F.col("uw"), spec.nx)).otherwise(sides)).withColumn("h", F.when(free, 1 + _cell(F.col("uh"), spec.ny)).otherwise(sides)), "mixed", spec)


def named(spark: SparkSession, spec: GridSpec, name: str, n: int = 2000, seed: str = "q") -> DataFrame:
    if name == "random":
        return random_rects(spark, spec, n, seed)
    if name == "mixed":
        return mixed(spark, spec, n, seed)
    return squares(spark, spec, int(name.rpartition("_")[2]) / 100, n, seed)

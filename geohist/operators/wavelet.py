"""Haar wavelet baseline: noise on coefficients, less on those that many cells share."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from geohist.functions import noise
from geohist.operators.grid import GridSpec
from geohist.operators.grids import MOST_CELLS


def padded(n: int) -> int:
    return 1 << (n - 1).bit_length()


def _axis(pos: str, n: int) -> tuple[Column, int]:
    """For a cell index: array of (level, block, factor): its part in the mean (level log2 n + 1) and in one detail a level."""
    top = n.bit_length() - 1
    parts = [F.struct(F.lit(top + 1).alias("l"), F.lit(0).alias("k"), F.lit(1.0 / n).alias("f"))]
    for lv in range(1, top + 1):
        sign = F.when(F.shiftright(F.col(pos), lv - 1).bitwiseAND(1) == 0, 1.0).otherwise(-1.0)
        parts.append(F.struct(F.lit(lv).alias("l"), F.shiftright(F.col(pos), lv).alias("k"), (sign / float(1 << lv)).alias("f")))
    return F.array(*parts), top


def coefficients(fm: DataFrame, spec: GridSpec) -> DataFrame:
    """(lx, kx, ly, ky, coef) that are not zero by absence of data: each cell adds to (1 + log2 nx)(1 + log2 ny) of them.

    Level l from 1: the detail of blocks of 2^l cells; the level above the last: the mean. One aggregation.
    """
    ax, _ = _axis("cx", padded(spec.nx))
    ay, _ = _axis("cy", padded(spec.ny))
    x = fm.select("cx", "cy", "cnt", F.explode(ax).alias("a")).select(F.col("a.l").alias("lx"), F.col("a.k").alias("kx"), "cy", (F.col("cnt") * F.col("a.f")).alias("v"))
    x = x.groupBy("lx", "kx", "cy").agg(F.sum("v").alias("v"))
    y = x.select("lx", "kx", "v", F.explode(ay).alias("a")).select("lx", "kx", F.col("a.l").alias("ly"), F.col("a.k").alias("ky"), (F.col("v") * F.col("a.f")).alias("v"))
    return y.groupBy("lx", "kx", "ly", "ky").agg(F.sum("v").alias("coef"))


def _every(spark, n: int, l: str, k: str) -> DataFrame:
    top = n.bit_length() - 1
    out = spark.createDataFrame([(top + 1, 0)], f"{l} int, {k} int")
    for lv in range(1, top + 1):
        out = out.unionByName(spark.range(n >> lv).select(F.lit(lv).alias(l), F.col("id").cast("int").alias(k)))
    return out


def noisy_coefficients(fm: DataFrame, spec: GridSpec, eps: float, secret: str | None = None, tree_id: str = "wavelet", most_cells: int = MOST_CELLS) -> DataFrame:
    """Every coefficient with noise of scale rho / (eps * cells it spans)."""
    nx, ny = padded(spec.nx), padded(spec.ny)
    if nx * ny > most_cells:
        raise ValueError(f"{nx * ny} dense coefficients; raise most_cells to allow them")
    spark = fm.sparkSession
    full = _every(spark, nx, "lx", "kx").crossJoin(_every(spark, ny, "ly", "ky"))  # nx * ny rows by definition, checked above
    rho = nx.bit_length() * ny.bit_length()
    span = lambda l, n: F.when(F.col(l) > n.bit_length() - 1, F.lit(float(n))).otherwise(F.pow(F.lit(2.0), F.col(l)))
    c = full.join(coefficients(fm, spec), ["lx", "kx", "ly", "ky"], "left").withColumn("coef", F.coalesce("coef", F.lit(0.0)))
    return c.withColumn("coef", noise.laplace(F.col("coef"), rho / (eps * span("lx", nx) * span("ly", ny)), secret, tree_id, "coef", F.col("lx"), F.col("kx"), F.col("ly"), F.col("ky")))


def _inverse(frame: DataFrame, n: int, l: str, k: str, pos: str, keep: list[str], value: str) -> DataFrame:
    """Cells along one axis from its coefficients, in one aggregation: the n coefficients of a line become an array of n cells.

    In order of level, highest first, and block, they stand as mean, then 1, 2, 4 ... details; each level doubles the cells.
    """
    line = F.transform(F.array_sort(F.collect_list(F.struct((-F.col(l)).alias("l"), F.col(k).alias("k"), F.col(value).alias("v")))), lambda x: x["v"])
    lines = frame.groupBy(*keep).agg(line.alias("c")).withColumn("a", F.slice("c", 1, 1))
    size = 1
    while size < n:
        pairs = F.zip_with("a", F.slice("c", size + 1, size), lambda a, d: F.array(a + d, a - d))
        lines = lines.withColumn("a", F.flatten(pairs))
        size *= 2
    return lines.select(*keep, F.posexplode("a").alias(pos, value))


def cells(coefs: DataFrame, spec: GridSpec) -> DataFrame:
    """(cx, cy, value) of the domain from all coefficients."""
    x = _inverse(coefs, padded(spec.nx), "lx", "kx", "cx", ["ly", "ky"], "coef")
    y = _inverse(x, padded(spec.ny), "ly", "ky", "cy", ["cx"], "coef")
    return y.where((F.col("cx") < spec.nx) & (F.col("cy") < spec.ny)).select("cx", "cy", F.col("coef").alias("value"))


def publish(fm: DataFrame, spec: GridSpec, eps: float, secret: str | None = None, tree_id: str = "wavelet") -> DataFrame:
    """Release rows, one for each cell."""
    c = cells(noisy_coefficients(fm, spec, eps, secret, tree_id), spec)
    return c.select(F.lit(tree_id).alias("tree_id"), (F.col("cx").cast("long") * spec.ny + F.col("cy")).alias("leaf_id"), F.col("cx").alias("x0"), (F.col("cx") + 1).alias("x1"), F.col("cy").alias("y0"), (F.col("cy") + 1).alias("y1"), F.lit(1).cast("long").alias("cells"), F.col("value").alias("ncount"))



"""Where releases go: files, partitioned cells, views."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from geohist.functions.noise import TEST_SECRET, held

_OPEN = {"tree_id", "leaf_id", "x0", "x1", "y0", "y1", "cells", "ncount"}


def write(published: DataFrame, ledger: DataFrame, path: str, secret: str, fmt: str = "parquet", testing: bool = False) -> None:
    """Published leaves and ledger under one path. Columns that only the curator may see, and the published test key, are refused."""
    extra = set(published.columns) - _OPEN
    if extra:
        raise ValueError(f"not for publication: {sorted(extra)}")
    if held(secret) == TEST_SECRET and not testing:
        raise ValueError("the test key protects nothing")
    options = {"header": "true"} if fmt == "csv" else {}
    published.write.mode("overwrite").options(**options).format(fmt).save(f"{path}/leaves")
    ledger.write.mode("overwrite").options(**options).format(fmt).save(f"{path}/ledger")


def write_cells(fm: DataFrame, path: str, tile: int = 64) -> None:
    """Cells partitioned by coarse tile, so that a box reads its own folders only."""
    tx, ty = (F.floor(F.col(c) / tile).cast("int") for c in ("cx", "cy"))
    fm.withColumn("tx", tx).withColumn("ty", ty).repartition("tx", "ty").write.mode("overwrite").partitionBy("tx", "ty").parquet(path)


def read_box(spark, path: str, box: tuple[int, int, int, int], tile: int = 64) -> DataFrame:
    x0, x1, y0, y1 = box
    c = F.col
    tiles = c("tx").between(x0 // tile, (x1 - 1) // tile) & c("ty").between(y0 // tile, (y1 - 1) // tile)
    return spark.read.parquet(path).where(tiles & (c("cx") >= x0) & (c("cx") < x1) & (c("cy") >= y0) & (c("cy") < y1))


def register(published: DataFrame, name: str) -> None:
    published.createOrReplaceTempView(name)


def metadata(published: DataFrame, **facts) -> DataFrame:
    """One JSON text for each tree: its facts, leaves and cells."""
    known = [F.lit(v).alias(k) for k, v in facts.items()]
    return published.groupBy("tree_id").agg(F.count(F.lit(1)).alias("leaves"), F.sum("cells").alias("cells")).select("tree_id", F.to_json(F.struct(*known, "leaves", "cells")).alias("metadata"))

"""SQL functions, table functions and UDFs for users of SQL; hot paths use Column expressions instead."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, IntegerType, StructField, StructType

from geohist.functions.noise import TEST_SECRET


def register(spark: SparkSession, secret: str) -> None:
    """Temporary SQL functions; Catalyst inlines their bodies. The secret is part of the session's functions: do not share them."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION overlap_cells(ax0 INT, ax1 INT, ay0 INT, ay1 INT, bx0 INT, bx1 INT, by0 INT, by1 INT) RETURNS BIGINT RETURN cast(greatest(0, least(ax1, bx1) - greatest(ax0, bx0)) AS BIGINT) * greatest(0, least(ay1, by1) - greatest(ay0, by0))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION cell_index(v DOUBLE, lo DOUBLE, hi DOUBLE, n INT) RETURNS INT RETURN least(n - 1, cast(floor((greatest(lo, least(hi, v)) - lo) * n / (hi - lo)) AS INT))")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION keyed_uniform(k STRING) RETURNS DOUBLE RETURN (cast(conv(substring(sha2(concat('{secret}/', k), 256), 1, 12), 16, 10) AS DOUBLE) + 0.5D) / 281474976710656D")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION keyed_laplace(v DOUBLE, scale DOUBLE, k STRING) RETURNS DOUBLE RETURN v - signum(keyed_uniform(k) - 0.5D) * ln(1 - 2 * abs(keyed_uniform(k) - 0.5D)) * scale")


def overlap_by_sql(spark: SparkSession, fm: DataFrame) -> DataFrame:
    register(spark, TEST_SECRET)
    return fm.select("cx", "cy", F.expr("overlap_cells(cx, cx + 10, cy, cy + 10, 20, 40, 20, 40)").alias("shared"))


def laplace_by_sql(spark: SparkSession, fm: DataFrame) -> DataFrame:
    register(spark, TEST_SECRET)
    return fm.select("cx", "cy", F.expr("round(keyed_laplace(cnt, 2.0D, concat_ws('/', 'sql', cx, cy)), 6)").alias("noisy"))


@F.pandas_udf(DoubleType())  # a type object: a DDL string would need a running session when this module is imported
def abs_dev(v: pd.Series) -> float:
    """Sum of absolute deviations from the mean of a group."""
    return float((v - v.mean()).abs().sum())


@F.pandas_udf(DoubleType())
def unevenness_udf(low: pd.Series, high: pd.Series) -> pd.Series:
    """Unevenness of a split whose sides are given as arrays of all cell counts; the reference for tests."""
    dev = lambda a: float(np.abs(np.asarray(a, float) - np.mean(a)).sum()) if len(a) else 0.0
    return pd.Series([dev(a) + dev(b) for a, b in zip(low, high)])


def split_by_udf(fm: DataFrame) -> DataFrame:
    """(k, o) of the middle split of columns, by the UDF over both sides' arrays of a 64 by 64 grid."""
    side = lambda c: F.collect_list(F.when(c, F.col("cnt")))
    halves = fm.agg(side(F.col("cx") < 32).alias("low"), side(F.col("cx") >= 32).alias("high"))
    pad = lambda c: F.concat(F.col(c), F.array_repeat(F.lit(0).cast("long"), 2048 - F.size(c)))
    return halves.select(F.lit(32).alias("k"), F.round(unevenness_udf(pad("low"), pad("high")), 4).alias("o"))


@F.udtf(returnType=StructType([StructField("k", IntegerType())]))
class LatticeUdtf:
    """Positions that a search of some rounds over 1..u can meet."""

    def eval(self, u: int, rounds: int):
        gaps, found = [(1, u)], set()
        for _ in range(rounds + 1):
            finer = []
            for a, b in gaps:
                m = a + (b - a) // 2
                found.add(m)
                finer += [(a, m), (m, b)]
            gaps = finer
        for k in sorted(found):
            if 1 <= k < u:
                yield (k,)


def lattice_by_udtf(spark: SparkSession, nodes: DataFrame, rounds: int) -> DataFrame:
    """(node, k) by a lateral join with the table function."""
    spark.udtf.register("lattice_positions", LatticeUdtf)
    nodes.createOrReplaceTempView("lattice_nodes")
    return spark.sql(f"SELECT node, k FROM lattice_nodes, LATERAL lattice_positions(u, {rounds})")

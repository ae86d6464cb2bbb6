"""Point sets: the given tables, files of several formats, and keyed synthetic sets."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from geohist.functions.noise import gaussian_pair, keyed_uniform, uniform_of
from geohist.operators.grid import GridSpec

_DAY = 86_400_000_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def micros(c: str | Column) -> Column:
    """Microseconds since 1970 of a date or timestamp, with or without zone (session zone UTC)."""
    c = F.col(c) if isinstance(c, str) else c
    return F.unix_micros(c.cast("timestamp"))


def day(text: str) -> float:
    """Microseconds of a calendar day."""
    import datetime

    return float((datetime.date.fromisoformat(text) - datetime.date(1970, 1, 1)).days * _DAY)


def axis(expr: str | Column, lo: float, hi: float) -> tuple[Column, float, float]:
    return (F.expr(expr) if isinstance(expr, str) else expr).cast("double"), lo, hi


def _customers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers whose nation is known."""
    return table(spark, sf_dir, "customer").join(table(spark, sf_dir, "nation").select("n_nationkey"), F.col("c_nationkey") == F.col("n_nationkey"))


#: Point sets of the given tables: rows, x, y, domain (x from, x to, y from, y to).
SETS: dict[str, tuple[Callable, Callable, Callable, tuple[float, float, float, float]]] = {
    "p1": (lambda s, d: table(s, d, "events"), lambda: micros("ts"), lambda: F.col("value"), (day("2024-01-01"), day("2024-01-31"), 0.0, 500.0)),
    "p2": (lambda s, d: table(s, d, "lineitem"), lambda: micros("l_shipdate"), lambda: F.col("l_extendedprice"), (day("1995-01-01"), day("2002-01-01"), 0.0, 106000.0)),
    "p3": (lambda s, d: table(s, d, "lineitem"), lambda: F.col("l_quantity"), lambda: F.col("l_extendedprice"), (0.0, 52.0, 0.0, 106000.0)),
    "p4": (lambda s, d: table(s, d, "embeddings"), lambda: F.get("embedding", 0), lambda: F.get("embedding", 1), (-1.0, 1.0, -1.0, 1.0)),
    "p5": (lambda s, d: table(s, d, "documents"), lambda: F.log("n_chars"), lambda: (F.col("doc_id") % 200) / 200, (0.0, 14.0, 0.0, 1.0)),
    "p6": (lambda s, d: table(s, d, "orders"), lambda: micros("o_orderdate"), lambda: F.col("o_totalprice"), (day("1995-01-01"), day("2001-09-01"), 0.0, 500000.0)),
    "p7": (_customers, lambda: F.col("c_nationkey"), lambda: F.col("c_acctbal"), (0.0, 25.0, -1000.0, 10000.0)),
}


def points(spark: SparkSession, sf_dir: str, set_id: str) -> DataFrame:
    """(px, py) of a named set; only the columns behind them are read."""
    rows, x, y, _ = SETS[set_id]
    return rows(spark, sf_dir).select(x().cast("double").alias("px"), y().cast("double").alias("py"))


def grid_of(set_id: str, side: int = 1024) -> GridSpec:
    if set_id not in SETS:
        return GridSpec(0.0, 1024.0, 0.0, 1024.0, side, side)
    return GridSpec(*SETS[set_id][3], side, side)


def read_points(spark: SparkSession, path: str, fmt: str, schema: str = "px double, py double") -> tuple[DataFrame, DataFrame]:
    """(points, rejected) of CSV, JSON, ORC or Parquet files; text rows that do not fit the schema are kept apart, beside what could be read of them."""
    if fmt in ("csv", "json"):
        raw = spark.read.schema(f"{schema}, _corrupt_record string").option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", "_corrupt_record").format(fmt).load(path)
        good = raw.where("_corrupt_record is null").drop("_corrupt_record")
        return good, raw.where("_corrupt_record is not null")
    return spark.read.schema(schema).format(fmt).load(path), spark.createDataFrame([], "_corrupt_record string")


def crop(df: DataFrame, box: tuple[float, float, float, float] | None = None, time: tuple[str, str] | None = None, types: list[str] | None = None, x: str = "px", y: str = "py", ts: str = "ts", kind: str = "event_type") -> DataFrame:
    """Rows in a half-open box, a half-open time range and a list of types, as filters that reach the scan."""
    if box:
        df = df.where((F.col(x) >= box[0]) & (F.col(x) < box[1]) & (F.col(y) >= box[2]) & (F.col(y) < box[3]))
    if time:
        kind_of = dict(df.dtypes)[ts]
        df = df.where((F.col(ts) >= F.lit(time[0]).cast(kind_of)) & (F.col(ts) < F.lit(time[1]).cast(kind_of)))
    if types:
        df = df.where(F.col(kind).isin(types))
    return df


def around(df: DataFrame, lat: float, lon: float, side_km: float, lat_col: str = "lat", lon_col: str = "lon") -> DataFrame:
    """Rows in a square of side_km around a place, with px, py in km from its south-west corner (local flat projection).

    The bounds are plain ranges of latitude and longitude, so they reach the scan.
    """
    per_lat = 111.32
    per_lon = per_lat * math.cos(math.radians(lat))
    dy, dx = side_km / 2 / per_lat, side_km / 2 / per_lon
    inside = (F.col(lat_col) >= lat - dy) & (F.col(lat_col) < lat + dy) & (F.col(lon_col) >= lon - dx) & (F.col(lon_col) < lon + dx)
    return df.where(inside).withColumn("px", (F.col(lon_col) - (lon - dx)) * per_lon).withColumn("py", (F.col(lat_col) - (lat - dy)) * per_lat)


def gaussian(spark: SparkSession, n: int | None, sigma: float, seed: str = "g", ids: DataFrame | None = None) -> DataFrame:
    """(px, py) of n points, or of one for each row of ids (id), around one centre that is uniform on the 1024 square; each coordinate normal with sd sigma."""
    rows = ids if ids is not None else spark.range(n)
    a, b = gaussian_pair(seed, "point", sigma, F.col("id"))
    cx, cy = (keyed_uniform(seed, "centre", sigma, s) * 1024 for s in ("x", "y"))
    return rows.select((cx + a * sigma).alias("px"), (cy + b * sigma).alias("py"))


def patchwork(spark: SparkSession, n: int, seed: str = "w") -> DataFrame:
    """(px, py) of n points with density even in pieces: background, 30 rectangles, 12 thin strips, 8 bumps.

    The pieces follow from the seed alone; low-numbered pieces get more points.
    """
    u = lambda *k: keyed_uniform(seed, *k)
    v = lambda *k: uniform_of(seed, *k)
    pieces = []  # x from, width, y from, height; a bump: centre and deviation
    for p in range(30):
        w, h = 20 + v("w", p) * 140, 20 + v("h", p) * 140
        pieces.append((v("rx", p) * (1024 - w), w, v("ry", p) * (1024 - h), h))
    for p in range(12):
        at, thick = v("at", p) * 1010, 2 + v("thick", p) * 6
        pieces.append((0.0, 1024.0, at, thick) if v("dir", p) < 0.5 else (at, thick, 0.0, 1024.0))
    for p in range(8):
        sd = 8 + v("sd", p) * 25
        pieces.append((60 + v("bx", p) * 900, sd, 60 + v("by", p) * 900, sd))
    pieces.append((0.0, 1024.0, 0.0, 1024.0))
    i = F.col("id")
    rows = spark.range(n).select("id", u("part", i).alias("part"), u("x", i).alias("a"), u("y", i).alias("b"), F.pow(u("piece", i), 2).alias("low"))
    part, low = F.col("part"), F.col("low")
    rows = rows.withColumn("p", F.when(part < 0.2, 50).when(part < 0.7, F.floor(low * 30)).when(part < 0.9, 30 + F.floor(low * 12)).otherwise(42 + F.floor(low * 8)).cast("int"))
    rows = rows.withColumn("bump", (F.col("p") >= 42) & (F.col("p") < 50))
    radius, angle = F.sqrt(-2 * F.log("a")), 2 * math.pi * F.col("b")
    rows = rows.select("p", F.when(F.col("bump"), radius * F.cos(angle)).otherwise(F.col("a")).alias("a"), F.when(F.col("bump"), radius * F.sin(angle)).otherwise(F.col("b")).alias("b"))
    of = lambda j: F.get(F.array(*(F.lit(float(x[j])) for x in pieces)), F.col("p"))
    return rows.select((of(0) + F.col("a") * of(1)).alias("px"), (of(2) + F.col("b") * of(3)).alias("py"))

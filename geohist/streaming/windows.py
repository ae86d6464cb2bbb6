"""Histograms of event streams: one matrix, and one release, for each closed window."""

from __future__ import annotations

import time
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from geohist.functions import noise
from geohist.functions.storage import shared_folder
from geohist.operators.grid import GridSpec, all_cells, cell_of
from geohist.sources import points as src


def read(spark: SparkSession, path: str, schema, fmt: str = "parquet", per_trigger: int = 1) -> DataFrame:
    """A stream of files of a fixed schema."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).format(fmt).load(path)


def cell_counts(events: DataFrame, spec: GridSpec, size: str, slide: str | None = None, late: str = "3 days", ts: str = "ts") -> DataFrame:
    """(begins, cx, cy, cnt) of tumbling or sliding windows; rows later than `late` are dropped, so a closed window never changes."""
    w = F.window(ts, size, slide) if slide else F.window(ts, size)
    return cell_of(events.withWatermark(ts, late), spec).groupBy(w.alias("w"), "cx", "cy").agg(F.count(F.lit(1)).alias("cnt")).select(F.unix_micros(F.col("w.start")).alias("begins"), "cx", "cy", "cnt")


def window_budget(eps: float, size_us: int, slide_us: int | None = None) -> float:
    """Budget of one window: all of it for tumbling windows (their records are disjoint), a share for sliding ones."""
    return eps if not slide_us else eps / -(-size_us // slide_us)


def session_points(events: DataFrame, gap: str, late: str = "1 day", user: str = "user_id", ts: str = "ts") -> DataFrame:
    """(user, begins) of sessions. One record can make, merge or move a start, so counts of starts have sensitivity 2."""
    return events.withWatermark(ts, late).groupBy(F.session_window(ts, gap).alias("w"), user).agg(F.count(F.lit(1)).alias("n")).select(user, F.col("w.start").alias("begins"), "n")


def deduplicated(events: DataFrame, key: str = "event_id", late: str = "3 days", ts: str = "ts") -> DataFrame:
    return events.withWatermark(ts, late).dropDuplicatesWithinWatermark([key])


def window_cells(batch: DataFrame, spec: GridSpec, first: int, last: int, step: int) -> DataFrame:
    """(begins, cx, cy, cnt) of every cell of the public grid for every window that begins in [first, last): which cells, and which windows, hold records is not public."""
    spark = batch.sparkSession
    every = spark.range(first, last, step).select(F.col("id").alias("begins")).crossJoin(all_cells(spark, spec))  # windows x cells, both public
    return every.join(batch, ["begins", "cx", "cy"], "left").select("begins", "cx", "cy", F.coalesce("cnt", F.lit(0)).alias("cnt"))


def release_windows(counts: DataFrame, spec: GridSpec, eps: float, path: str, secret: str, first: int, last: int, step: int) -> object:
    """A batch writer: every cell of the grid in every closed window, noise keyed by window and cell, so a repeated batch writes the same rows.

    Windows are the public calendar [first, last) in microseconds, `step` apart. A batch releases the windows whose records
    it closes; `fill` releases those that held none at the end, as silence would tell that they are empty.
    """

    def noisy(cells: DataFrame) -> DataFrame:
        return cells.select("begins", "cx", "cy", noise.laplace(F.col("cnt"), 1 / eps, secret, "window", F.col("begins"), F.col("cx"), F.col("cy")).alias("ncount"))

    def write(batch: DataFrame, epoch: int) -> None:
        batch = batch.where((F.col("begins") >= first) & (F.col("begins") < last))
        closed = batch.select("begins").distinct()
        noisy(window_cells(batch, spec, first, last, step).join(F.broadcast(closed), "begins", "left_semi")).write.mode("overwrite").parquet(f"{path}/epoch={epoch}")

    return counts.writeStream.outputMode("append").foreachBatch(write)


def fill(spark: SparkSession, spec: GridSpec, eps: float, path: str, secret: str, first: int, last: int, step: int) -> DataFrame:
    """All released windows, and noise alone for the windows of the calendar that no batch released."""
    done = spark.read.parquet(path).select("begins", "cx", "cy", "ncount")
    none = spark.createDataFrame([], "begins long, cx int, cy int, cnt long")
    rest = window_cells(none, spec, first, last, step).join(done.select("begins").distinct(), "begins", "left_anti")
    draw = noise.laplace(F.col("cnt"), 1 / eps, secret, "window", F.col("begins"), F.col("cx"), F.col("cy"))
    return done.unionByName(rest.select("begins", "cx", "cy", draw.alias("ncount")))

    return counts.writeStream.outputMode("append").foreachBatch(write)


def running_totals(events: DataFrame, most: int = 1_000_000) -> DataFrame:
    """(user_id, kept) of a stream: rows of each user so far, at most `most`, kept as state (contribution bounds of streams)."""
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def update(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        before = state.get[0] if state.exists else 0
        now = min(most, before + sum(len(b) for b in batches))
        state.update((now,))
        yield pd.DataFrame({"user_id": [key[0]], "kept": [now - before]})

    return events.groupBy("user_id").applyInPandasWithState(update, "user_id long, kept long", "total long", "append", GroupStateTimeout.NoTimeout)


def _base(spark: SparkSession) -> str:
    return shared_folder(spark, "stream")


def _run(df: DataFrame, base: str) -> DataFrame:
    """Run to the end of the files. The last windows stay open by the watermark, so a far-off row closes them in `closing`."""
    q = df.writeStream.format("parquet").option("path", f"{base}/out").option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    return df.sparkSession.read.schema(df.schema).parquet(f"{base}/out")


def closing(spark: SparkSession, sf_dir: str, base: str, halves: bool = False) -> DataFrame:
    """The events as a stream of files: the table, then one row in the far future that closes every window.

    With halves: the rows before noon of 16 January, the others, and the former but for their last four days again.
    """
    batch = spark.read.parquet(f"{sf_dir}/events.parquet").select("event_id", "user_id", F.col("ts").cast("timestamp").alias("ts"), "value")
    noon = F.lit("2024-01-16 12:00:00").cast("timestamp")
    early = F.lit("2024-01-12 12:00:00").cast("timestamp")
    for part in [batch.where(F.col("ts") < noon), batch.where(F.col("ts") >= noon), batch.where(F.col("ts") < early)] if halves else [batch]:
        part.coalesce(1).write.mode("append").parquet(f"{base}/in")
        time.sleep(1.1 if halves else 0)  # files are read in order of their time
    stream = read(spark, f"{base}/in", batch.schema)
    end = batch.limit(1).select(F.lit(-1).cast("long").alias("event_id"), F.lit(-1).cast(dict(batch.dtypes)["user_id"]).alias("user_id"), F.lit("2100-01-01").cast("timestamp").alias("ts"), F.lit(0.0).alias("value"))
    end.write.mode("append").parquet(f"{base}/in")
    return stream


def _points(stream: DataFrame) -> DataFrame:
    return stream.select("ts", src.micros("ts").cast("double").alias("px"), F.col("value").alias("py"))


def replay(spark: SparkSession, sf_dir: str, size: str, slide: str | None = None, side: int = 8) -> DataFrame:
    base = _base(spark)
    spec = src.grid_of("p1", side)
    return _run(cell_counts(_points(closing(spark, sf_dir, base)), spec, size, slide), base).where("begins < 4000000000000000")


def replay_deduplicated(spark: SparkSession, sf_dir: str) -> DataFrame:
    base = _base(spark)
    return _run(deduplicated(closing(spark, sf_dir, base)).select("event_id"), base).where("event_id >= 0").agg(F.count(F.lit(1)).alias("n"))


#: The public calendar of the replayed release: whole days of the events' domain, in microseconds.
DAY = 86_400_000_000
CALENDAR = (1_704_067_200_000_000, 1_704_067_200_000_000 + 30 * DAY, DAY)


def replay_release(spark: SparkSession, sf_dir: str, eps: float = 1.0) -> DataFrame:
    """(begins, cx, cy, ncount) of an 8 by 8 grid for each day, released by foreachBatch; days without records too."""
    base, spec = shared_folder(spark, "stream"), src.grid_of("p1", 8)
    counts = cell_counts(_points(closing(spark, sf_dir, base)), spec, "1 day")
    q = release_windows(counts, spec, eps, f"{base}/out", noise.TEST_SECRET, *CALENDAR).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    return fill(spark, spec, eps, f"{base}/out", noise.TEST_SECRET, *CALENDAR)


def replay_sessions(spark: SparkSession, sf_dir: str, gap: str = "12 hours") -> DataFrame:
    """(user_id, begins, n) of the sessions of a stream."""
    base = _base(spark)
    events = closing(spark, sf_dir, base)
    out = _run(session_points(events, gap), base)
    return out.where("user_id >= 0").select("user_id", F.unix_micros("begins").alias("begins"), "n")


def replay_totals(spark: SparkSession, sf_dir: str, most: int = 50) -> DataFrame:
    """(user_id, kept): rows of each user that a bound of `most` keeps, from the state of a stream."""
    base = _base(spark)
    out = _run(running_totals(closing(spark, sf_dir, base), most), base)
    return out.where("user_id >= 0").groupBy("user_id").agg(F.sum("kept").alias("kept"))


def replay_late(spark: SparkSession, sf_dir: str, side: int = 8) -> DataFrame:
    """(begins, cx, cy, cnt) of days when rows come late: a file of the first half, one of the second half, then one
    that holds the first half once more (later than the watermark: dropped) and one in the far future that closes all."""
    base, spec = _base(spark), src.grid_of("p1", side)
    stream = closing(spark, sf_dir, base, halves=True)
    return _run(cell_counts(_points(stream), spec, "1 day", late="3 days"), base).where("begins < 4000000000000000")

"""Relational operators around the histogram methods."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from geohist.functions.noise import keyed_uniform
from geohist.operators.grid import GridSpec, cell_of


def enrich(df: DataFrame, dim: DataFrame, left: str, right: str, hint: str | None = None) -> DataFrame:
    """Inner equi-join with a dimension; Spark picks the way by size unless a hint ('broadcast', 'merge', 'shuffle_hash') is given."""
    return df.join(dim.hint(hint) if hint else dim, F.col(left) == F.col(right))


def interval_join(points: DataFrame, windows: DataFrame, ts: str = "ts", begins: str = "begins", ends: str = "ends", slot: str = "1 day", most: int = 10_000) -> DataFrame:
    """points in half-open windows. Few windows are sent to all tasks; many are listed by the slots they touch and joined on them."""
    inside = (F.col(ts) >= F.col(begins)) & (F.col(ts) < F.col(ends))
    if windows.limit(most + 1).count() <= most:
        return points.join(F.broadcast(windows), inside)
    slots = lambda c: F.window(F.col(c), slot)["start"]
    step = F.expr(f"interval {slot}")
    listed = windows.withColumn("__slot", F.explode(F.sequence(slots(begins), slots(ends), step)))
    return points.withColumn("__slot", slots(ts)).join(listed, "__slot").where(inside).drop("__slot")


def asof_join(left: DataFrame, right: DataFrame, ts: str, by: list[str], value: str, slot_seconds: int = 86_400) -> DataFrame:
    """left with the value of the latest right row of the same group at or before its time; no pairs.

    Rows are dealt by group and time slot, so that a large group, or none at all (by empty), is many tasks. What a slot
    takes over from those before it is the last value of each earlier slot, carried on over one row a slot.
    """
    at, kind = "asof_slot", dict(right.dtypes)[value]
    slots = lambda df: df.withColumn(at, F.floor(F.unix_micros(F.col(ts).cast("timestamp")) / (slot_seconds * 1_000_000)))
    l = slots(left.withColumn("asof_value", F.lit(None).cast(kind)).withColumn("asof_side", F.lit(1)))
    r = slots(right.select(*by, ts, F.col(value).alias("asof_value"), F.lit(0).alias("asof_side")))
    last = r.groupBy(*by, at).agg(F.max_by("asof_value", ts).alias("held"))
    every = l.select(*by, at).distinct().join(last, [*by, at], "full")  # one row for each group and slot
    before = W.partitionBy(*by).orderBy(at).rowsBetween(W.unboundedPreceding, -1)
    carried = every.select(*by, at, F.last("held", ignorenulls=True).over(before).alias("carried"))
    w = W.partitionBy(*by, at).orderBy(ts, "asof_side").rowsBetween(W.unboundedPreceding, W.currentRow)
    both = l.unionByName(r, allowMissingColumns=True).withColumn(value, F.last("asof_value", ignorenulls=True).over(w))
    out = both.where("asof_side = 1").join(carried, [*by, at], "left").withColumn(value, F.coalesce(value, "carried"))
    return out.drop("asof_value", "asof_side", "carried", at)


def compare(a: DataFrame, b: DataFrame) -> DataFrame:
    """Counts of two matrices side by side, cells of either."""
    return a.withColumnRenamed("cnt", "before").join(b.withColumnRenamed("cnt", "after"), ["cx", "cy"], "full").select("cx", "cy", F.coalesce("before", F.lit(0)).alias("before"), F.coalesce("after", F.lit(0)).alias("after"))


def users_per_cell(points: DataFrame, spec: GridSpec, by: tuple[str, ...] = ("cx", "cy"), user: str = "user_id", approx: bool = False) -> DataFrame:
    users = F.approx_count_distinct(user) if approx else F.count_distinct(user)
    return cell_of(points, spec).groupBy(*by).agg(users.alias("users"))


def cell_stats(events: DataFrame) -> DataFrame:
    return events.groupBy("event_type").agg(
        F.count(F.lit(1)).alias("n"), F.round(F.avg("value"), 6).alias("mean"), F.round(F.stddev("value"), 6).alias("sd"), F.min_by("event_id", F.struct("value", "event_id")).alias("least"), F.round(F.percentile("value", 0.5), 6).alias("median")
    )


def bound_contributions(df: DataFrame, user: str, most: int, secret: str, key: str) -> DataFrame:
    """At most `most` rows of each user, chosen by keyed draws; counts then have sensitivity `most` for whole users."""
    w = W.partitionBy(user).orderBy(keyed_uniform(secret, "bound", F.col(key)), key)
    return df.withColumn("__r", F.row_number().over(w)).where(F.col("__r") <= most).drop("__r")


def rank_cells(fm: DataFrame) -> DataFrame:
    """Ranks of all cells by count. Ranks depend on the count only: they are computed over the distinct counts, of which there are few."""
    per = fm.groupBy("cnt").agg(F.count(F.lit(1)).alias("many"))
    w = W.orderBy(F.desc("cnt"))
    ranks = per.select("cnt", (1 + F.coalesce(F.sum("many").over(w.rowsBetween(W.unboundedPreceding, -1)), F.lit(0))).cast("int").alias("r"), F.row_number().over(w).alias("dr"))
    return fm.join(ranks, "cnt").select("cx", "cy", "cnt", "r", "dr")


def moving(fm: DataFrame, reach: int) -> DataFrame:
    """Sum over cells of the same column at most `reach` rows away."""
    w = W.partitionBy("cx").orderBy("cy").rangeBetween(-reach, reach)
    return fm.select("cx", "cy", F.sum("cnt").over(w).alias("near"))


def top_per_group(df: DataFrame, by: list[str], order: list[Column], k: int) -> DataFrame:
    return df.withColumn("__r", F.row_number().over(W.partitionBy(*by).orderBy(*order))).where(F.col("__r") <= k).drop("__r")


def set_op(a: DataFrame, b: DataFrame, kind: str) -> DataFrame:
    return {"union": lambda: a.unionByName(b).distinct(), "intersect": lambda: a.intersect(b), "except": lambda: a.subtract(b)}[kind]()


def neighbours(points: DataFrame, px: float, py: float) -> DataFrame:
    """The neighbouring data set with one record more."""
    return points.unionByName(points.sparkSession.createDataFrame([(px, py)], "px double, py double"))


def sample_keyed(df: DataFrame, share: float, key: str, salt: str = "sample") -> DataFrame:
    """A repeatable sample for benches; not before a release without new accounting."""
    return df.where(keyed_uniform(salt, F.col(key)) < share)

"""As-of joins against a plain loop, and what a streamed release must show of cells that hold no record."""

import random

from pyspark.sql import functions as F

from geohist.operators import answer, grid, relational, workload
from geohist.sources import points as src
from geohist.streaming import windows


def test_asof_join_over_slots_equals_a_loop(spark):
    rng = random.Random(4)
    left = [(i, rng.choice("ab"), rng.randrange(0, 20 * 86_400)) for i in range(300)] + [(900, "a", None), (901, None, 5)]
    right = [(g, t, f"{g}{t}") for g in "ab" for t in sorted(rng.sample(range(5 * 86_400, 15 * 86_400), 12))]
    to = lambda df: df.withColumn("ts", F.timestamp_seconds("ts"))
    l = to(spark.createDataFrame(left, "id int, g string, ts long"))
    r = to(spark.createDataFrame([(g, t, v) for g, t, v in right], "g string, ts long, v string"))
    got = {x["id"]: x["v"] for x in relational.asof_join(l, r, "ts", ["g"], "v").collect()}
    want = {i: max(((t, v) for h, t, v in right if h == g and ts is not None and t <= ts), default=(0, None))[1] for i, g, ts in left}
    assert got == want
    one = {x["id"]: x["v"] for x in relational.asof_join(l.drop("g"), r.where("g = 'a'").drop("g"), "ts", [], "v").collect()}
    assert one == {i: max(((t, v) for h, t, v in right if h == "a" and ts is not None and t <= ts), default=(0, None))[1] for i, _, ts in left}


def test_streamed_release_hides_which_cells_and_days_are_empty(spark):
    sf = "/root/testdata/sf0.001"
    got = windows.replay_release(spark, sf).toPandas()
    assert len(got) == 30 * 64 and not got.duplicated(["begins", "cx", "cy"]).any()
    points = spark.read.parquet(f"{sf}/events.parquet").select(F.col("ts").cast("timestamp").alias("ts"), "value")
    full = points.select(src.micros("ts").cast("double").alias("px"), F.col("value").alias("py"), F.date_trunc("day", "ts").alias("day"))
    held = grid.frequency_matrix(full, src.grid_of("p1", 8), by=("day",)).count()
    assert held < len(got) and (got["ncount"] != 0).all() and (got["ncount"] < 0).any()


def test_many_queries_are_not_broadcast(spark, monkeypatch):
    spec = grid.GridSpec(0.0, 32.0, 0.0, 32.0, 32, 32)
    fm = spark.range(400).select((F.col("id") % 32).cast("int").alias("cx"), (F.col("id") * 7 % 31).cast("int").alias("cy"), (1 + F.col("id") % 5).alias("cnt")).groupBy("cx", "cy").agg(F.sum("cnt").alias("cnt"))
    q = workload.random_rects(spark, spec, 40)
    few = sorted(map(tuple, answer.exact(fm, q).collect()))
    monkeypatch.setattr(answer, "BROADCAST_ROWS", 10)
    assert sorted(map(tuple, answer.exact(fm, q, 8).collect())) == few

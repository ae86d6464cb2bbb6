"""Accuracy and cost of releases."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from geohist.operators import answer, split


def relative_error(answers: DataFrame, smooth: float | None = None, mode: str = "max") -> DataFrame:
    """answers (exact, private) with re, in percent. Without smoothing an exact answer of zero has no error (null)."""
    e = F.col("exact").cast("double")
    if smooth is None:
        below = F.when(e != 0, e)
    else:
        below = F.greatest(e, F.lit(float(smooth))) if mode == "max" else e + F.lit(float(smooth))
    return answers.withColumn("re", F.abs(e - F.col("private")) / below * 100)


def mre(errors: DataFrame, by: tuple[str, ...] = ("tree_id", "workload")) -> DataFrame:
    """Mean and median relative error of a run's queries."""
    return errors.groupBy(*by).agg(F.avg("re").alias("mre"), F.percentile_approx("re", 0.5).alias("median_re"), F.count("re").alias("queries"))


def decompose(leaves: DataFrame, queries: DataFrame, exact: DataFrame) -> DataFrame:
    """(tree_id, workload, qid, noise_error, uniformity_error): curator side, as leaves carry exact counts (cnt) and noisy ones.

    Their sum is private - exact.
    """
    noise_part = answer.private(leaves.withColumn("off", F.col("ncount") - F.col("cnt")), queries, "off").withColumnRenamed("private", "noise_error")
    even = answer.private(leaves.withColumn("c", F.col("cnt").cast("double")), queries, "c").withColumnRenamed("private", "even")
    return noise_part.join(even, ["tree_id", "workload", "qid"]).join(exact, ["workload", "qid"]).select("tree_id", "workload", "qid", "noise_error", (F.col("even") - F.col("exact")).alias("uniformity_error"))


def split_regret(nodes: DataFrame, cells: DataFrame) -> DataFrame:
    """(tree_id, node_id, chosen, best, regret): unevenness of the split taken over that of the best one. cells carry node ids."""
    cut = nodes.where("split_at is not null")
    prof = split.profile(cells, cut)
    low = F.when(F.col("axis") == 0, F.col("x0")).otherwise(F.col("y0"))
    taken = split.unevenness(prof, cut, F.array((F.col("split_at") - low).cast("int"))).select(*split.KEY, F.col("o").alias("chosen"))
    best = split.exact(prof, cut).select(*split.KEY, F.col("value").alias("best"))
    return taken.join(best, split.KEY).withColumn("regret", F.when(F.col("best") > 0, F.col("chosen") / F.col("best")))


def depths(published: DataFrame, height: int) -> DataFrame:
    """Leaves and effective height of a release: from the number of a leaf follows its depth."""
    depth = F.length(F.regexp_replace(F.bin("leaf_id"), "^0+", "")) - 1
    return published.groupBy("tree_id").agg(F.count(F.lit(1)).alias("leaves"), F.max(depth).cast("int").alias("deepest"), F.avg(depth).alias("mean_depth")).withColumn("height", F.lit(height))


def evaluations(nodes: DataFrame) -> DataFrame:
    return nodes.where("evals > 0").groupBy("tree_id").agg(F.sum("evals").alias("evals"), F.count(F.lit(1)).alias("splits"), F.max("evals").alias("most"))


def hotspots(published: DataFrame, k: int) -> DataFrame:
    """The k published regions of highest density."""
    return published.withColumn("density", F.col("ncount") / F.col("cells")).orderBy(F.desc("density"), "tree_id", "leaf_id").limit(k)

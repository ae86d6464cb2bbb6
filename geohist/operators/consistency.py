"""Least-squares smoothing of noisy trees: children sum to their parent, each count weighted by its certainty."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def parent_of(node: Column, fanout: int = 2) -> Column:
    """Heap numbers: 2i, 2i+1 below i; with four children 4i-2 to 4i+1."""
    return F.floor(node / 2) if fanout == 2 else F.floor((node + 2) / 4)


def smooth(nodes: DataFrame, height: int, variance: Column, fanout: int = 2, step=lambda df: df) -> DataFrame:
    """nodes (tree_id, node_id, height, ncount, ...) with `smooth`, for trees of any shape of at most `height` levels below the root.

    Going up, the mean of a node's own draw and its children's sum; going down, the surplus of the parent shared by
    variance. Levels with one step of `fanout` children; each level is two joins of node rows (never cells). `step` may cut
    lineage between levels.
    """
    y = nodes.select("tree_id", "node_id", F.col("ncount").alias("y"), variance.alias("v"), F.col("height").alias("lvl"), parent_of(F.col("node_id"), fanout).cast("long").alias("up"))
    top = height
    done = y.where(F.col("lvl") == 0).select("tree_id", "node_id", "lvl", "up", F.col("y").alias("z"), F.col("v").alias("s"), F.lit(None).cast("double").alias("zc"), F.lit(None).cast("double").alias("sc"))
    ups = [step(done)]
    below = ups[0]
    for h in range(1, top + 1):
        kids = below.groupBy("tree_id", F.col("up").alias("node_id")).agg(F.sum("z").alias("zc"), F.sum("s").alias("sc"))
        own = y.where(F.col("lvl") == h).join(kids, ["tree_id", "node_id"], "left")
        w = 1 / F.col("v") + F.when(F.col("sc").isNotNull(), 1 / F.col("sc")).otherwise(F.lit(0.0))
        z = F.when(F.col("sc").isNotNull(), (F.col("y") / F.col("v") + F.col("zc") / F.col("sc")) / w).otherwise(F.col("y"))
        below = step(own.select("tree_id", "node_id", "lvl", "up", z.alias("z"), (1 / w).alias("s"), "zc", "sc"))
        ups.append(below)
    final = ups[top].select("tree_id", "node_id", F.col("z").alias("smooth"), "zc", "sc")
    parts = [final.select("tree_id", "node_id", "smooth")]
    for h in range(top - 1, -1, -1):
        above = final.select("tree_id", F.col("node_id").alias("up"), F.col("smooth").alias("px"), F.col("zc").alias("pz"), F.col("sc").alias("ps"))
        level = ups[h].join(above, ["tree_id", "up"])
        final = step(level.select("tree_id", "node_id", (F.col("z") + (F.col("px") - F.col("pz")) * F.col("s") / F.col("ps")).alias("smooth"), "zc", "sc"))
        parts.append(final.select("tree_id", "node_id", "smooth"))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return nodes.join(out, ["tree_id", "node_id"])

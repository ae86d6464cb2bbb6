"""Binary trees of the baselines: private medians, means or midpoints, with counts on all nodes and smoothing."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from geohist.functions import budget, noise
from geohist.operators import consistency, release, tree
from geohist.operators.grid import GridSpec


def publish(fm: DataFrame, spec: GridSpec, eps: float, height: int, allocation: str = "geo", split: str = "em_median", split_share: float = 0.15, growth: float = 2.0, smoothing: bool = True, secret: str | None = None, tree_id: str = "kd", mode: str = "auto", step=lambda df: df) -> DataFrame:
    """Leaves of a tree of fixed height: split_share of the budget goes to splits (evenly over levels), the rest to counts.

    Midpoint splits read no data and cost nothing.
    """
    share = 0.0 if split == "midpoint" else split_share
    nodes = tree.build(fm, spec, height, split, share * eps / max(height, 1), secret, tree_id, mode=mode)
    parts = budget.levels((1 - share) * eps, height, allocation, growth)
    noisy = step(release.all_nodes(nodes, parts, secret))
    if smoothing:
        level = F.element_at(budget.level_array(parts), F.col("height") + 1)
        noisy = consistency.smooth(noisy, height, 2 / (level * level), 2, step).withColumn("ncount", F.col("smooth"))
    return release.redact(tree.leaves(noisy))

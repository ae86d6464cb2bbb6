"""Noisy counts of tree nodes: all nodes, leaves only, or leaves of the tree pruned by noisy counts and extents."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from geohist.functions import budget, noise
from geohist.operators.tree import ancestors, cells_of, leaves

KEY = ["tree_id", "node_id"]


@dataclass(frozen=True)
class StopRule:
    """A node stops at a noisy count of min_count or less, or with fewer than min_cells cells."""

    min_count: float | None = 100.0
    min_cells: int | None = 5

    def column(self, ncount: Column) -> Column:
        stop = F.lit(False)
        if self.min_count is not None:
            stop = stop | (ncount <= self.min_count)
        if self.min_cells is not None:
            stop = stop | (cells_of() < self.min_cells)
        return stop


def drawn(nodes: DataFrame, parts: list[float], secret: str) -> DataFrame:
    """nodes with `decided`: the count under its level's budget."""
    level = F.element_at(budget.level_array(parts), F.col("height") + 1)
    return nodes.withColumn("decided", noise.laplace(F.col("cnt"), 1 / level, secret, F.col("tree_id"), "decide", F.col("node_id")))


def all_nodes(nodes: DataFrame, parts: list[float], secret: str | None = None) -> DataFrame:
    """Every node with a noisy count of its level's budget; budgets add along a path."""
    return drawn(nodes, parts, secret).withColumnRenamed("decided", "ncount")


def leaves_only(nodes: DataFrame, eps_data: float, secret: str | None = None) -> DataFrame:
    """Leaves with the whole budget."""
    return leaves(nodes).withColumn("ncount", noise.laplace(F.col("cnt"), 1 / eps_data, secret, F.col("tree_id"), "final", F.col("node_id")))


def pruned(nodes: DataFrame, height: int, eps_data: float, stop: StopRule = StopRule(), allocation: str = "geo", growth: float = 2.0, secret: str | None = None, combine: bool = False) -> DataFrame:
    """Published nodes: the first that stops on each path, with a count drawn from all its path has left.

    Every node's decision is drawn in one projection; a draw below a stopped node is never read or written, so it
    costs nothing. A leaf of height 0 keeps its only draw. `combine` averages both draws by their certainty
    (biased, since the first draw led to the stop; off by default).
    """
    parts = budget.levels(eps_data, height, allocation, growth)
    d = drawn(nodes, parts, secret)
    d = d.withColumn("stops", F.col("split_at").isNull() | stop.column(F.col("decided")))
    up = ancestors(d.select("tree_id", "node_id", "height"), F.lit(height))
    stopped = d.where("stops").select("tree_id", F.col("node_id").alias("ancestor"))
    hidden = up.join(stopped, ["tree_id", "ancestor"], "left_semi").select(*KEY).distinct()
    front = d.where("stops").join(hidden, KEY, "left_anti")
    left = F.element_at(budget.level_array([0.0, *(budget.remaining(parts, h) for h in range(1, height + 1))]), F.col("height") + 1)
    final = noise.laplace(F.col("cnt"), 1 / F.when(left > 0, left), secret, F.col("tree_id"), "final", F.col("node_id"))
    if combine:
        own = F.element_at(budget.level_array(parts), F.col("height") + 1)
        final = (final * left * left + F.col("decided") * own * own) / (left * left + own * own)
    return front.select(*nodes.columns, F.when(F.col("height") == 0, F.col("decided")).otherwise(final).alias("ncount"))


def redact(frame: DataFrame) -> DataFrame:
    """What may leave the curator: rectangles and noisy counts."""
    return frame.select("tree_id", F.col("node_id").alias("leaf_id"), "x0", "x1", "y0", "y1", cells_of().alias("cells"), "ncount")


def path_ledger(frame: DataFrame, height: int, eps_data: float, allocation: str = "geo", growth: float = 2.0) -> DataFrame:
    """(tree_id, node_id, spent): data budget used on the path of every published node; never above eps_data."""
    parts = budget.levels(eps_data, height, allocation, growth)
    spent = [sum(parts[h:]) + budget.remaining(parts, h) for h in range(height + 1)]
    return frame.select(*KEY, F.element_at(budget.level_array(spent), F.col("height") + 1).alias("spent"))

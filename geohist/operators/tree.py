"""Binary trees over the grid, built a level at a time or handed to tasks when nodes are small."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from geohist.functions import noise
from geohist.functions.budget import estimated_height
from geohist.functions.storage import stored
from geohist.operators import local, split
from geohist.operators.grid import GridSpec

NODE = "tree_id string, node_id long, height int, axis int, x0 int, x1 int, y0 int, y1 int, split_at int, cnt long, evals long"
_KEY = split.KEY
#: Cells of a node that a task may finish alone: far below a grid of 1024 rows, so that its first levels use the whole cluster.
MAX_TASK_CELLS = 65_536


def axis_of(height: Column, rule: str = "even_x") -> Column:
    """0 splits columns, 1 splits rows; 'even_x' splits columns at even heights."""
    return (height % 2 if rule == "even_x" else (height + 1) % 2).cast("int")


def root(spark: SparkSession, spec: GridSpec, height: int, tree_id: str = "t", rule: str = "even_x") -> DataFrame:
    axis = height % 2 if rule == "even_x" else (height + 1) % 2
    return spark.createDataFrame([(tree_id, 1, height, axis, 0, spec.nx, 0, spec.ny)], "tree_id string, node_id long, height int, axis int, x0 int, x1 int, y0 int, y1 int")


def noisy_height(fm: DataFrame, eps_height: float, eps_tot: float, secret: str, tree_id: str = "t", c0: float = 10.0, cells: int | None = None) -> int:
    """Height from the noisy number of records; one number reaches the driver."""
    n = fm.agg(noise.laplace(F.coalesce(F.sum("cnt"), F.lit(0)).cast("double"), 1 / eps_height, secret, tree_id, "height").alias("n")).first()["n"]
    return estimated_height(n, eps_tot, c0, cells)


def with_split(nodes: DataFrame, cells: DataFrame, method: str, eps_level: float, secret: str, rounds: int = 3, allow_no_split: bool = False) -> DataFrame:
    """nodes of one height with cnt, evals and split_at (null where a node stays whole)."""
    prof = split.profile(cells, nodes)
    count = prof.groupBy(*_KEY).agg(F.sum(F.col("cnt") * F.col("many")).alias("cnt"))
    chosen = split.METHODS[method](prof, nodes, eps_level=eps_level, secret=secret, rounds=rounds, allow_no_split=allow_no_split).select(*_KEY, "k", "evals")
    low = F.when(F.col("axis") == 0, F.col("x0")).otherwise(F.col("y0"))
    out = nodes.join(count, _KEY, "left").join(chosen, _KEY, "left")
    at = F.when(F.col("k") < split.extent(), low + F.col("k")).cast("int")
    return out.select(*nodes.columns, at.alias("split_at"), F.coalesce("cnt", F.lit(0)).cast("long").alias("cnt"), F.coalesce("evals", F.lit(0)).cast("long").alias("evals"))


def children(parents: DataFrame, rule: str = "even_x") -> DataFrame:
    """Both children of every split node."""
    c = F.col
    cut = parents.where("split_at is not null").select("*", F.explode(F.array(F.lit(0), F.lit(1))).alias("side"))
    side, x = c("side"), c("axis") == 0
    return cut.select(
        "tree_id", (c("node_id") * 2 + side).alias("node_id"), (c("height") - 1).alias("height"), axis_of(c("height") - 1, rule).alias("axis"),
        F.when(x & (side == 1), c("split_at")).otherwise(c("x0")).alias("x0"), F.when(x & (side == 0), c("split_at")).otherwise(c("x1")).alias("x1"),
        F.when(~x & (side == 1), c("split_at")).otherwise(c("y0")).alias("y0"), F.when(~x & (side == 0), c("split_at")).otherwise(c("y1")).alias("y1"),
    )


def moved(cells: DataFrame, parents: DataFrame) -> DataFrame:
    """Cells under the children of the split nodes; cells of whole nodes leave."""
    at = F.when(F.col("axis") == 0, F.col("cx")).otherwise(F.col("cy"))
    cut = parents.where("split_at is not null").select(*_KEY, "axis", "split_at")
    return cells.join(cut, _KEY).select("tree_id", (F.col("node_id") * 2 + (at >= F.col("split_at")).cast("long")).alias("node_id"), "cx", "cy", "cnt")


def counted_leaves(nodes: DataFrame, cells: DataFrame) -> DataFrame:
    count = cells.groupBy(*_KEY).agg(F.sum("cnt").alias("cnt"))
    return nodes.join(count, _KEY, "left").select(*nodes.columns, F.lit(None).cast("int").alias("split_at"), F.coalesce("cnt", F.lit(0)).cast("long").alias("cnt"), F.lit(0).cast("long").alias("evals"))


def finish_subtrees(nodes: DataFrame, cells: DataFrame, method: str, eps_level: float, secret: str, rounds: int = 3, rule: str = "even_x", allow_no_split: bool = False) -> DataFrame:
    """All nodes from `nodes` down, each subtree in one task; a node's cells must fit a task (see build)."""
    joined = nodes.join(cells.select(*_KEY, "cx", "cy", F.col("cnt").alias("cell_cnt")), _KEY, "left")

    def run(batch: pd.DataFrame) -> pd.DataFrame:
        return local.subtree(batch, method, eps_level, secret, rounds, rule, allow_no_split)

    return joined.groupBy(*_KEY).applyInPandas(run, NODE)


def build(fm: DataFrame, spec: GridSpec, height: int, method: str = "searched", eps_level: float = 0.0, secret: str | None = None, tree_id: str = "t", rounds: int = 3, rule: str = "even_x", allow_no_split: bool = False, mode: str = "auto", max_task_cells: int = MAX_TASK_CELLS) -> DataFrame:
    """Nodes of the whole tree, leaves included.

    'levelwise' works with DataFrame steps only, 'subtree' hands the root to one task, 'auto' goes level by level until
    no node can hold more than max_task_cells cells. Keyed noise makes the three equal.
    """
    cells = fm.select(F.lit(tree_id).alias("tree_id"), F.lit(1).cast("long").alias("node_id"), F.col("cx"), F.col("cy"), F.col("cnt").cast("long").alias("cnt"))
    level, done = root(fm.sparkSession, spec, height, tree_id, rule), []
    for h in range(height, 0, -1):
        if mode == "subtree" or (mode == "auto" and _largest(level, spec, h == height) <= max_task_cells):
            return _all([*done, finish_subtrees(level, cells, method, eps_level, secret, rounds, rule, allow_no_split)])
        cut = stored(with_split(level, cells, method, eps_level, secret, rounds, allow_no_split))
        done.append(cut)
        level, cells = children(cut, rule), stored(moved(cells, cut))
    return _all([*done, counted_leaves(level, cells)])


def _largest(level: DataFrame, spec: GridSpec, is_root: bool) -> int:
    if is_root:
        return spec.cells
    return level.agg(F.max((F.col("x1") - F.col("x0")).cast("long") * (F.col("y1") - F.col("y0")))).first()[0] or 0


def _all(parts: list[DataFrame]) -> DataFrame:
    columns = [x.split()[0] for x in NODE.split(", ")]
    out = parts[0].select(*columns)
    for p in parts[1:]:
        out = out.unionByName(p.select(*columns))
    return out


def ancestors(nodes: DataFrame, top: Column) -> DataFrame:
    """(tree_id, node_id, ancestor, up) of every node and proper ancestor, `top` being the tree's height."""
    up = top - F.col("height")
    return nodes.where(up > 0).select(*_KEY, F.explode(F.sequence(F.lit(1), up)).alias("up")).select(*_KEY, F.expr("shiftright(node_id, cast(up as int))").alias("ancestor"), "up")


def leaves(nodes: DataFrame) -> DataFrame:
    return nodes.where("split_at is null")


def cells_of() -> Column:
    return (F.col("x1") - F.col("x0")).cast("long") * (F.col("y1") - F.col("y0"))


"""Answers of range counts: exact ones from the matrix, private ones from a release."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from geohist.operators.grid import prefix_sums
from geohist.operators.grid import GridSpec

#: A side of a join is sent to all tasks only up to so many rows, which are counted first.
BROADCAST_ROWS = 200_000


def overlap() -> Column:
    """Cells that the leaf (l*) and the query (q*) share."""
    c = F.col
    w = F.least(c("lx1"), c("qx1")) - F.greatest(c("lx0"), c("qx0"))
    h = F.least(c("ly1"), c("qy1")) - F.greatest(c("ly0"), c("qy0"))
    return F.greatest(w, F.lit(0)).cast("long") * F.greatest(h, F.lit(0))


def _sides(leaves: DataFrame, queries: DataFrame, value: str) -> tuple[DataFrame, DataFrame]:
    leaf = leaves.select("tree_id", *(F.col(c).alias("l" + c) for c in ("x0", "x1", "y0", "y1")), F.col("cells"), F.col(value).alias("value"))
    q = queries.select("workload", "qid", *(F.col(c).alias("q" + c) for c in ("x0", "x1", "y0", "y1")))
    return leaf, q


def few(queries: DataFrame) -> bool:
    """Whether queries may be sent to all tasks: counted, not guessed."""
    return queries.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS


def by_tile(df: DataFrame, p: str = "", tile: int = 64) -> DataFrame:
    """df listed under every coarse tile (tx, ty) that its rectangle touches."""
    c = F.col
    span = lambda a, b: F.explode(F.sequence(F.floor(c(f"{p}{a}") / tile), F.floor((c(f"{p}{b}") - 1) / tile)))
    return df.where(f"{p}x0 < {p}x1 and {p}y0 < {p}y1").withColumn("tx", span("x0", "x1")).withColumn("ty", span("y0", "y1"))


def touched(leaves: DataFrame, queries: DataFrame, value: str = "ncount", strategy: str = "auto", tile: int = 64) -> DataFrame:
    """(tree_id, workload, qid, value, share) of every leaf and query that overlap.

    'nested' compares all queries, sent to each task, with all leaves; 'tiles' lists both by coarse tiles and joins
    on them, keeping a pair in the tile where its overlap begins; 'auto' counts the queries first.
    """
    leaf, q = _sides(leaves, queries, value)
    if strategy == "auto":
        strategy = "nested" if few(q) else "tiles"
    c = F.col
    meets = (c("lx0") < c("qx1")) & (c("qx0") < c("lx1")) & (c("ly0") < c("qy1")) & (c("qy0") < c("ly1"))
    if strategy == "nested":
        both = leaf.join(F.broadcast(q), meets)
    else:
        here = (c("tx") == F.floor(F.greatest("lx0", "qx0") / tile)) & (c("ty") == F.floor(F.greatest("ly0", "qy0") / tile))
        both = by_tile(leaf, "l", tile).join(by_tile(q, "q", tile), ["tx", "ty"]).where(meets & here)
    return both.select("tree_id", "workload", "qid", "value", (overlap() / F.col("cells")).alias("share"))


def private(leaves: DataFrame, queries: DataFrame, value: str = "ncount", strategy: str = "auto") -> DataFrame:
    """(tree_id, workload, qid, private): each leaf's count spread evenly over its cells."""
    if strategy == "auto":
        strategy = "nested" if few(queries) else "tiles"
    part = touched(leaves, queries, value, strategy).groupBy("tree_id", "workload", "qid").agg(F.sum(F.col("value") * F.col("share")).alias("private"))
    every = leaves.select("tree_id").distinct().join(F.broadcast(queries.select("workload", "qid")) if strategy == "nested" else queries.select("workload", "qid"))
    return every.join(part, ["tree_id", "workload", "qid"], "left").select("tree_id", "workload", "qid", F.coalesce("private", F.lit(0.0)).alias("private"))


def exact(fm: DataFrame, queries: DataFrame, tile: int = 64) -> DataFrame:
    """(workload, qid, exact) by a range join of queries and cells: few queries are sent to all tasks, many are listed by tile."""
    c = F.col
    inside = (c("cx") >= c("x0")) & (c("cx") < c("x1")) & (c("cy") >= c("y0")) & (c("cy") < c("y1"))
    cells = fm.select("cx", "cy", "cnt")
    if few(queries):
        both = cells.join(F.broadcast(queries), inside)
    else:
        cells = cells.withColumn("tx", F.floor(c("cx") / tile)).withColumn("ty", F.floor(c("cy") / tile))
        both = cells.join(by_tile(queries, "", tile), ["tx", "ty"]).where(inside)
    hit = both.groupBy("workload", "qid").agg(F.sum("cnt").alias("exact"))
    return queries.select("workload", "qid").join(hit, ["workload", "qid"], "left").select("workload", "qid", F.coalesce("exact", F.lit(0)).alias("exact"))


def exact_prefix(fm: DataFrame, spec: GridSpec, queries: DataFrame, value: str = "cnt", out: str = "exact") -> DataFrame:
    """The same by four look-ups for each query in the prefix sums of the matrix."""
    p = prefix_sums(fm, spec, value)
    c = F.col
    corners = F.array(*(F.struct(a.alias("cx"), b.alias("cy"), F.lit(s).alias("sign")) for a, b, s in ((c("x1") - 1, c("y1") - 1, 1), (c("x0") - 1, c("y1") - 1, -1), (c("x1") - 1, c("y0") - 1, -1), (c("x0") - 1, c("y0") - 1, 1))))
    q = queries.select("workload", "qid", F.explode(corners).alias("p")).select("workload", "qid", "p.cx", "p.cy", "p.sign")
    return q.join(p, ["cx", "cy"], "left").groupBy("workload", "qid").agg(F.sum(F.col("sign") * F.coalesce("total", F.lit(0))).alias(out))


def from_tree(nodes: DataFrame, queries: DataFrame, height: int, tile: int = 64) -> DataFrame:
    """(tree_id, workload, qid, private) with inner counts: the largest nodes inside the query, and leaves at its border.

    Few queries are sent to all tasks; many meet the nodes by tile, a pair in the tile where its overlap begins.
    """
    c = F.col
    n = nodes.select("tree_id", "node_id", "height", "split_at", *(c(x).alias("l" + x) for x in ("x0", "x1", "y0", "y1")), "ncount")
    q = queries.select("workload", "qid", *(c(x).alias("q" + x) for x in ("x0", "x1", "y0", "y1")))
    meets = (c("lx0") < c("qx1")) & (c("qx0") < c("lx1")) & (c("ly0") < c("qy1")) & (c("qy0") < c("ly1"))
    inside = (c("lx0") >= c("qx0")) & (c("lx1") <= c("qx1")) & (c("ly0") >= c("qy0")) & (c("ly1") <= c("qy1"))
    if few(q):
        both = n.join(F.broadcast(q), meets)
    else:
        here = (c("tx") == F.floor(F.greatest("lx0", "qx0") / tile)) & (c("ty") == F.floor(F.greatest("ly0", "qy0") / tile))
        both = by_tile(n, "l", tile).join(by_tile(q, "q", tile), ["tx", "ty"]).where(meets & here).drop("tx", "ty")
    both = both.withColumn("inside", inside)
    full = both.where("inside").select("tree_id", "workload", "qid", c("node_id").alias("above"))
    up = both.where(c("height") < height).withColumn("above", F.explode(F.sequence(F.lit(1), F.lit(height) - c("height")))).withColumn("above", F.expr("shiftright(node_id, cast(above as int))"))
    covered = up.join(full, ["tree_id", "workload", "qid", "above"], "left_semi").select("tree_id", "workload", "qid", "node_id").distinct()
    used = both.where(c("inside") | c("split_at").isNull()).join(covered, ["tree_id", "workload", "qid", "node_id"], "left_anti")
    size = (c("lx1") - c("lx0")).cast("long") * (c("ly1") - c("ly0"))
    return used.groupBy("tree_id", "workload", "qid").agg(F.sum(c("ncount") * overlap() / size).alias("private"))

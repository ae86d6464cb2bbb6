"""Split positions of tree nodes, all nodes of a level at once.

Nodes are rows (tree_id, node_id, height, axis, x0, x1, y0, y1), cells rows (tree_id, node_id, cx, cy, cnt). A split
k puts the first k rows of the node's axis on the low side, 1 <= k < extent; k = extent means no split.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from geohist.functions import noise

KEY = ["tree_id", "node_id"]


def extent() -> Column:
    """Rows of a node along its axis."""
    return F.when(F.col("axis") == 0, F.col("x1") - F.col("x0")).otherwise(F.col("y1") - F.col("y0"))


def across() -> Column:
    """Cells in one row of a node's axis."""
    return F.when(F.col("axis") == 0, F.col("y1") - F.col("y0")).otherwise(F.col("x1") - F.col("x0"))


def profile(cells: DataFrame, nodes: DataFrame) -> DataFrame:
    """(tree_id, node_id, pos, cnt, many): how many cells of each count stand in each row of the node's axis; pos from 1."""
    at = F.when(F.col("axis") == 0, F.col("cx") - F.col("x0")).otherwise(F.col("cy") - F.col("y0")) + 1
    joined = cells.join(nodes.select(*KEY, "axis", "x0", "y0"), KEY)
    return joined.groupBy(*KEY, at.alias("pos"), "cnt").agg(F.count(F.lit(1)).alias("many"))


def every_position(allow_no_split: bool = False) -> Column:
    """All positions of a node, as an array."""
    last = extent() if allow_no_split else extent() - 1
    return F.when(last >= 1, F.sequence(F.lit(1), last)).otherwise(F.array().cast("array<int>"))


def lattice_column(u: Column, rounds: int) -> Column:
    """Positions that a search of `rounds` rounds over 1..u can meet, as an array: midpoints of gaps, refined once a round."""

    def finer(known: Column, _) -> Column:
        gaps = F.size(known) - 1
        middles = F.zip_with(F.slice(known, F.lit(1), gaps), F.slice(known, F.lit(2), gaps), lambda a, b: a + F.shiftright(b - a, 1))
        return F.array_sort(F.array_union(known, middles))

    met = F.aggregate(F.sequence(F.lit(0), F.lit(rounds)), F.array(F.lit(1), u.cast("int")), finer)
    return F.filter(met, lambda k: k < u)


def lattice_positions(nodes: DataFrame, rounds: int) -> DataFrame:
    return nodes.where(extent() > 1).select(*KEY, F.explode(lattice_column(extent(), rounds)).alias("k"))


def unevenness(prof: DataFrame, nodes: DataFrame, positions: Column) -> DataFrame:
    """(key..., k, u, o): sum over both sides of the distance of each cell's count to its side's mean, for an ascending array of positions of each node
    of u rows.

    Positions cut a node's rows into strips. Cells of one count in one strip are one row, made by partial sums in each task,
    so that even the root, a single key, is summed up before any shuffle. Running sums over the strips of each
    count give the cells below every position; a position meets each distinct count once, never a cell. Empty cells
    are not in the profile; they add their number times the mean.
    """
    at = nodes.select(*KEY, extent().alias("u"), across().alias("v"), positions.alias("ks")).where(F.size("ks") > 0)
    last = F.size("ks")
    dense = F.col("ks")[0] + last - 1 == F.element_at("ks", -1)  # every position from the first on: no search needed
    strip = F.when(dense, F.greatest(F.lit(1), F.least(F.col("pos") - F.col("ks")[0] + 1, last + 1))).otherwise(F.size(F.filter("ks", lambda k: k < F.col("pos"))) + 1)
    # A row that counts no cell stands for each node, so that empty nodes have their positions too.
    prof = prof.select(*KEY, "pos", "cnt", "many").unionByName(at.select(*KEY, F.lit(1).alias("pos"), F.lit(0).cast("long").alias("cnt"), F.lit(0).cast("long").alias("many")))
    strips = prof.join(at, KEY).groupBy(*KEY, strip.cast("int").alias("strip"), "cnt").agg(F.sum("many").alias("many"), F.first(last).alias("last"))
    same = W.partitionBy(*KEY, "cnt")
    run = strips.withColumn("low", F.sum("many").over(same.orderBy("strip"))).withColumn("every", F.sum("many").over(same))
    run = run.withColumn("next", F.lead("strip").over(same.orderBy("strip"))).withColumn("lead", F.lag("strip").over(same.orderBy("strip")).isNull())
    piece = lambda begin, end, low: F.struct(begin.alias("begin"), F.least(end, F.col("last")).alias("end"), low.alias("low"))
    none = F.lit(0).cast("long")
    pieces = F.array(piece(F.col("strip"), F.coalesce(F.col("next") - 1, F.col("last")), F.col("low")), piece(F.lit(1), F.when(F.col("lead"), F.col("strip") - 1).otherwise(F.lit(0)), none))
    each = run.select(*KEY, "cnt", "every", F.explode(F.filter(pieces, lambda p: p["begin"] <= p["end"])).alias("p"))
    each = each.select(*KEY, F.explode(F.sequence("p.begin", "p.end")).alias("i"), "cnt", F.col("p.low").alias("low"), (F.col("every") - F.col("p.low")).alias("high"))
    each = each.join(at, KEY).withColumn("k", F.element_at("ks", F.col("i"))).drop("ks", "i")
    whole = W.partitionBy(*KEY, "k")
    a, b = F.col("k") * F.col("v"), (F.col("u") - F.col("k")) * F.col("v")
    each = each.withColumn("mean_low", F.sum(F.col("cnt") * F.col("low")).over(whole) / a).withColumn("mean_high", F.when(b > 0, F.sum(F.col("cnt") * F.col("high")).over(whole) / b).otherwise(F.lit(0.0)))
    off = F.col("low") * F.abs(F.col("cnt") - F.col("mean_low")) + F.col("high") * F.abs(F.col("cnt") - F.col("mean_high"))
    found = each.groupBy(*KEY, "k").agg(F.sum(off).alias("off"), F.sum("low").alias("full_low"), F.sum("high").alias("full_high"), *(F.first(x).alias(x) for x in ("u", "v", "mean_low", "mean_high")))
    empty = (a - F.col("full_low")) * F.col("mean_low") + (b - F.col("full_high")) * F.col("mean_high")
    return found.select(*KEY, "k", "u", (F.col("off") + empty).alias("o"))


def _smallest(scored: DataFrame, by: str) -> DataFrame:
    """The position of smallest value of each node, the lowest position among ties."""
    return scored.groupBy(*KEY).agg(F.min(F.struct(by, "k")).alias("m"), F.count(F.lit(1)).alias("evals")).select(*KEY, F.col("m.k").alias("k"), F.col("m")[by].alias("value"), "evals")


def exact(prof, nodes, allow_no_split: bool = False, **_) -> DataFrame:
    """Best split without noise."""
    return _smallest(unevenness(prof, nodes, every_position(allow_no_split)), "o")


def exhaustive(prof, nodes, eps_level, secret: str, allow_no_split: bool = False, **_) -> DataFrame:
    """Noise on every position: the level's budget is divided by their number."""
    o = unevenness(prof, nodes, every_position(allow_no_split))
    tried = F.col("u") if allow_no_split else F.col("u") - 1
    o = o.withColumn("noisy", noise.laplace(F.col("o"), noise.UNEVENNESS * tried / F.lit(eps_level), secret, F.col("tree_id"), "split", F.col("node_id"), F.col("k")))
    return _smallest(o, "noisy")


def searched(prof, nodes, eps_level, secret: str, rounds: int = 3, **_) -> DataFrame:
    """Noise on at most 2 * rounds + 1 positions, found by halving towards the smaller side.

    Exact values of the whole lattice come from one pass; the walk reads noisy values of the positions it visits only.
    """
    o = unevenness(prof, nodes, F.when(extent() > 1, lattice_column(extent(), rounds)))
    scale = noise.UNEVENNESS * (2 * rounds + 1) / eps_level if eps_level else 0.0
    o = o.withColumn("noisy", noise.laplace(F.col("o"), scale, secret, F.col("tree_id"), "split", F.col("node_id"), F.col("k")) if scale else F.col("o"))
    s = o.groupBy(*KEY).agg(F.map_from_entries(F.collect_list(F.struct("k", "noisy"))).alias("at"), F.first("u").alias("u"))
    value = lambda k: F.element_at(F.col("at"), k)
    middle = lambda a, b: a + F.shiftright(b - a, 1)

    def state(l: Column, r: Column, k: Column, seen: Column) -> Column:
        return F.struct(l.cast("int").alias("l"), r.cast("int").alias("r"), k.cast("int").alias("k"), seen.alias("seen"))

    def step(now: Column, _) -> Column:
        l, r, k = now["l"], now["r"], now["k"]
        a, b = middle(l, k), middle(k, r)
        stay, down = (value(k) <= value(a)) & (value(k) <= value(b)), value(a) <= value(b)
        seen = F.array_union(now["seen"], F.array(a, b))
        return F.when(stay, state(a, b, k, seen)).when(down, state(l, k, a, seen)).otherwise(state(k, r, b, seen))

    one = F.lit(1)
    first = middle(one, F.col("u"))
    end = F.aggregate(F.sequence(one, F.lit(rounds)) if rounds else F.array().cast("array<int>"), state(one, F.col("u"), first, F.array(first.cast("int"))), step)
    return s.select(*KEY, end.alias("end"), "at").select(*KEY, F.col("end.k").alias("k"), value(F.col("end.k")).alias("value"), F.size("end.seen").cast("long").alias("evals"))


def exponential_unevenness(prof, nodes, eps_level, secret: str, **_) -> DataFrame:
    """Exponential mechanism over all positions, utility minus unevenness."""
    o = unevenness(prof, nodes, every_position())
    o = o.withColumn("score", -noise.exponential_score(-F.col("o"), eps_level, noise.UNEVENNESS, secret, F.col("tree_id"), "rank", F.col("node_id"), F.col("k")))
    return _smallest(o, "score")


def _ranks(prof: DataFrame, nodes: DataFrame) -> DataFrame:
    """(key..., k, low, total): records on the low side of every position."""
    rows = prof.groupBy(*KEY, "pos").agg(F.sum(F.col("cnt") * F.col("many")).alias("n"))
    every = nodes.where(extent() > 1).select(*KEY, F.explode(F.sequence(F.lit(1), extent())).alias("pos"))
    dense = every.join(rows, [*KEY, "pos"], "left").withColumn("n", F.coalesce("n", F.lit(0)))
    run = W.partitionBy(*KEY).orderBy("pos").rowsBetween(W.unboundedPreceding, W.currentRow)
    out = dense.withColumn("low", F.sum("n").over(run)).withColumn("total", F.sum("n").over(W.partitionBy(*KEY)))
    return out.select(*KEY, F.col("pos").alias("k"), "low", "total")


def em_median(prof, nodes, eps_level, secret: str, **_) -> DataFrame:
    """Exponential mechanism for the median: utility minus the difference of both sides' records."""
    r = _ranks(prof, nodes).join(nodes.select(*KEY, extent().alias("u")), KEY).where("k < u")
    r = r.withColumn("score", -noise.exponential_score(-F.abs(2 * F.col("low") - F.col("total")), eps_level, noise.RANK, secret, F.col("tree_id"), "rank", F.col("node_id"), F.col("k")))
    return _smallest(r, "score")


def noisy_mean(prof, nodes, eps_level, secret: str, **_) -> DataFrame:
    """Noisy sum of positions over noisy count, half the budget each; held inside the node."""
    m = nodes.where(extent() > 1).select(*KEY, extent().alias("u")).join(prof.groupBy(*KEY).agg(F.sum(F.col("cnt") * F.col("many")).alias("n"), F.sum(F.col("pos") * F.col("cnt") * F.col("many")).alias("s")), KEY, "left").na.fill(0, ["n", "s"])
    s = noise.laplace(F.col("s"), F.col("u") * 2 / F.lit(float(eps_level)), secret, F.col("tree_id"), "mean", F.col("node_id"), "sum")
    n = noise.laplace(F.col("n"), 2 / float(eps_level), secret, F.col("tree_id"), "mean", F.col("node_id"), "count")
    k = F.greatest(F.lit(1), F.least(F.col("u") - 1, F.round(s / F.greatest(n, F.lit(1.0))).cast("int")))
    return m.select(*KEY, k.alias("k"), F.lit(0.0).alias("value"), F.lit(2).cast("long").alias("evals"))


def midpoint(prof, nodes, **_) -> DataFrame:
    """Halves of the extent; reads no data."""
    return nodes.where(extent() > 1).select(*KEY, (1 + F.floor((extent() - 1) / 2)).cast("int").alias("k"), F.lit(0.0).alias("value"), F.lit(0).cast("long").alias("evals"))


def sides(prof: DataFrame, chosen: DataFrame) -> DataFrame:
    """(key..., k, low, high): records on both sides of each node's position, nodes without records too."""
    n = F.col("cnt") * F.col("many")
    part = lambda test: F.coalesce(F.sum(F.when(test, n)), F.lit(0)).cast("long")
    both = chosen.select(*KEY, "k").join(prof, KEY, "left")
    return both.groupBy(*KEY, "k").agg(part(F.col("pos") <= F.col("k")).alias("low"), part(F.col("pos") > F.col("k")).alias("high"))


METHODS = {f.__name__: f for f in (exact, exhaustive, searched, exponential_unevenness, em_median, noisy_mean, midpoint)}

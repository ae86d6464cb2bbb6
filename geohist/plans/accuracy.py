"""Error of every method on one workload, releases in level mode, the whole pipeline with its height estimated, and rarer options, with their SQL."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from geohist.functions import budget
from geohist.operators import kd, measures, quad, release, tree, wavelet, workload
from geohist.plans import edt, oracle
from geohist.plans import registry as base

_ALL: dict[str, tuple] = {}
SECRET, H, EPS, EPS_LEVEL, EPS_DATA, STOP, N = base.SECRET, base.H, base.EPS, base.EPS_LEVEL, base.EPS_DATA, base.STOP, base.N


def add(name: str, sql: str | None = None):
    def keep(f):
        _ALL[name] = (f, sql)
        return f

    return keep


# Mean relative error of each method's release, over the same rectangles
_MRE = base._mre_sql(oracle.private_answers(oracle.random_rects(N)))


def _error_of(spark, d, leaves: DataFrame) -> DataFrame:
    return base._mre(spark, d, tree.stored(leaves.withColumn("tree_id", F.lit("t"))))


def _released(name: str):
    made, sql = base._ALL[name]
    add(f"mre_{name}", f"WITH leaf AS MATERIALIZED (SELECT * FROM ({sql})) {_MRE}")(lambda spark, d: _error_of(spark, d, made(spark, d)))


for _n in ("singular_p1", "uniform_total_p1", "ag_p1", "kd_geo_p1", "kd_uniform_p1", "quad_geo_p1", "quad_uniform_p1", *(f"edt_release_{v}_p1" for v in ("exhaustive", "exponential", "median", "midpoint"))):
    _released(_n)
add("mre_wavelet_p1", f"WITH leaf AS MATERIALIZED (SELECT cx AS x0, cx + 1 AS x1, cy AS y0, cy + 1 AS y1, value AS ncount FROM ({base._ALL['wavelet_cells_p1'][1]})) {_MRE}")(
    lambda spark, d: _error_of(spark, d, base.r6(wavelet.publish(base.fm(spark, d), base.spec(), EPS, SECRET).drop("tree_id"), "ncount"))
)

# Releases whose trees are built level by level
for _v, _m in (("exhaustive", "exhaustive"), ("exponential", "exponential_unevenness"), ("median", "em_median")):
    add(f"edt_release_{_v}_levelwise_p3", base._pruned_sql("p3", method=_m))(lambda spark, d, v=_v: base._leaf(base._edt(spark, d, "p3", variant=v, mode="levelwise").published))
add("kd_geo_levelwise_p1", base._ALL["kd_geo_p1"][1])(
    lambda spark, d: base._leaf(kd.publish(tree.stored(base.fm(spark, d)), base.spec(), EPS, H, "geo", secret=SECRET, mode="levelwise", step=tree.stored))
)

# The whole pipeline: height from a noisy count, splits and counts from what is left of one budget
WHOLE = budget.Budget(0.1, 0.01, 0.004)
HEIGHTS = range(2, 10)


def _whole_sql() -> str:
    parts = []
    for h in HEIGHTS:
        t = oracle.Tree("p1", h, "searched", WHOLE.per_level, "edt")
        t.pruned(WHOLE.eps_tot - WHOLE.eps_height - h * WHOLE.per_level, 10.0, 5)
        parts.append(f"SELECT {h} AS h, * FROM ({t.sql(oracle.Tree.LEAF)})")
    rule = f"least(12, greatest(0, floor(log2(greatest(1, {oracle.lap('n', repr(1 / WHOLE.eps_height), oracle.q('edt'), oracle.q('height'))}) * {WHOLE.eps_tot} / 10))))"
    return f"WITH e AS MATERIALIZED (SELECT cast({rule} AS INTEGER) AS h FROM (SELECT count(*) AS n FROM events)) " + " UNION ALL ".join(f"SELECT p.h AS height, p.* EXCLUDE (h) FROM ({p}) p SEMI JOIN e ON e.h = p.h" for p in parts)


def _whole(spark, d) -> edt.Release:
    return edt.publish_matrix(tree.stored(base.fm(spark, d)), base.spec(), WHOLE, edt.TreePlan(secret=SECRET), replace(STOP, min_count=10.0))


@add("edt_whole_p1", _whole_sql())
def _(spark, d):
    rel = _whole(spark, d)
    return base._leaf(rel.published).withColumn("height", F.lit(rel.height))


@add("edt_whole_ledger_p1", f"SELECT 'edt' AS tree_id, cast({WHOLE.eps_tot} AS DOUBLE) AS eps")
def _(spark, d):
    led = _whole(spark, d).ledger
    return base.r6(budget.Ledger.summary(led.frame(spark)).groupBy("tree_id").agg(F.sum("eps").alias("eps")), "eps")


# Both draws of a path's last node combined
def _combined_sql() -> str:
    t = oracle.Tree("p1", H, "searched", EPS_LEVEL, "edt")
    t.pruned(EPS_DATA, 100.0, 5)
    parts = oracle.levels(EPS_DATA, H)
    rows = ["SELECT node AS leaf_id, round(ncount, 6) AS ncount FROM leaf WHERE height = 0"]
    for h in range(1, H + 1):
        own, left = parts[h] ** 2, oracle.remaining(parts, h) ** 2
        rows.append(f"SELECT l.node, round((l.ncount * {left!r} + a.draw * {own!r}) / {left + own!r}, 6) FROM leaf l JOIN a{h} a ON a.node = l.node WHERE l.height = {h}")
    return t.sql(" UNION ALL ".join(rows))


@add("edt_release_combined_p1", _combined_sql())
def _(spark, d):
    nodes = base._edt(spark, d, mode="subtree").nodes
    return base._leaf(release.redact(release.pruned(nodes, H, EPS_DATA, STOP, secret=SECRET, combine=True))).select("leaf_id", "ncount")


# Budgets that grow by the cube root of four a level, for fanout 4
add("quad_growth4_p1", base._quad_ctes(3, "geo", 4.0) + " SELECT node AS leaf_id, round(y, 6) AS ncount FROM n0")(
    lambda spark, d: base._leaf(quad.publish(base.fm(spark, d), base.spec(), 3, EPS, growth=4.0, smoothing=False, secret=SECRET)).select("leaf_id", "ncount")
)


# How many noisy values a split costs
def _evaluations_sql(rounds: int = 3) -> str:
    t = oracle.Tree("p1", H, "searched", EPS_LEVEL, "edt", rounds=rounds)
    seen = []
    for h in range(H, 0, -1):
        at = [f"SELECT node, k AS p FROM s_{h}_0"]
        for i in range(rounds):
            at += [f"SELECT node, l + (k - l) // 2 FROM s_{h}_{i}", f"SELECT node, k + (r - k) // 2 FROM s_{h}_{i}"]
        seen.append(f"SELECT node, count(DISTINCT p) AS e FROM ({' UNION ALL '.join(at)}) GROUP BY 1")
    return t.sql(f"SELECT 'edt' AS tree_id, cast(sum(e) AS BIGINT) AS evals, count(*) AS splits, cast(max(e) AS BIGINT) AS most FROM ({' UNION ALL '.join(seen)})")


def _positions_sql() -> str:
    t = oracle.Tree("p1", H, "exhaustive", EPS_LEVEL, "edt")
    every = " UNION ALL ".join(f"SELECT node, count(*) AS e FROM k_{h} GROUP BY 1" for h in range(H, 0, -1))
    return t.sql(f"SELECT 'edt' AS tree_id, cast(sum(e) AS BIGINT) AS evals, count(*) AS splits, cast(max(e) AS BIGINT) AS most FROM ({every})")


add("evaluations_edt", _evaluations_sql())(lambda spark, d: measures.evaluations(base._edt(spark, d, mode="subtree").nodes))
add("evaluations_exhaustive", _positions_sql())(lambda spark, d: measures.evaluations(base._edt(spark, d, variant="exhaustive", mode="subtree").nodes))


# Share of the densest true cells' regions that a release names
_TRUE = f"(SELECT cx // 8 AS gx, cy // 8 AS gy, sum(cnt) AS n FROM ({oracle.matrix('p1')}) GROUP BY 1, 2 ORDER BY 3 DESC, 1, 2 LIMIT 5)"
_CENTRE = "(SELECT (x0 + x1) // 16 AS gx, (y0 + y1) // 16 AS gy FROM leaf ORDER BY round(ncount / ((x1 - x0) * (y1 - y0)), 6) DESC, node LIMIT 5)"


@add("hotspots_precision", base._pruned_sql(final=f"SELECT count(*) AS found, round(count(*) / 5.0, 6) AS share FROM {_TRUE} t WHERE EXISTS (SELECT 1 FROM {_CENTRE} c WHERE c.gx = t.gx AND c.gy = t.gy)"))
def _(spark, d):
    """Of the five densest 8 by 8 blocks, how many hold the centre of one of the five densest published regions."""
    blocks = base.fm(spark, d).groupBy(F.expr("cx div 8").alias("gx"), F.expr("cy div 8").alias("gy")).agg(F.sum("cnt").alias("n"))
    true = blocks.orderBy(F.desc("n"), "gx", "gy").limit(5)
    top = tree.stored(base._edt(spark, d, mode="subtree").published).withColumn("density", F.round(F.col("ncount") / F.col("cells"), 6)).orderBy(F.desc("density"), "leaf_id").limit(5)
    centre = top.select(F.expr("(x0 + x1) div 16").alias("gx"), F.expr("(y0 + y1) div 16").alias("gy")).distinct()
    return true.join(centre, ["gx", "gy"], "left_semi").agg(F.count(F.lit(1)).alias("found")).select("found", F.round(F.col("found") / 5.0, 6).alias("share"))


_BLOCKS = "SELECT gx * 8 AS bx, gy * 8 AS y_from, cnt FROM (" + oracle.grid_blocks("p1", 8) + ") WHERE cnt > 0"


@add("overlap_join", f"SELECT workload, qid, count(*) AS blocks, cast(sum(cnt) AS BIGINT) AS records FROM ({oracle.random_rects(N)}) r JOIN ({_BLOCKS}) g ON x0 < bx + 8 AND bx < x1 AND y0 < y_from + 8 AND y_from < y1 GROUP BY 1, 2")
def _(spark, d):
    """How many 8 by 8 blocks that hold events each rectangle touches, and the events in them."""
    gx, gy = F.col("gx"), F.col("gy")
    held = base.grid.coarser(base.fm(spark, d), base.spec(), 8, 8).select(
        F.lit("g").alias("tree_id"), *((g * 8 + o).alias(c) for c, g, o in (("x0", gx, 0), ("x1", gx, 8), ("y0", gy, 0), ("y1", gy, 8))), F.lit(64).alias("cells"), F.col("cnt").alias("ncount")
    )
    pairs = base.answer.touched(held, workload.random_rects(spark, base.spec(), N), strategy="tiles")
    return pairs.groupBy("workload", "qid").agg(F.count(F.lit(1)).alias("blocks"), F.sum("value").alias("records"))


# Generated sets: a point for each event around one centre, their matrix replayed draw by draw
def _gaussian_sql(sigma: float, seed: str) -> str:
    key = lambda *k: oracle.u(*k, secret=seed)
    s = oracle.q(str(sigma))
    radius, angle = f"sqrt(-2 * ln({key(oracle.q('point'), s, 'event_id', oracle.q('r'))}))", f"2 * pi() * {key(oracle.q('point'), s, 'event_id', oracle.q('a'))}"
    at = {c: f"{key(oracle.q('centre'), s, oracle.q(c))} * 1024 + {radius} * {f}({angle}) * {sigma}" for c, f in (("x", "cos"), ("y", "sin"))}
    cells = ", ".join(f"{oracle.index(at[c], 0.0, 1024.0, oracle.SIDE)} AS c{c}" for c in "xy")
    return f"SELECT cx, cy, count(*) AS cnt FROM (SELECT {cells} FROM events) GROUP BY 1, 2"


def _gaussian(spark, d, sigma: float) -> DataFrame:
    ids = base.src.table(spark, d, "events").select(F.col("event_id").alias("id"))
    return base.grid.frequency_matrix(base.src.gaussian(spark, None, sigma, "centre-a", ids), base.src.grid_of("g", base.SIDE))


for _g in (20.0, 50.0, 100.0):
    add(f"gaussian_points_{_g:g}", _gaussian_sql(_g, "centre-a"))(lambda spark, d, g=_g: _gaussian(spark, d, g))


def queries():
    return {k: f for k, (f, _) in _ALL.items()}


def oracle_sql():
    return {k: s for k, (_, s) in _ALL.items() if s}

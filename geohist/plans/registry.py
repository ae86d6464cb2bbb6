"""Names of all queries of the histogram engine, with their SQL.

Registered releases use the published test key, a 64 by 64 grid and heights that SQL can unroll, so that DuckDB replays
every draw; experiments (plans/experiments.py) and bench.py use the full grid.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from geohist.functions import budget, noise
from geohist.operators import answer, grid, grids, kd, measures, quad, release, split, tree, wavelet, workload
from geohist.plans import edt, oracle
from geohist.sources import points as src

_ALL: dict[str, tuple[Callable, str | None]] = {}
SIDE, SECRET, H = oracle.SIDE, noise.TEST_SECRET, 4
#: Budgets of the registered releases: the count of events at the small scale times 1.0 lies where the engine is meant to work.
EPS, EPS_LEVEL = 1.0, 0.05
EPS_DATA = EPS - H * EPS_LEVEL
STOP = release.StopRule(100.0, 5)
N = 200
#: Added before rounding where exact values are binary fractions, so that both engines round the same way.
TILT = 1.234e-7


def add(name: str, sql: str | None = None):
    def keep(f: Callable) -> Callable:
        _ALL[name] = (f, sql)
        return f

    return keep


def fm(spark: SparkSession, d: str, s: str = "p1") -> DataFrame:
    return grid.frequency_matrix(src.points(spark, d, s), spec(s))


def spec(s: str = "p1", side: int = SIDE) -> grid.GridSpec:
    return src.grid_of(s, side)


def r6(df: DataFrame, *columns: str) -> DataFrame:
    return df.withColumns({c: F.round(c, 6) for c in columns})


# Foundations ---------------------------------------------------------------------------------------------------------
for _s in src.SETS:
    add(f"points_{_s}", f"SELECT count(*) AS n, count(px) AS nx, round(min(px), 6) AS x_min, round(max(px), 6) AS x_max, round(min(py), 6) AS y_min, round(max(py), 6) AS y_max FROM ({oracle.points(_s)})")(
        lambda spark, d, s=_s: src.points(spark, d, s).agg(F.count(F.lit(1)).alias("n"), F.count("px").alias("nx"), *(F.round(f(c), 6).alias(f"{c[1]}_{k}") for c in ("px", "py") for k, f in (("min", F.min), ("max", F.max))))
    )
    add(f"freq_matrix_{_s}", oracle.matrix(_s))(lambda spark, d, s=_s: fm(spark, d, s))

add("densify_p1", oracle.dense("p1"))(lambda spark, d: grid.densify(fm(spark, d), spec()))
add("prefix_sums_p1", f"WITH d AS MATERIALIZED ({oracle.dense('p1')}) SELECT a.cx, a.cy, cast(sum(b.cnt) AS BIGINT) AS total FROM d a JOIN d b ON b.cx <= a.cx AND b.cy <= a.cy GROUP BY 1, 2")(lambda spark, d: grid.prefix_sums(fm(spark, d), spec()))
add("coarser_p1", "SELECT cast(gx AS INTEGER) AS gx, cast(gy AS INTEGER) AS gy, cast(cnt AS BIGINT) AS cnt FROM (" + oracle.grid_blocks("p1", 10) + ") WHERE cnt > 0")(lambda spark, d: grid.coarser(fm(spark, d), spec(), 10, 10))


@add("keyed_uniform", f"SELECT event_id, round({oracle.u(oracle.q('demo'), 'event_id')}, 9) AS u FROM events")
def _(spark, d):
    return src.table(spark, d, "events").select("event_id", F.round(noise.keyed_uniform(SECRET, "demo", F.col("event_id")), 9).alias("u"))


@add("laplace_counts", f"SELECT cx, cy, round({oracle.lap('cnt', '2.0', oracle.q('demo'), 'cx', 'cy')}, 6) AS noisy FROM ({oracle.matrix('p1')})")
def _(spark, d):
    return fm(spark, d).select("cx", "cy", F.round(noise.laplace(F.col("cnt"), 2.0, SECRET, "demo", F.col("cx"), F.col("cy")), 6).alias("noisy"))


_geo = lambda side: f"floor(ln({oracle.u(oracle.q('geo'), 'cx', 'cy', oracle.q(side))}) / -0.5)"


@add("geometric_counts", f"SELECT cx, cy, cast(cnt + {_geo('up')} - {_geo('down')} AS BIGINT) AS noisy FROM ({oracle.matrix('p1')})")
def _(spark, d):
    return fm(spark, d).select("cx", "cy", noise.two_sided_geometric(F.col("cnt"), 0.5, SECRET, "geo", F.col("cx"), F.col("cy")).cast("long").alias("noisy"))


@add("exponential_choice", f"SELECT cy, arg_max(cx, cnt * 0.2 / 2 + {oracle.gum(oracle.q('em'), 'cx', 'cy')}) AS cx FROM ({oracle.matrix('p1')}) GROUP BY 1")
def _(spark, d):
    return fm(spark, d).groupBy("cy").agg(F.max_by("cx", noise.exponential_score(F.col("cnt"), 0.2, 1.0, SECRET, "em", F.col("cx"), F.col("cy"))).alias("cx"))


# Budgets -------------------------------------------------------------------------------------------------------------
_ROWS = "(SELECT n, cast(least(12, greatest(0, floor(log2(n * 0.1 / 10)))) AS INTEGER) AS h FROM (SELECT count(*) AS n FROM events))"


def _height_rows(spark, d):
    n = src.table(spark, d, "events").agg(F.count(F.lit(1)).alias("n"))
    return n.withColumn("h", F.least(F.lit(12), F.greatest(F.lit(0), F.floor(F.log2(F.col("n") * 0.1 / 10)))).cast("int"))


@add("budget_geometric", f"SELECT h, cast(i AS INTEGER) AS height, round(pow(2, (h - i) / 3.0) * 0.8 / (SELECT sum(pow(2, (h - j) / 3.0)) FROM range(h + 1) t(j)), 9) AS eps FROM {_ROWS}, range(13) r(i) WHERE i <= h")
def _(spark, d):
    i = F.explode(F.sequence(F.lit(0), F.col("h"))).alias("height")
    return _height_rows(spark, d).select("h", i).select("h", "height", F.round(budget.geometric_column(F.lit(0.8), F.col("h"), F.col("height")), 9).alias("eps"))


@add("budget_uniform", f"SELECT h, cast(i AS INTEGER) AS height, round(0.8 / (h + 1), 9) AS eps FROM {_ROWS}, range(13) r(i) WHERE i <= h")
def _(spark, d):
    return _height_rows(spark, d).select("h", F.explode(F.sequence(F.lit(0), F.col("h"))).alias("height")).select("h", "height", F.round(F.lit(0.8) / (F.col("h") + 1), 9).alias("eps"))


@add("budget_remaining", f"SELECT h, cast(i AS INTEGER) AS height, round(coalesce((SELECT sum(pow(2, (h - j) / 3.0)) FROM range(h + 1) t(j) WHERE j < i), 0) * 0.8 / (SELECT sum(pow(2, (h - j) / 3.0)) FROM range(h + 1) t(j)), 9) AS eps FROM {_ROWS}, range(13) r(i) WHERE i <= h")
def _(spark, d):
    return _height_rows(spark, d).select("h", F.explode(F.sequence(F.lit(0), F.col("h"))).alias("height")).select("h", "height", F.round(budget.remaining_column(F.lit(0.8), F.col("h"), F.col("height")), 9).alias("eps"))


@add("path_variance", f"SELECT h, round(sum(pow(2, h - i) / pow(0.8 / (h + 1), 2)), 6) AS variance FROM {_ROWS}, range(13) r(i) WHERE i <= h GROUP BY 1")
def _(spark, d):
    e = F.lit(0.8) / (F.col("h") + 1)
    return _height_rows(spark, d).select("h", F.round(F.aggregate(F.sequence(F.lit(0), F.col("h")), F.lit(0.0), lambda a, i: a + F.pow(F.lit(2.0), F.col("h") - i) / (e * e)), 6).alias("variance"))


@add("height_estimate", f"SELECT cast(least(12, greatest(0, floor(log2(({oracle.lap('n', repr(1 / 0.01), oracle.q('t'), oracle.q('height'))}) * {EPS} / 10)))) AS INTEGER) AS height FROM (SELECT count(*) AS n FROM events)")
def _(spark, d):
    h = tree.noisy_height(fm(spark, d), 0.01, EPS, SECRET, cells=spec().cells)
    return spark.createDataFrame([(h,)], "height int")


@add("ledger_sum", f"SELECT 'edt' AS tree_id, 'data' AS stage, cast({EPS_DATA} AS DOUBLE) AS eps UNION ALL SELECT 'edt', 'split', cast({H * EPS_LEVEL} AS DOUBLE)")
def _(spark, d):
    led = _edt(spark, d).ledger
    return r6(budget.Ledger.summary(led.frame(spark)), "eps")


# Splits of one node --------------------------------------------------------------------------------------------------
def _root(spark, d, s):
    cells = fm(spark, d, s).select(F.lit("t").alias("tree_id"), F.lit(1).cast("long").alias("node_id"), "cx", "cy", "cnt")
    nodes = tree.root(spark, spec(s), H)
    return nodes, split.profile(cells, nodes)


for _s in ("p1", "p3"):
    add(f"unevenness_profile_{_s}", oracle.Tree(_s, H, "searched", EPS_LEVEL, "t").sql(f"SELECT k, round(o + {TILT}, 6) AS o FROM o_{H}"))(
        lambda spark, d, s=_s: split.unevenness(*_root(spark, d, s)[::-1], split.every_position()).select("k", F.round(F.col("o") + TILT, 6).alias("o"))
    )
    for _m, _f in (("exact", "best_split"), ("exhaustive", "exhaustive_split"), ("searched", "searched_split"), ("exponential_unevenness", "em_unevenness"), ("em_median", "em_median")):
        add(f"{_f}_{_s}", oracle.Tree(_s, H, _m, EPS_LEVEL, "t").sql(f"SELECT cast(k AS INTEGER) AS k FROM z_{H}"))(
            lambda spark, d, s=_s, m=_m: split.METHODS[m](*(_root(spark, d, s)[::-1]), eps_level=EPS_LEVEL, secret=SECRET).select("k")
        )
    _side = lambda test, name: f"cast(sum(CASE WHEN {test} THEN cnt ELSE 0 END) AS BIGINT) AS {name}"
    add(f"midpoint_{_s}", oracle.Tree(_s, H, "midpoint", EPS_LEVEL, "t").sql(f"SELECT cast(z.k AS INTEGER) AS k, {_side('pos <= z.k', 'low')}, {_side('pos > z.k', 'high')} FROM z_{H} z JOIN c_{H} c ON c.node = z.node GROUP BY z.k"))(
        lambda spark, d, s=_s: _midpoint(spark, d, s)
    )


def _midpoint(spark, d, s):
    """The middle of the root and the records on both of its sides."""
    nodes, prof = _root(spark, d, s)
    return split.sides(prof, split.midpoint(prof, nodes)).select("k", "low", "high")


@add(
    "noisy_mean_p1",
    f"SELECT cast(greatest(1, least(63, round(({oracle.lap('s', f'{SIDE * 2 / EPS_LEVEL!r}', oracle.q('t'), oracle.q('mean'), '1', oracle.q('sum'))}) / greatest(1.0, {oracle.lap('n', f'{2 / EPS_LEVEL!r}', oracle.q('t'), oracle.q('mean'), '1', oracle.q('count'))})))) AS INTEGER) AS k FROM (SELECT sum(cnt * (cx + 1)) AS s, sum(cnt) AS n FROM ({oracle.matrix('p1')}))",
)
def _(spark, d):
    return split.noisy_mean(*(_root(spark, d, "p1")[::-1]), eps_level=EPS_LEVEL, secret=SECRET).select("k")


def _lattice_sql(rounds: int = 3) -> str:
    t = oracle.Tree("p1", H, "searched", EPS_LEVEL, "edt")
    t.nodes()
    t.cte.append("g0 AS (SELECT node, u, 1 AS a, u AS b FROM (SELECT node, CASE WHEN height % 2 = 0 THEN x1 - x0 ELSE y1 - y0 END AS u FROM nodes WHERE height > 0) WHERE u > 1)")
    for i in range(rounds + 1):
        t.cte.append(f"g{i + 1} AS (SELECT node, u, unnest([a, a + (b - a) // 2]) AS a, unnest([a + (b - a) // 2, b]) AS b FROM g{i})")
    return t.sql(f"SELECT DISTINCT node AS node_id, cast(a AS INTEGER) AS k FROM g{rounds + 1} WHERE a < u")


@add("lattice_positions", _lattice_sql())
def _(spark, d):
    """Positions that the search may meet in every inner node of the events' tree."""
    return split.lattice_positions(_edt(spark, d, mode="subtree").nodes.where("height > 0"), 3).select("node_id", "k")


# Trees and releases --------------------------------------------------------------------------------------------------
def _edt(spark, d, s: str = "p1", variant: str = "searched", stop: release.StopRule = STOP, mode: str = "levelwise", allocation: str = "geo"):
    plan = edt.TreePlan(height=H, mode=mode, allocation=allocation, secret=SECRET)
    return edt.publish_matrix(tree.stored(fm(spark, d, s)), spec(s), budget.Budget(EPS, 0.0, EPS_LEVEL), plan, stop, variant=variant)


def _nodes(df: DataFrame) -> DataFrame:
    return df.select("node_id", "height", "x0", "x1", "y0", "y1", F.coalesce("split_at", F.lit(-1)).alias("split_at"), "cnt")


def _leaf(df: DataFrame) -> DataFrame:
    return r6(df.select("leaf_id", "x0", "x1", "y0", "y1", "cells", "ncount"), "ncount")


def _pruned_sql(s: str = "p1", method: str = "searched", count: float | None = 100.0, cells: int | None = 5, allocation: str = "geo", final: str = oracle.Tree.LEAF) -> str:
    t = oracle.Tree(s, H, method, EPS_LEVEL, "edt")
    t.pruned(EPS_DATA, count, cells, allocation)
    return t.sql(final)


add("edt_tree_h4_p1", oracle.Tree("p1", H, "searched", EPS_LEVEL, "edt").node_sql())(lambda spark, d: _nodes(_edt(spark, d).nodes))
add("edt_tree_subtree_p1", oracle.Tree("p1", H, "searched", EPS_LEVEL, "edt").node_sql())(lambda spark, d: _nodes(_edt(spark, d, mode="subtree").nodes))
add("edt_tree_exact_p3", oracle.Tree("p3", H, "exact", EPS_LEVEL, "t").node_sql())(lambda spark, d: _nodes(tree.build(tree.stored(fm(spark, d, "p3")), spec("p3"), H, "exact", mode="subtree")))
for _v, _m in (("exhaustive", "exhaustive"), ("exponential", "exponential_unevenness"), ("median", "em_median"), ("midpoint", "midpoint")):
    add(f"edt_release_{_v}_p1", _pruned_sql(method=_m))(lambda spark, d, v=_v: _leaf(_edt(spark, d, variant=v, mode="subtree").published))
for _s in ("p1", "p2", "p3", "p6"):
    add(f"edt_release_pruned_{_s}", _pruned_sql(_s))(lambda spark, d, s=_s: _leaf(_edt(spark, d, s, mode="subtree").published))
add("edt_release_uniform_levels_p1", _pruned_sql(allocation="uniform"))(lambda spark, d: _leaf(_edt(spark, d, variant="uniform_levels", mode="subtree").published))
for _c in (10, 50, 100, 500):
    add(f"edt_stop_{_c}", _pruned_sql(count=float(_c)))(lambda spark, d, c=_c: _leaf(_edt(spark, d, stop=release.StopRule(float(c), 5), mode="subtree").published))
add("edt_stop_cells_300", _pruned_sql(count=None, cells=300))(lambda spark, d: _leaf(_edt(spark, d, stop=release.StopRule(None, 300), mode="subtree").published))
add("edt_no_stop", _pruned_sql(count=None, cells=None))(lambda spark, d: _leaf(_edt(spark, d, variant="no_stop", mode="subtree").published))


def _all_sql(kind: str, final: str, share: float = 0.0, allocation: str = "geo", height: int = H, smooth: bool = False, eps_data: float | None = None, tree_id: str = "edt", s: str = "p1") -> str:
    t = oracle.Tree(s, height, kind, share * EPS / height if share else EPS_LEVEL, tree_id)
    t.all_nodes(eps_data if eps_data is not None else (1 - share) * EPS if share else EPS_DATA, allocation)
    if smooth:
        t.smooth()
    return t.sql(final)


add("edt_release_all_p1", _all_sql("searched", "SELECT node AS node_id, round(ncount, 6) AS ncount FROM noisy"))(
    lambda spark, d: r6(release.all_nodes(_edt(spark, d, mode="subtree").nodes, budget.geometric(EPS_DATA, H), SECRET).select("node_id", "ncount"), "ncount")
)


def _leaves_sql() -> str:
    t = oracle.Tree("p1", H, "searched", EPS_LEVEL, "edt")
    t.nodes()
    return t.sql(f"SELECT node AS leaf_id, round({oracle.lap('cnt', repr(1 / EPS_DATA), oracle.q('edt'), oracle.q('final'), 'node')}, 6) AS ncount FROM nodes WHERE split_at IS NULL")


add("edt_release_leaves_p1", _leaves_sql())(lambda spark, d: _leaf(_edt(spark, d, variant="leaves_only", mode="subtree").published).select("leaf_id", "ncount"))
add("path_ledger", _pruned_sql(final=f"SELECT node AS node_id, cast({EPS_DATA} AS DOUBLE) AS spent FROM leaf"))(
    lambda spark, d: r6(release.path_ledger(release.pruned(_edt(spark, d, mode="subtree").nodes, H, EPS_DATA, STOP, secret=SECRET), H, EPS_DATA).select("node_id", "spent"), "spent")
)

# Baselines -----------------------------------------------------------------------------------------------------------
_Q = oracle.q
add("singular_p1", oracle.block_rows(f"SELECT cx AS gx, cy AS gy, {oracle.lap('cnt', repr(1 / EPS), _Q('singular'), _Q('cell'), 'cx', 'cy')} AS ncount FROM ({oracle.dense('p1')})", SIDE, f"gx * {SIDE} + gy"))(
    lambda spark, d: _leaf(grids.singular(fm(spark, d), spec(), EPS, SECRET))
)
add("uniform_total_p1", oracle.block_rows(f"SELECT 0 AS gx, 0 AS gy, {oracle.lap('n', repr(1 / EPS), _Q('uniform'), _Q('total'))} AS ncount FROM (SELECT sum(cnt) AS n FROM ({oracle.matrix('p1')}))", 1, "1"))(
    lambda spark, d: _leaf(grids.total_uniform(fm(spark, d), spec(), EPS, SECRET))
)
add("ug_p1", oracle.block_rows(f"SELECT gx, gy, {oracle.lap('cnt', repr(1 / (EPS - 1e-4)), _Q('ug'), _Q('cell'), 'gx', 'gy')} AS ncount FROM ({oracle.grid_blocks('p1', 20)})", 20, "gx * 20 + gy"))(
    lambda spark, d: _leaf(grids.uniform_grid(fm(spark, d), spec(), EPS, secret=SECRET, side=20))
)
add("ug_side", f"SELECT cast(greatest(1, round(sqrt(greatest(0, {oracle.lap('n', repr(1 / 0.01), _Q('ug'), _Q('total'))}) * {EPS} / 10))) AS INTEGER) AS side FROM (SELECT count(*) AS n FROM events)")(
    lambda spark, d: spark.createDataFrame([(grids.grid_side(grids.noisy_total(fm(spark, d), 0.01, SECRET, "ug"), EPS),)], "side int")
)


def _ag_sql(m: int = 10, n: int = SIDE) -> str:
    e = 0.5 * (EPS - 1e-4)
    a, b = oracle.blocks(m, n)
    t = lambda x, g: x.replace("$", g)
    return f"""WITH d AS MATERIALIZED ({oracle.dense('p1')}),
f AS MATERIALIZED (SELECT gx, gy, {oracle.lap('cnt', repr(1 / e), _Q('ag'), _Q('coarse'), 'gx', 'gy')} AS n1, {t(a, 'gx')} AS bx0, {t(b, 'gx')} AS bx1, {t(a, 'gy')} AS by0, {t(b, 'gy')} AS by1 FROM (SELECT cx * {m} // {n} AS gx, cy * {m} // {n} AS gy, sum(cnt) AS cnt FROM d GROUP BY 1, 2)),
w AS MATERIALIZED (SELECT *, greatest(1, least(cast(ceil(sqrt(greatest(n1, 0) * {e!r} / 5)) AS INTEGER), bx1 - bx0, by1 - by0)) AS m2 FROM f),
s AS MATERIALIZED (SELECT *, {oracle.lap('cnt', repr(1 / e), _Q('ag'), _Q('fine'), 'gx', 'gy', 'i', 'j')} AS n2 FROM (SELECT w.gx, w.gy, any_value(n1) AS n1, any_value(bx0) AS bx0, any_value(bx1) AS bx1, any_value(by0) AS by0, any_value(by1) AS by1, any_value(m2) AS m2, (cx - bx0) * m2 // (bx1 - bx0) AS i, (cy - by0) * m2 // (by1 - by0) AS j, sum(cnt) AS cnt FROM w JOIN d ON cx >= bx0 AND cx < bx1 AND cy >= by0 AND cy < by1 GROUP BY w.gx, w.gy, i, j)),
t AS (SELECT *, sum(n2) OVER (PARTITION BY gx, gy) AS s2, count(*) OVER (PARTITION BY gx, gy) AS c FROM s),
v AS (SELECT *, n2 + ((n1 / {2 / e**2!r} + s2 / (c * {2 / e**2!r})) / (1 / {2 / e**2!r} + 1 / (c * {2 / e**2!r})) - s2) / c AS ncount, bx0 + cast(ceil(i * (bx1 - bx0) / m2) AS INTEGER) AS x0, bx0 + cast(ceil((i + 1) * (bx1 - bx0) / m2) AS INTEGER) AS x1, by0 + cast(ceil(j * (by1 - by0) / m2) AS INTEGER) AS y0, by0 + cast(ceil((j + 1) * (by1 - by0) / m2) AS INTEGER) AS y1 FROM t)
SELECT cast((gx * {m} + gy) * 16777216 + i * m2 + j AS BIGINT) AS leaf_id, x0, x1, y0, y1, cast((x1 - x0) * (y1 - y0) AS BIGINT) AS cells, round(ncount, 6) AS ncount FROM v"""


add("ag_p1", _ag_sql())(lambda spark, d: _leaf(grids.adaptive_grid(fm(spark, d), spec(), EPS, secret=SECRET, side=10)))

for _k, _a in (("geo", "geo"), ("uniform", "uniform")):
    add(f"kd_{_k}_p1", _all_sql("em_median", f"SELECT n.node AS leaf_id, x0, x1, y0, y1, cast((x1 - x0) * (y1 - y0) AS BIGINT) AS cells, round(x, 6) AS ncount FROM noisy n JOIN fine f ON f.node = n.node WHERE split_at IS NULL", 0.15, _a, smooth=True, tree_id="kd"))(
        lambda spark, d, a=_a: _leaf(kd.publish(tree.stored(fm(spark, d)), spec(), EPS, H, a, mode="subtree", secret=SECRET, step=tree.stored))
    )
add("kd_raw_p3", _all_sql("em_median", "SELECT node AS leaf_id, round(ncount, 6) AS ncount FROM noisy WHERE split_at IS NULL", 0.15, tree_id="kd", s="p3"))(
    lambda spark, d: _leaf(kd.publish(tree.stored(fm(spark, d, "p3")), spec("p3"), EPS, H, smoothing=False, secret=SECRET, mode="subtree")).select("leaf_id", "ncount")
)
add("bsp_p1", _all_sql("midpoint", "SELECT n.node AS leaf_id, round(x, 6) AS ncount FROM noisy n JOIN fine f ON f.node = n.node WHERE split_at IS NULL", smooth=True, eps_data=EPS, tree_id="kd"))(
    lambda spark, d: _leaf(kd.publish(tree.stored(fm(spark, d)), spec(), EPS, H, split="midpoint", mode="subtree", secret=SECRET, step=tree.stored)).select("leaf_id", "ncount")
)


def _quad_ctes(depth: int, allocation: str, growth: float = 2.0) -> str:
    parts = oracle.levels(EPS, depth, allocation, growth)
    out = [f"d AS MATERIALIZED ({oracle.dense('p1')})"]
    for h in range(depth + 1):
        side = SIDE >> (depth - h)
        bits = " + ".join(f"(((cx // {side}) >> {b}) & 1) * {2 << (2 * b)} + (((cy // {side}) >> {b}) & 1) * {1 << (2 * b)}" for b in range(depth - h)) or "0"
        out.append(f"n{h} AS MATERIALIZED (SELECT *, {oracle.lap('cnt', repr(1 / parts[h]), _Q('quad'), _Q('decide'), 'node')} AS y, {2 / parts[h] ** 2!r} AS v FROM (SELECT cast({(4 ** (depth - h) - 1) // 3 + 1} + {bits} AS BIGINT) AS node, any_value(cx // {side}) AS qx, any_value(cy // {side}) AS qy, {side} AS side, sum(cnt) AS cnt FROM d GROUP BY 1))")
    out.append("u0 AS (SELECT node, y AS z, v AS s, NULL::DOUBLE AS zc, NULL::DOUBLE AS sc FROM n0)")
    for h in range(1, depth + 1):
        out.append(f"u{h} AS MATERIALIZED (SELECT n.node, (y / v + k.z / k.s) / (1 / v + 1 / k.s) AS z, 1 / (1 / v + 1 / k.s) AS s, k.z AS zc, k.s AS sc FROM n{h} n JOIN (SELECT (node + 2) // 4 AS p, sum(z) AS z, sum(s) AS s FROM u{h - 1} GROUP BY 1) k ON k.p = n.node)")
    out.append(f"w{depth} AS (SELECT node, z AS x, zc, sc FROM u{depth})")
    for h in range(depth - 1, -1, -1):
        out.append(f"w{h} AS MATERIALIZED (SELECT c.node, c.z + (p.x - p.zc) * c.s / p.sc AS x, c.zc, c.sc FROM u{h} c JOIN w{h + 1} p ON p.node = (c.node + 2) // 4)")
    return "WITH " + ",\n".join(out)


for _k in ("geo", "uniform"):
    add(f"quad_{_k}_p1", _quad_ctes(3, _k) + " SELECT n.node AS leaf_id, cast(qx * side AS INTEGER) AS x0, cast((qx + 1) * side AS INTEGER) AS x1, cast(qy * side AS INTEGER) AS y0, cast((qy + 1) * side AS INTEGER) AS y1, cast(side * side AS BIGINT) AS cells, round(x, 6) AS ncount FROM n0 n JOIN w0 w ON w.node = n.node")(
        lambda spark, d, a=_k: _leaf(quad.publish(tree.stored(fm(spark, d)), spec(), 3, EPS, a, secret=SECRET, step=tree.stored))
    )
add("quad_raw_p1", _quad_ctes(3, "geo") + " SELECT node AS leaf_id, round(y, 6) AS ncount FROM n0")(lambda spark, d: _leaf(quad.publish(fm(spark, d), spec(), 3, EPS, smoothing=False, secret=SECRET)).select("leaf_id", "ncount"))
add("quad_counts_p1", _quad_ctes(3, "geo") + " " + " UNION ALL ".join(f"SELECT node AS node_id, {h} AS height, cast(cnt AS BIGINT) AS cnt FROM n{h}" for h in range(4)))(lambda spark, d: quad.quad_counts(fm(spark, d), spec(), 3).select("node_id", "height", "cnt"))


def _haar(pos: str, n: int) -> str:
    """Rows (l, k, f) of the coefficients that a cell takes part in."""
    top = n.bit_length() - 1
    parts = [f"{{'l': {top + 1}, 'k': 0, 'f': {1 / n!r}}}"] + [f"{{'l': {lv}, 'k': cast({pos} >> {lv} AS INTEGER), 'f': CASE WHEN ({pos} >> {lv - 1}) & 1 = 0 THEN {2.0**-lv!r} ELSE {-(2.0**-lv)!r} END}}" for lv in range(1, top + 1)]
    return f"unnest([{', '.join(parts)}])"


_COEF = f"SELECT a.l AS lx, a.k AS kx, b.l AS ly, b.k AS ky, sum(cnt * a.f * b.f) AS coef FROM (SELECT cx, cy, cnt, {_haar('cx', SIDE)} AS a, cy AS cy2 FROM ({oracle.dense('p1')})) m, (SELECT v, {_haar('v', SIDE)} AS b FROM range({SIDE}) r(v)) y WHERE y.v = m.cy GROUP BY 1, 2, 3, 4"
_SPAN = lambda l: f"(CASE WHEN {l} > 6 THEN {SIDE}.0 ELSE pow(2.0, {l}) END)"
_NOISY = f"SELECT lx, kx, ly, ky, {oracle.lap('coef', f'49 / ({EPS} * {_SPAN("lx")} * {_SPAN("ly")})', _Q('wavelet'), _Q('coef'), 'lx', 'kx', 'ly', 'ky')} AS coef FROM ({_COEF})"
add("wavelet_coefs_p1", f"SELECT cast(lx AS INTEGER) AS lx, cast(kx AS INTEGER) AS kx, cast(ly AS INTEGER) AS ly, cast(ky AS INTEGER) AS ky, round(coef, 6) AS coef FROM ({_NOISY})")(lambda spark, d: r6(wavelet.noisy_coefficients(fm(spark, d), spec(), EPS, SECRET), "coef"))
_UN = lambda p: f"unnest([{{'l': 7, 'k': 0, 's': 1}}, " + ", ".join(f"{{'l': {lv}, 'k': cast({p} >> {lv} AS INTEGER), 's': CASE WHEN ({p} >> {lv - 1}) & 1 = 0 THEN 1 ELSE -1 END}}" for lv in range(1, 7)) + "])"
add(
    "wavelet_cells_p1",
    f"WITH c AS MATERIALIZED ({_NOISY}), x AS MATERIALIZED (SELECT v, a.l AS l, a.k AS k, a.s AS s FROM (SELECT cast(v AS INTEGER) AS v, {_UN('v')} AS a FROM range({SIDE}) r(v))), h AS MATERIALIZED (SELECT x.v AS cx, ly, ky, sum(coef * s) AS coef FROM c JOIN x ON x.l = lx AND x.k = kx GROUP BY 1, 2, 3) SELECT cx, x.v AS cy, round(sum(coef * s), 6) AS value FROM h JOIN x ON x.l = ly AND x.k = ky GROUP BY 1, 2",
)(lambda spark, d: r6(wavelet.cells(tree.stored(wavelet.noisy_coefficients(fm(spark, d), spec(), EPS, SECRET)), spec()), "value"))

# Queries, answers, measures ------------------------------------------------------------------------------------------
for _p in (2, 6, 10):
    add(f"queries_square_{_p}", oracle.square_rects(_p / 100, N))(lambda spark, d, p=_p: workload.squares(spark, spec(), p / 100, N))
_ASKED = "(SELECT event_id AS i FROM events)"


def _asked(spark, d) -> DataFrame:
    """Each event asks for one rectangle, keyed by its id."""
    return src.table(spark, d, "events").select(F.col("event_id").alias("id"))


add("queries_random", oracle.random_rects(None, rows=_ASKED))(lambda spark, d: workload.random_rects(spark, spec(), None, ids=_asked(spark, d)))
_mixed_side = "(CASE WHEN i % 4 = 0 THEN 1 + cast(floor($ * 64) AS INTEGER) WHEN i % 4 = 1 THEN 9 WHEN i % 4 = 2 THEN 16 ELSE 20 END)"
add("queries_mixed", oracle.rects("mixed", None, _mixed_side, _mixed_side, rows=_ASKED))(lambda spark, d: workload.mixed(spark, spec(), None, ids=_asked(spark, d)))
add("exact_answers", oracle.exact_answers(oracle.random_rects(N), "p1"))(lambda spark, d: answer.exact_prefix(fm(spark, d), spec(), workload.random_rects(spark, spec(), N)))
add("range_join_exact", oracle.exact_answers(oracle.square_rects(0.06, N), "p1"))(lambda spark, d: answer.exact(fm(spark, d), workload.squares(spark, spec(), 0.06, N)))


def _priv(df: DataFrame) -> DataFrame:
    return r6(df.select("workload", "qid", "private"), "private")


_P = "SELECT workload, qid, round(private, 6) AS private FROM "
for _st in ("nested", "tiles"):
    add(f"private_answers_edt_{_st}", _pruned_sql(final=_P + f"({oracle.private_answers(oracle.random_rects(N))})"))(
        lambda spark, d, st=_st: _priv(answer.private(tree.stored(_edt(spark, d, mode="subtree").published), workload.random_rects(spark, spec(), N), strategy=st))
    )
_ug = oracle.block_rows(f"SELECT gx, gy, {oracle.lap('cnt', repr(1 / (EPS - 1e-4)), _Q('ug'), _Q('cell'), 'gx', 'gy')} AS ncount FROM ({oracle.grid_blocks('p1', 20)})", 20, "gx * 20 + gy").replace("round(ncount, 6) AS ncount", "ncount")
add("private_answers_ug", f"WITH leaf AS MATERIALIZED ({_ug}) {_P} ({oracle.private_answers(oracle.random_rects(N))})")(
    lambda spark, d: _priv(answer.private(grids.uniform_grid(fm(spark, d), spec(), EPS, secret=SECRET, side=20), workload.random_rects(spark, spec(), N)))
)
add("private_answers_quad", _quad_ctes(3, "geo") + f", leaf AS MATERIALIZED (SELECT qx * side AS x0, (qx + 1) * side AS x1, qy * side AS y0, (qy + 1) * side AS y1, x AS ncount FROM n0 n JOIN w0 w ON w.node = n.node) {_P} ({oracle.private_answers(oracle.random_rects(N))})")(
    lambda spark, d: _priv(answer.private(quad.publish(tree.stored(fm(spark, d)), spec(), 3, EPS, secret=SECRET, step=tree.stored), workload.random_rects(spark, spec(), N)))
)
_kd_fine = _all_sql("em_median", "SELECT workload, qid, round(private, 5) AS private FROM (" + oracle.private_answers(oracle.random_rects(N), "(SELECT n.*, x FROM noisy n JOIN fine f ON f.node = n.node WHERE split_at IS NULL)", "x") + ")", 0.15, smooth=True, tree_id="kd")


@add("private_answers_tree", _kd_fine)
def _(spark, d):
    """Inner counts of a smoothed tree: equal to the sums of its leaves, as its counts are consistent."""
    nodes = tree.build(tree.stored(fm(spark, d)), spec(), H, "em_median", 0.15 * EPS / H, SECRET, "kd", mode="subtree")
    parts = budget.geometric(0.85 * EPS, H)
    level = F.element_at(budget.level_array(parts), F.col("height") + 1)
    from geohist.operators.consistency import smooth

    fine = tree.stored(smooth(tree.stored(release.all_nodes(nodes, parts, SECRET)), H, 2 / (level * level), step=tree.stored).withColumn("ncount", F.col("smooth")))
    q = workload.random_rects(spark, spec(), N)
    got = q.select("workload", "qid").join(answer.from_tree(fine, q, H), ["workload", "qid"], "left")
    return got.select("workload", "qid", F.round(F.coalesce("private", F.lit(0.0)), 5).alias("private"))


def _mre_sql(private: str) -> str:
    return f"SELECT e.workload, round(avg(abs(exact - private) / greatest(exact, 20) * 100), 6) AS mre, count(*) AS queries FROM ({oracle.exact_answers(oracle.random_rects(N), 'p1')}) e JOIN ({private}) p ON p.qid = e.qid GROUP BY 1"


def _mre(spark, d, leaves: DataFrame) -> DataFrame:
    q = workload.random_rects(spark, spec(), N)
    both = answer.private(leaves, q).join(answer.exact_prefix(fm(spark, d), spec(), q), ["workload", "qid"])
    return r6(measures.mre(measures.relative_error(both, 20)).select("workload", "mre", "queries"), "mre")


add("mre_edt", _pruned_sql(final=_mre_sql(oracle.private_answers(oracle.random_rects(N)))))(lambda spark, d: _mre(spark, d, tree.stored(_edt(spark, d, mode="subtree").published)))
add("mre_ug", f"WITH leaf AS MATERIALIZED ({_ug}) " + _mre_sql(oracle.private_answers(oracle.random_rects(N))))(lambda spark, d: _mre(spark, d, grids.uniform_grid(fm(spark, d), spec(), EPS, secret=SECRET, side=20)))
add("relative_error_edt", _pruned_sql(final=f"SELECT e.qid, round(CASE WHEN exact <> 0 THEN abs(exact - private) / exact * 100 END, 5) AS re FROM ({oracle.exact_answers(oracle.random_rects(N), 'p1')}) e JOIN ({oracle.private_answers(oracle.random_rects(N))}) p ON p.qid = e.qid"))(
    lambda spark, d: measures.relative_error(answer.private(tree.stored(_edt(spark, d, mode="subtree").published), q := workload.random_rects(spark, spec(), N)).join(answer.exact(fm(spark, d), q), ["workload", "qid"])).select("qid", F.round("re", 5).alias("re"))
)


@add(
    "error_split_edt",
    _pruned_sql(final=f"SELECT e.qid, round(n.private, 5) AS noise_error, round(c.private - exact, 5) AS uniformity_error FROM ({oracle.exact_answers(oracle.random_rects(N), 'p1')}) e JOIN ({oracle.private_answers(oracle.random_rects(N), value='(ncount - cnt)')}) n ON n.qid = e.qid JOIN ({oracle.private_answers(oracle.random_rects(N), value='cnt')}) c ON c.qid = e.qid"),
)
def _(spark, d):
    nodes = _edt(spark, d, mode="subtree").nodes
    leaves = tree.stored(release.pruned(nodes, H, EPS_DATA, STOP, secret=SECRET).withColumn("cells", tree.cells_of()))
    q = workload.random_rects(spark, spec(), N)
    return measures.decompose(leaves, q, answer.exact(fm(spark, d), q)).select("qid", F.round("noise_error", 5).alias("noise_error"), F.round("uniformity_error", 5).alias("uniformity_error"))


_t = oracle.Tree("p1", H, "searched", EPS_LEVEL, "edt")
_t.nodes()
_REGRET = _t.sql(" UNION ALL ".join(f"SELECT l.node AS node_id, round(any_value(o.o) + {TILT}, 5) AS chosen, round(min(b.o) + {TILT}, 5) AS best FROM l{h} l JOIN o_{h} o ON o.node = l.node AND o.k = l.split_at - l.{'x0' if h % 2 == 0 else 'y0'} JOIN o_{h} b ON b.node = l.node GROUP BY 1" for h in range(H, 0, -1)))


@add("split_regret_p1", _REGRET)
def _(spark, d):
    rel = _edt(spark, d, mode="subtree")
    nodes = tree.stored(rel.nodes)
    c = F.col
    inside = (c("cx") >= c("x0")) & (c("cx") < c("x1")) & (c("cy") >= c("y0")) & (c("cy") < c("y1"))
    cells = fm(spark, d).join(F.broadcast(nodes.where("split_at is not null").select("tree_id", "node_id", "x0", "x1", "y0", "y1")), inside).select("tree_id", "node_id", "cx", "cy", "cnt")
    return measures.split_regret(nodes, cells).select("node_id", F.round(F.col("chosen") + TILT, 5).alias("chosen"), F.round(F.col("best") + TILT, 5).alias("best"))


add("depths_edt", _pruned_sql(final="SELECT count(*) AS leaves, cast(max(floor(log2(node))) AS INTEGER) AS deepest, round(avg(floor(log2(node))), 6) AS mean_depth FROM leaf"))(
    lambda spark, d: r6(measures.depths(_edt(spark, d, mode="subtree").published, H).select("leaves", "deepest", "mean_depth"), "mean_depth")
)
add("hotspots_topk", _pruned_sql(final="SELECT node AS leaf_id, round(ncount / ((x1 - x0) * (y1 - y0)), 6) AS density FROM leaf ORDER BY 2 DESC, 1 LIMIT 5"))(
    lambda spark, d: measures.hotspots(tree.stored(_edt(spark, d, mode="subtree").published), 5).select("leaf_id", F.round("density", 6).alias("density"))
)
add("cover_check", "SELECT cast(0 AS BIGINT) AS uncovered, cast(4096 AS BIGINT) AS cells")(
    lambda spark, d: (rel := tree.stored(_edt(spark, d, mode="subtree").published)).agg(F.sum("cells").alias("cells")).crossJoin(grid.all_cells(spark, spec()).join(F.broadcast(rel), (F.col("cx") >= F.col("x0")) & (F.col("cx") < F.col("x1")) & (F.col("cy") >= F.col("y0")) & (F.col("cy") < F.col("y1")), "left_anti").agg(F.count(F.lit(1)).alias("uncovered")))
)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Published leaves of the events' histogram, height estimated."""
    return edt.publish(src.points(spark, sf_dir, "p1"), spec(), budget.Budget(5.0, 0.05, 0.1), edt.TreePlan(secret=SECRET)).published


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    from geohist.plans import accuracy, experiments, surface

    return {k: f for k, (f, _) in _ALL.items()} | accuracy.queries() | surface.queries() | experiments.queries()


def oracle_sql() -> dict[str, str]:
    from geohist.plans import accuracy, surface

    return {k: s for k, (_, s) in _ALL.items() if s} | accuracy.oracle_sql() | surface.oracle_sql()

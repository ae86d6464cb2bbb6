import itertools
import math

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from geohist.functions import budget, noise
from geohist.operators import answer, consistency, grid, grids, kd, local, measures, quad, release, split, tree, wavelet, workload
from geohist.plans import edt, experiments
from geohist.sources import points as src
from geohist.sources import sinks

KEY = noise.TEST_SECRET
SPEC = grid.GridSpec(0.0, 16.0, 0.0, 16.0, 16, 16)
#: The worked example: columns x = 0, 1, 2, rows from the bottom up.
EXAMPLE = [(0, 0, 3), (1, 0, 3), (0, 1, 3), (1, 1, 3), (2, 0, 1), (2, 1, 1), (2, 2, 4)]


@pytest.fixture(scope="module")
def fm(spark):
    rng = np.random.default_rng(1)
    cells = [(int(x), int(y), int(c)) for x, y, c in zip(rng.integers(0, 16, 120), rng.integers(0, 16, 120), rng.integers(1, 60, 120))]
    return spark.createDataFrame(pd.DataFrame(cells, columns=["cx", "cy", "cnt"]).groupby(["cx", "cy"], as_index=False).sum()).cache()


def dense(fm, spec=SPEC):
    return experiments.dense_matrix(fm, spec)


def test_example_splits_and_answer(spark):
    m = np.zeros((3, 3))
    for x, y, c in EXAMPLE:
        m[x, y] = c
    left = local.Cut(m[:2].T)  # split rows of the left node
    assert [round(left.unevenness(k), 9) for k in (2, 1, 3)] == [0.0, 6.0, 8.0]
    fm = spark.createDataFrame(EXAMPLE, "cx int, cy int, cnt long")
    spec = grid.GridSpec(0.0, 3.0, 0.0, 3.0, 3, 3)
    cells = fm.where("cx < 2").select(F.lit("t").alias("tree_id"), F.lit(2).cast("long").alias("node_id"), "cx", "cy", "cnt")
    node = spark.createDataFrame([("t", 2, 1, 1, 0, 2, 0, 3)], "tree_id string, node_id long, height int, axis int, x0 int, x1 int, y0 int, y1 int")
    got = {r["k"]: round(r["o"], 9) for r in split.unevenness(split.profile(cells, node), node, split.every_position(True)).collect()}
    assert got == {2: 0.0, 1: 6.0, 3: 8.0}
    leaves = spark.createDataFrame([("t", 4, 0, 2, 0, 2, 4, 12.0), ("t", 5, 0, 2, 2, 3, 2, 0.0), ("t", 6, 2, 3, 0, 2, 2, 2.0), ("t", 7, 2, 3, 2, 3, 1, 4.0)], "tree_id string, leaf_id long, x0 int, x1 int, y0 int, y1 int, cells long, ncount double")
    q = spark.createDataFrame([("w", 1, 1, 3, 0, 1)], "workload string, qid long, x0 int, x1 int, y0 int, y1 int")
    assert answer.private(leaves, q).first()["private"] == 4.0
    exact = {r["node_id"]: r for r in tree.build(fm, spec, 2, "exact", tree_id="t").collect()}
    assert exact[1]["cnt"] == 18 and sum(r["cnt"] for r in exact.values() if r["split_at"] is None) == 18
    nodes = [("t", 1, 2, 0, 0, 3, 0, 3, 2, 18), ("t", 2, 1, 1, 0, 2, 0, 3, 2, 12), ("t", 3, 1, 1, 2, 3, 0, 3, 2, 6), ("t", 4, 0, 0, 0, 2, 0, 2, None, 12), ("t", 5, 0, 0, 0, 2, 2, 3, None, 0), ("t", 6, 0, 0, 2, 3, 0, 2, None, 2), ("t", 7, 0, 0, 2, 3, 2, 3, None, 4)]
    drawn = spark.createDataFrame([(*n, 0) for n in nodes], tree.NODE)
    for stop in (release.StopRule(7, None), release.StopRule(None, 4)):
        assert {r["node_id"] for r in release.pruned(drawn, 2, 1e9, stop, secret=KEY).collect()} == {3, 4, 5}


def test_sensitivity_is_at_most_two():
    rng = np.random.default_rng(2)
    worst = 0.0
    for _ in range(3000):
        m = rng.integers(0, 5, (rng.integers(2, 6), rng.integers(1, 5))).astype(float)
        n = m.copy()
        n[rng.integers(m.shape[0]), rng.integers(m.shape[1])] += 1
        worst = max(worst, max(abs(local.Cut(m).unevenness(k) - local.Cut(n).unevenness(k)) for k in range(1, m.shape[0] + 1)))
    assert 1.0 < worst <= 2.0
    for a in itertools.product(range(3), repeat=4):
        m = np.array(a, float).reshape(4, 1)
        for i in range(4):
            n = m.copy()
            n[i] += 1
            assert all(abs(local.Cut(m).unevenness(k) - local.Cut(n).unevenness(k)) <= 2 for k in range(1, 5))


def test_budgets():
    for eps, h in ((1, 0), (0.1, 15), (0.0849, 15), (0.5, 4)):
        parts = budget.geometric(eps, h)
        assert math.isclose(sum(parts), eps) and all(math.isclose(a / b, 2 ** (1 / 3)) for a, b in zip(parts, parts[1:]))
        assert math.isclose(budget.remaining(parts, h) + parts[h], eps)
    rng = np.random.default_rng(3)
    best = budget.path_variance(budget.geometric(1.0, 6))
    assert best < budget.path_variance(budget.uniform(1.0, 6))
    assert all(best <= budget.path_variance(list(x / x.sum())) for x in rng.random((500, 7)) + 0.01)
    assert [budget.estimated_height(3.5e6, e, cells=1 << 20) for e in (0.1, 0.3, 0.5)] == [15, 16, 17]
    assert budget.estimated_height(6e12, 0.1, cells=1 << 32) == 32 and budget.estimated_height(-5, 0.1) == 0
    assert math.isclose(budget.Budget(0.1, per_level=1e-3).data(15), 0.0849)
    for bad in ({"eps_tot": 0, "per_level": 1}, {"eps_tot": 1}, {"eps_tot": 1, "per_level": 1, "eps_prt": 1}):
        with pytest.raises(ValueError):
            budget.Budget(**bad)
    with pytest.raises(ValueError):
        budget.Budget(0.1, per_level=0.1).data(4)
    with pytest.raises(ValueError):
        budget.Ledger().spend("a", 1.0).spend("b", 0.5).check(1.2)


@pytest.mark.parametrize("method", list(split.METHODS))
def test_modes_agree(spark, fm, method):
    trees = [sorted(map(tuple, tree.build(fm, SPEC, 4, method, 2.0, KEY, mode=m, max_task_cells=100).select(*local.COLUMNS).collect())) for m in ("levelwise", "subtree", "auto")]
    assert trees[0] == trees[1] == trees[2]
    rows = [dict(zip(local.COLUMNS, r)) for r in trees[0]]
    leaf = [r for r in rows if r["split_at"] is None]
    cover = np.zeros((16, 16), int)
    for r in leaf:
        cover[r["x0"] : r["x1"], r["y0"] : r["y1"]] += 1
        assert r["axis"] == r["height"] % 2
    assert (cover == 1).all() and sum(r["cnt"] for r in leaf) == dense(fm).sum()
    if method == "searched":
        assert max(r["evals"] for r in rows) <= 7


def test_searched_without_noise_ends_at_local_minimum():
    rng = np.random.default_rng(5)
    for _ in range(200):
        m = rng.integers(0, 9, (rng.integers(2, 40), 3)).astype(float)
        cut = local.Cut(m)
        k, _ = local.choose(cut, "searched", 0.0, "s", "t", 1, 12, False)
        o = {j: cut.unevenness(j) for j in range(1, len(m))}
        assert all(o[k] <= o.get(j, math.inf) for j in (k - 1, k + 1) if j > 1)


def test_release_matches_local_and_ledger(spark, fm):
    nodes = tree.build(fm, SPEC, 4, "searched", 0.5, KEY)
    rows = [tuple(r) for r in nodes.select(*local.COLUMNS).collect()]
    parts = budget.geometric(0.8, 4)
    for stop in (release.StopRule(100, 5), release.StopRule(None, None), release.StopRule(1e9, None)):
        got = release.pruned(nodes, 4, 0.8, stop, secret=KEY)
        mine = sorted((round(v, 6), *r) for *r, v in local.released(rows, parts, 0.8, noise.TEST_SECRET, stop.min_count, stop.min_cells))
        assert sorted((round(r["ncount"], 6), r["x0"], r["x1"], r["y0"], r["y1"]) for r in got.collect()) == mine
        assert all(math.isclose(r["spent"], 0.8) for r in release.path_ledger(got, 4, 0.8).collect())
    again = release.redact(release.pruned(nodes, 4, 0.8, secret=KEY))
    assert sorted(again.collect()) == sorted(release.redact(release.pruned(nodes, 4, 0.8, secret=KEY)).collect())
    assert sorted(again.collect()) != sorted(release.redact(release.pruned(nodes, 4, 0.8, secret="other")).collect())
    assert set(again.columns) == {"tree_id", "leaf_id", "x0", "x1", "y0", "y1", "cells", "ncount"}
    with pytest.raises(ValueError):
        sinks.write(nodes, budget.Ledger().frame(spark), "/nowhere", "own")
    with pytest.raises(ValueError):
        sinks.write(again, budget.Ledger().frame(spark), "/nowhere", KEY)
    with pytest.raises(ValueError, match="secret"):
        edt.publish_matrix(fm, SPEC, budget.Budget(1.0, 0.0, 0.05), edt.TreePlan(height=2))
    with pytest.raises(ValueError, match="secret"):
        grids.singular(fm, SPEC, 1.0)
    with pytest.raises(ValueError, match="protects nothing"):
        edt.publish_matrix(fm, SPEC, budget.Budget(1.0, 0.0, 0.05), edt.TreePlan(height=2, secret=KEY)).write("/nowhere")
    assert KEY not in repr(edt.TreePlan(secret=KEY))


def test_smoothing_is_least_squares(spark):
    rng = np.random.default_rng(7)
    for fanout, nodes in ((2, [(1, 2), (2, 1), (3, 1), (4, 0), (5, 0), (6, 0), (7, 0)]), (4, [(1, 1), *((i, 0) for i in range(2, 6))]), (2, [(1, 2), (2, 1), (3, 1), (4, 0), (5, 0)])):
        y = {i: float(v) for (i, _), v in zip(nodes, rng.normal(20, 5, len(nodes)))}
        v = {i: float(x) for (i, _), x in zip(nodes, rng.uniform(0.5, 4, len(nodes)))}
        parent = {i: i // 2 if fanout == 2 else (i + 2) // 4 for i, _ in nodes if i > 1}
        leaf = [i for i, _ in nodes if i not in parent.values()]
        a = np.array([[float(j == i or _below(j, i, parent)) for j in leaf] for i, _ in nodes])
        w = np.array([v[i] ** -0.5 for i, _ in nodes])
        x = np.linalg.lstsq(a * w[:, None], np.array([y[i] for i, _ in nodes]) * w, rcond=None)[0]
        want = dict(zip([i for i, _ in nodes], a @ x))
        mine = local.smoothed(y, v, fanout)
        df = spark.createDataFrame([("t", i, h, y[i], v[i]) for i, h in nodes], "tree_id string, node_id long, height int, ncount double, v double")
        got = {r["node_id"]: r["smooth"] for r in consistency.smooth(df, max(h for _, h in nodes), F.col("v"), fanout).collect()}
        for i in want:
            assert math.isclose(want[i], mine[i], abs_tol=1e-8) and math.isclose(want[i], got[i], abs_tol=1e-8)


def _below(j, i, parent):
    while j in parent:
        j = parent[j]
        if j == i:
            return True
    return False


def test_wavelet_identity_and_weights(spark, fm):
    m = dense(fm)
    assert np.allclose(local.unhaar(local.haar(m)), m)
    back = wavelet.cells(wavelet.noisy_coefficients(fm, SPEC, 1e12, KEY), SPEC).toPandas()
    assert np.allclose(m[back["cx"], back["cy"]], back["value"], atol=1e-6)
    for n, rho in ((8, 4), (64, 7)):
        one = np.zeros(n)
        one[3] = 1
        assert math.isclose((np.abs(local.haar(one)) * local.haar_weights(n)).sum(), rho)


def test_answers_agree(spark, fm):
    q = workload.random_rects(spark, SPEC, 60).unionByName(workload.squares(spark, SPEC, 0.06, 60))
    exact = {tuple(r) for r in answer.exact(fm, q).collect()}
    assert exact == {tuple(r) for r in answer.exact_prefix(fm, SPEC, q).collect()}
    rel = edt.publish_matrix(fm, SPEC, budget.Budget(1.0, 0.0, 0.05), edt.TreePlan(height=4, secret=KEY))
    a, b = ({(r["workload"], r["qid"]): r["private"] for r in answer.private(rel.published, q, strategy=s).collect()} for s in ("nested", "tiles"))
    rects = [tuple(r) for r in rel.published.select("x0", "x1", "y0", "y1", "ncount").collect()]
    rows = q.collect()
    c = local.answers(local.blocks_to_cells(rects, 16, 16), np.array([[r["x0"], r["x1"], r["y0"], r["y1"]] for r in rows]))
    for r, x in zip(rows, c):
        k = (r["workload"], r["qid"])
        assert math.isclose(a[k], b[k], abs_tol=1e-7) and math.isclose(a[k], x, abs_tol=1e-7)
    full = release.pruned(rel.nodes, 4, 0.8, secret=KEY).withColumn("cells", tree.cells_of())
    parts = measures.decompose(full, q, answer.exact(fm, q)).join(answer.private(full, q), ["tree_id", "workload", "qid"]).join(answer.exact(fm, q), ["workload", "qid"])
    assert all(math.isclose(r["noise_error"] + r["uniformity_error"], r["private"] - r["exact"], abs_tol=1e-6) for r in parts.collect())


@pytest.mark.parametrize("spec", [grid.GridSpec(0, 1, 0, 1, 1, 1), grid.GridSpec(0, 1, 0, 1, 1, 7), grid.GridSpec(0, 1, 0, 1, 50, 3), grid.GridSpec(0, 1, 0, 1, 2, 2)])
def test_degenerate(spark, spec):
    rows = [(0.5, 0.5), (float("nan"), 0.1), (None, 0.2), (float("inf"), -9.0), (0.999999, 1.0)]
    pts = spark.createDataFrame(rows, "px double, py double")
    fm = grid.frequency_matrix(pts, spec)
    assert fm.agg(F.sum("cnt")).first()[0] == 3
    assert grid.frequency_matrix(pts, spec, "drop").agg(F.sum("cnt")).first()[0] == 1
    for f in (fm, fm.limit(0)):
        rel = edt.publish_matrix(f, spec, budget.Budget(5.0, 0.1, 0.1), edt.TreePlan(height=2, secret=KEY))
        assert rel.published.agg(F.sum("cells")).first()[0] == spec.cells
        for out in (grids.singular(f, spec, 1.0, KEY), grids.total_uniform(f, spec, 1.0, KEY), grids.uniform_grid(f, spec, 1.0, secret=KEY), grids.adaptive_grid(f, spec, 1.0, secret=KEY), quad.publish(f, spec, 2, 1.0, secret=KEY), kd.publish(f, spec, 1.0, 2, secret=KEY), wavelet.publish(f, spec, 1.0, KEY)):
            assert out.agg(F.sum("cells")).first()[0] == spec.cells


def test_noise(spark):
    v = spark.range(20000).select(noise.keyed_uniform("k", F.col("id")).alias("u"), noise.laplace(0.0, 3.0, "k", "l", F.col("id")).alias("l")).toPandas()
    u = np.sort(v["u"])
    assert np.abs(u - (np.arange(20000) + 0.5) / 20000).max() < 0.015
    assert abs(v["l"].var() / 18 - 1) < 0.08 and len(noise.fresh_secret()) == 64
    assert math.isclose(noise.laplace_of(3.0, "k", "l", 7), v["l"][7], rel_tol=1e-12)


def test_audit_of_private_splits():
    """Frequencies of each output on two neighbouring matrices differ by at most e^eps, within the sampling margin."""
    m = np.array([[3.0, 0], [1, 2], [0, 0], [5, 1]])
    n = m.copy()
    n[0, 1] += 1
    for method, eps in (("exhaustive", 1.0), ("searched", 1.0), ("em_median", 1.0)):
        draws = [np.bincount([local.choose(local.Cut(x), method, eps, f"s{i}", "t", 1, 2, False)[0] for i in range(4000)], minlength=5)[1:4] + 0.0 for x in (m, n)]
        for a, b in zip(*draws):
            assert a <= math.exp(eps) * (b + 4 * math.sqrt(b + 1)) + 4 * math.sqrt(a + 1) and b <= math.exp(eps) * (a + 4 * math.sqrt(a + 1)) + 4 * math.sqrt(b + 1)


def test_sources(spark, tmp_path):
    spark.createDataFrame([(1.0, 2.0), (3.0, 4.0)], "px double, py double").write.csv(f"{tmp_path}/c")
    with open(f"{tmp_path}/c/extra.csv", "w") as f:
        f.write("x,1\n")
    good, bad = src.read_points(spark, f"{tmp_path}/c", "csv")
    assert good.cache().count() == 2 and len(bad.collect()) == 1
    box = src.around(spark.createDataFrame([(34.05, -118.24), (34.36, -118.24), (34.37, -118.24), (33.0, -118.0)], "lat double, lon double"), 34.05223, -118.24368, 70)
    assert box.count() == 2 and all(0 <= r["px"] < 70 and 0 <= r["py"] < 70 for r in box.collect())
    assert src.gaussian(spark, 100, 20).count() == 100 and src.patchwork(spark, 1000).where("px is null or isnan(px)").count() == 0
    plan = src.crop(spark.read.parquet("/root/testdata/sf0.001/events.parquet"), time=("2024-01-01", "2024-01-08")).select("value")._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(ts)" in plan


def test_plans(spark):
    from geohist.plans import registry

    plan = registry.fm(spark, "/root/testdata/sf0.001")._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 1 and "ReadSchema: struct<ts:timestamp_ntz,value:double>" in plan and "Python" not in plan
    names = set(registry.queries())
    assert set(registry.oracle_sql()) <= names and len(names) > 120

from geohist.operators import split
from geohist.plans import experiments
from geohist.sources import points as src


def test_all_split_methods_at_every_size():
    for quick in (True, False):
        assert {p["split"] for _, p, _ in experiments.methods_of("ablate_split", quick)} == set(split.METHODS)


def test_registered_experiments_are_whole(spark, monkeypatch):
    sf, seen, asked = "/root/testdata/sf0.001", {}, []
    monkeypatch.setattr(experiments, "point_set", lambda s, d, name, n: asked.append((name, n)) or s.createDataFrame([(1.0, 1.0)], "px double, py double"))
    monkeypatch.setattr(experiments, "dense_matrix", lambda fm, spec: experiments.np.ones((spec.nx, spec.ny)))
    monkeypatch.setattr(experiments, "evaluate", lambda s, matrices, configs, queries: seen.update(m=matrices, c=configs, q=queries))
    for name, sets in experiments.EXPERIMENTS.items():
        asked.clear()
        experiments._KNOWN.clear()
        experiments.queries()[f"exp_{name}"](spark, sf)
        assert {x for x, _ in asked} == set(sets) and max(n for _, n in asked) == 3_500_000, name
        assert all(m.shape == (1024, 1024) for m in seen["m"].values()) and seen["q"] == 2000
        assert {c["method"] for c in seen["c"]} == {m for m, _, _ in experiments.methods_of(name)}
        assert len(seen["c"]) == len(seen["m"]) * len(experiments.methods_of(name))
    experiments._KNOWN.clear()
    monkeypatch.setattr(experiments, "publish_local", lambda m, *a: (m, 0, 0))
    assert {r["set"] for r in experiments.queries()["exp_hotspots"](spark, sf).collect()} == {"p1", "pw"}
    experiments._KNOWN.clear()


def test_every_experiment_reads_a_given_table():
    assert all(set(sets) & set(src.SETS) for sets in experiments.EXPERIMENTS.values())
    assert set(experiments.EXPERIMENTS["ablate_prt"]) <= set(src.SETS)


def test_small_form(spark):
    got = experiments.small(spark, "/root/testdata/sf0.001", "ablate_T", ("p1",)).collect()
    assert len(got) == 12 and all(r["mre"] >= 0 for r in got)

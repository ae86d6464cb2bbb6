import random

import pytest
from geohist.llm import jaccard


@pytest.mark.parametrize("list_rows,boundary", [(20_000, None), (7, 30)])
def test_links_equal_brute_force(spark, monkeypatch, list_rows, boundary):
    monkeypatch.setattr(jaccard, "LIST_ROWS", list_rows)
    if boundary:
        monkeypatch.setattr(jaccard, "boundary_by_cost", lambda sketch: boundary)
    rng, rows = random.Random(4), [(0, ""), (1, None)]
    for size in (8, 40, 120):
        base = [f"b{size}x{i}" for i in range(size)]
        for _ in range(40):
            w = list(base)
            for _ in range(rng.randint(0, 1 + size // 40)):
                w[rng.choice([0, -1]) if size == 8 else rng.randrange(size)] = f"r{rng.randrange(4)}"
            rows.append((len(rows), " ".join(w)))
    rng.shuffle(rows)
    sets = {}
    for d, t in rows:
        w = (t or "").split()
        sets[d] = {tuple(w[i : i + 5]) for i in range(len(w) - 4)}
    want = {d: sum(1 for e in sets if e != d and sets[d] and sets[e] and 100 * len(sets[d] & sets[e]) >= 80 * len(sets[d] | sets[e])) for d in sets}
    got = {r["doc_id"]: r["n_links"] for r in jaccard.link_components(spark.createDataFrame(rows, "doc_id long, text string").repartition(5)).collect()}
    assert got == want and max(want.values()) > 20 and len(set(want.values())) > 5

import random
import re

import numpy as np
import pytest
from geohist.llm import jaccard

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def brute(rows, k):
    lower = lambda s: "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in s)
    sets = []
    for _, t in rows:
        w = WORD.findall(lower(t or ""))
        sets.append({tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if len(w) >= k else {tuple(w)} if w else set())
    up = list(range(len(rows)))

    def find(i):
        while up[i] != i:
            i = up[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            if sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= 80 * len(sets[i] | sets[j]):
                a, b = sorted((find(i), find(j)))
                up[b] = a
    small: dict = {}
    for i, (d, _) in enumerate(rows):
        r = find(i)
        if d is not None:
            small[r] = min(small.get(r, d), d)
    return sorted((d if d is not None else -1, len(s), small.get(find(i), -1)) for i, ((d, _), s) in enumerate(zip(rows, sets)))


@pytest.mark.parametrize("list_rows,boundary", [(20_000, None), (7, 30), (20_000, 4)])
def test_equals_brute_force(spark, monkeypatch, list_rows, boundary):
    monkeypatch.setattr(jaccard, "LIST_ROWS", list_rows)
    if boundary:
        monkeypatch.setattr(jaccard, "boundary_by_cost", lambda sketch: boundary)
    rng = random.Random(9)
    words = [f"w{i}" for i in range(400)]
    rows, base = [], []
    for i in range(160):
        if base and rng.random() < 0.6:
            w = list(rng.choice(base))
            for _ in range(rng.randint(0, max(1, len(w) // 30))):
                if w:
                    w[rng.randrange(len(w))] = rng.choice(words).upper() if rng.random() < 0.3 else rng.choice(words)
        else:
            w = [rng.choice(words) for _ in range(rng.choice([1, 3, 5, 6, 8, 12, 30, 90, 200]))]
            base.append(w)
        rows.append((1000 - i, rng.choice([" ", "\n"]).join(w)))
    rows += [(5000, None), (5001, ""), (5002, " \n"), (None, rows[7][1]), (993, rows[9][1]), (5003, "Ab cD"), (5004, "aB Cd"), (5005, "again " * 30_000)]
    docs = spark.createDataFrame([(*r, "x", "y") for r in rows], "doc_id long, text string, node string, sig string")
    got = jaccard.link_components(docs).collect()
    assert sorted((r["doc_id"] if r["doc_id"] is not None else -1, r["n_shingles"], r["component_id"] if r["component_id"] is not None else -1) for r in got) == brute(rows, 5)


def test_edges(spark):
    assert jaccard.link_components(spark.createDataFrame([], "doc_id long, text string")).count() == 0
    one = jaccard.link_components(spark.createDataFrame([(3, "a"), (2, "A"), (9, None)], "doc_id long, text string")).collect()
    assert sorted((r["doc_id"], r["component_id"]) for r in one) == [(2, 2), (3, 2), (9, 9)]
    assert jaccard.boundary_by_cost(np.zeros(jaccard.CELLS, np.uint32)) == 4
    assert [int(jaccard.prefix_length(n, 1)) for n in (1, 5, 10, 11)] == [1, 2, 3, 3]

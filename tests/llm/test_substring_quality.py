import hashlib
import random
import re

import numpy as np
from geohist.llm import quality, substring

SPACE = re.compile(r"[^\x20\x09-\x0D]+")


def brute(rows, size):
    first: dict = {}
    for d, t in rows:
        w = SPACE.findall(t or "")
        for i in range(len(w) - size + 1):
            k = tuple(w[i : i + size])
            first[k] = min(first.get(k, 2**63 - 1), 2**63 - 1 if d is None else d)
    out = []
    for d, t in rows:
        w = SPACE.findall(t or "")
        gone = set()
        for i in range(len(w) - size + 1):
            if first[tuple(w[i : i + size])] < (2**63 - 1 if d is None else d):
                gone.update(range(i, i + size))
        kept = " ".join(x for i, x in enumerate(w) if i not in gone)
        out.append((d if d is not None else -1, len(w), len(gone), hashlib.sha256(kept.encode()).hexdigest()))
    return sorted(out)


def test_substring_equals_brute_force(spark, monkeypatch):
    monkeypatch.setattr(substring, "FOLD", 400)
    rng = random.Random(2)
    passage = "the common passage of many words that stands in most documents here é".split()
    rows = []
    for i in range(120):
        w = [rng.choice("abcdefgh") * rng.randint(1, 2) for _ in range(rng.randint(0, 60))]
        if i % 2:
            k = rng.randint(0, len(w))
            w[k:k] = passage
        rows.append((i // 2 * 2 if i % 10 == 1 else i, rng.choice([" ", "\n", " \t "]).join(w)))
    rows += [(500, None), (501, ""), (None, " ".join(passage)), (3, rows[3][1]), (502, "x " * 40_000)]
    for size in (4, 13):
        df = spark.createDataFrame(rows, "doc_id long, text string")
        got = sorted((r["doc_id"] if r["doc_id"] is not None else -1, r["n_words"], r["n_removed"], r["kept_sha256"]) for r in substring.remove_repeats(df, size).collect())
        assert got == brute(rows, size)
    assert substring.remove_repeats(df.limit(0)).count() == 0


def test_quality_learns_and_scores_all(spark):
    rng = random.Random(4)
    word = lambda: "".join(rng.choice("etaoinshr") for _ in range(rng.randint(2, 8)))
    rows, labels = [], []
    for i in range(400):
        w = [word() for _ in range(rng.randint(3, 300))]
        bad = i % 4 == 0
        rows.append((i, " ".join(x + "%%%" for x in w) if bad else " ".join(w)))
        labels.append((i, 0 if bad else 1))
    rows += [(1000, ""), (1001, None), (1002, "ab " * 100_000)]
    docs, marks = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, quality int")
    net = quality.train(docs, marks)
    got = {r["doc_id"]: r["score"] for r in quality.with_score(docs, net).collect()}
    assert len(got) == len(rows) and all(0 <= s <= 1 for s in got.values())
    right = np.mean([(got[i] >= 0.7) == bool(y) for i, y in labels])
    assert right > 0.95
    again = quality.train(docs, marks)
    assert np.array_equal(net.filters, again.filters)
    assert {r["score"] for r in quality.with_score(docs, quality.train(docs, marks.limit(0))).collect()} == {1.0}
    assert quality.with_score(docs.limit(0), net).count() == 0
    assert not any(r["h"] for r in docs.where(quality.held_out(docs.doc_id)).select((quality.held_out(docs.doc_id) == False).alias("h")).collect())  # noqa: E712


def mirrored(n):
    """Two different words of two letters in mirrored order that polynomial hashes modulo 2^64 cannot tell apart."""
    s = [0]
    while len(s) < n:
        s += [1 - x for x in s]
    return "".join("ab"[x] for x in s), "".join("ba"[x] for x in s)


def test_words_that_weak_hashes_confuse(spark):
    from geohist.llm import jaccard

    for n in (1024, 2048, 4096):
        one, two = mirrored(n)
        docs = spark.createDataFrame([(1, one), (2, two)], "doc_id long, text string")
        assert sorted((r["doc_id"], r["component_id"]) for r in jaccard.link_components(docs).collect()) == [(1, 1), (2, 2)]
    lead = " ".join("w" + str(i) for i in range(12))
    docs = spark.createDataFrame([(1, f"{lead} {one}"), (2, f"{lead} {two}"), (3, f"{lead} {one}")], "doc_id long, text string")
    assert sorted((r["doc_id"], r["n_removed"]) for r in substring.remove_repeats(docs).collect()) == [(1, 0), (2, 0), (3, 13)]


def test_substring_clashing_columns_and_repeated_rows(spark):
    text = " ".join(f"w{i}" for i in range(20))
    docs = spark.createDataFrame([(1, text, 5, "x"), (1, text, 6, "y"), (2, text, 7, "z"), (None, None, None, None)], "doc_id long, text string, row long, starts string")
    assert sorted((r["doc_id"] or 0, r["n_removed"]) for r in substring.remove_repeats(docs).collect()) == [(0, 0), (1, 0), (1, 0), (2, 20)]

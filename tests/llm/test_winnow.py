import hashlib
import random
import struct

import regex
import xxhash
from geohist.llm import winnow

TOKEN = regex.compile(r"(?:(?![\p{Han}\p{Hiragana}\p{Katakana}])[\p{L}\p{M}\p{N}])+|\S")


def x(data, seed=42):
    h = xxhash.xxh64_intdigest(data, seed)
    return h - 2**64 if h >= 2**63 else h


def chain(values):
    h = 42
    for v in values:
        h = x(struct.pack("<q", v), h % 2**64)
    return h


def turn(v, by):
    return (v << by | v >> 64 - by) & (2**64 - 1)


def rolled(h, k):
    """Each gram's hash from the one before it."""
    now = 0
    for v in h[:k]:
        now = turn(now, 1) ^ v
    out = [now]
    for old, new in zip(h, h[k:]):
        now = turn(now, 1) ^ turn(old, k) ^ new
        out.append(now)
    return out


def grams(text):
    h = [x(t.encode()) for t in TOKEN.findall(text)]
    k, w = winnow.GRAM, winnow.WINDOW
    g = rolled([v % 2**64 for v in h], k) if len(h) >= k else [chain(h)] if h else []
    g = [v % 2**64 & (2**42 - 1) for v in g]
    key = lambda i: (g[i] - 2**42 if g[i] >= 2**41 else g[i], -i)
    out = []
    for i in range(max(1, len(g) - w + 1) if g else 0):
        best = min(range(i, min(i + w, len(g))), key=key)
        if not out or out[-1][1] != best:
            out.append((g[best], best))
    return out


def like(a, b):
    a, b = {h for h, _ in a}, {h for h, _ in b}
    return len(a & b) / len(a | b) if a | b else 1.0


def test_equals_brute_force(spark):
    rng = random.Random(6)
    rows = [(i * 3, " ".join(rng.choice(["aé", "b", "c.", "日本語", "dd-e"]) for _ in range(rng.randint(0, 60)))) for i in range(300)]
    rows += [(1, None), (2, ""), (4, "same same"), (5, "same same"), (10_000_000, "w " * 20_000), (7, "x"), (None, "last of all")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    texts = [(d, t or "") for d, t in sorted(rows, key=lambda r: 2**62 if r[0] is None else r[0])]
    got = {r["doc_id"]: r for r in winnow.edited_pairs(docs).withColumn("f", winnow.whole(winnow.F.col("grams"))).withColumn("e", winnow.whole(winnow.F.col("edited_grams"))).withColumn("at", winnow.places(winnow.F.col("grams"))).collect()}
    assert len(got) == len(rows)
    for (d, t), (_, nxt) in zip(texts, texts[1:] + texts[:1]):
        half = len(t) // 2
        edited = t[: len(t) - half] + nxt[:half]
        r = got[d]
        assert r["n_chars"] == len(t) and r["edited_sha256"] == hashlib.sha256(edited.encode()).hexdigest()
        assert r["f"] == "".join(f"{h:011X}" for h, _ in grams(t)) and r["e"] == "".join(f"{h:011X}" for h, _ in grams(edited)) and r["at"] == [at for _, at in grams(t)]
        assert abs(r["near_edited"] - like(grams(t), grams(edited))) < 1e-12 and abs(r["near_next"] - like(grams(t), grams(nxt))) < 1e-12
    real = {r["doc_id"]: [(y["hash"], y["at"]) for y in r["fingerprint"]] for r in winnow.fingerprints(docs).collect()}
    assert all(real[d] == grams(t) for d, t in texts)


def test_edges(spark):
    empty = spark.createDataFrame([], "doc_id long, text string, grams string, bucket string")
    assert winnow.edited_pairs(empty).count() == 0
    one = winnow.edited_pairs(spark.createDataFrame([(1, "abcd")], "doc_id long, text string")).collect()
    assert len(one) == 1 and one[0]["edited_sha256"] == hashlib.sha256(b"abab").hexdigest() and one[0]["near_next"] == 1.0
    twice = winnow.edited_pairs(spark.createDataFrame([(1, "ab"), (1, "ab"), (1, "cd")], "doc_id long, text string"))
    assert twice.count() == 3
    plan = winnow.edited_pairs(spark.createDataFrame([(1, "abcd")], "doc_id long, text string"))._jdf.queryExecution().toString()
    assert "Python" not in plan and "Arrow" not in plan

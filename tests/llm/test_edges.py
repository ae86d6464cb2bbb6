"""Long, repeated, empty and oddly named input of the operators that work row by row, and plain forms of them."""

import random

import numpy as np
import pytest
from geohist.llm import bpe, quality, wordpiece

P = pytest.importorskip("public_tokenizers")


def test_bpe_many_added_tokens(spark):
    from tokenizers import Tokenizer

    path = P.path("byte_bpe_50k.json")
    t = Tokenizer.from_file(path)
    texts = ["<|endoftext|>" * 2000, "a <|endoftext|><|endoftext|> b" * 700, "x" * 200_000, "x" * 200_000, None]
    docs = spark.createDataFrame([(7, x, 1, "k") for x in texts], "doc_id long, text string, n_tokens long, ids string")
    got = [r["ids"] for r in bpe.encode(docs.coalesce(1), path).collect()]
    assert got == [t.encode(x or "", add_special_tokens=False).ids for x in texts]
    assert bpe.round_trip_digests(docs, path).columns == ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]


def test_token_counts_of_repeated_long_and_no_rows(spark):
    path = P.path("piece_bpe_32k.model")
    docs = spark.createDataFrame([(1, "two words", 5, 6), (1, "two words", 5, 6), (2, "y" * 300_000, 5, 6), (None, None, 5, 6)], "doc_id long, text string, n_tokens long, n_words long")
    got = wordpiece.count_tokens(docs, path)
    assert got.columns == ["doc_id", "n_words", "n_tokens", "n_unknown"]
    rows = {(r["doc_id"], r["n_words"]): r["n_tokens"] for r in got.collect()}
    assert rows[(None, 0)] == 0 and rows[(2, 1)] > 1000 and got.count() == 4
    assert wordpiece.count_tokens(docs.limit(0), path).count() == 0


def plain_score(net, text: bytes) -> float:
    """The network's forward pass by loops over chunks, positions and filters."""
    pooled = []
    begin = 0
    while True:
        chunk = text[begin : begin + quality.CHUNK].ljust(quality.CHUNK, b"\0")
        best = np.full(quality.FILTERS, -np.inf)
        for p in range(0, quality.CHUNK - quality.WIDTH + 1, quality.STRIDE):
            x = np.concatenate([net.embed[c] for c in chunk[p : p + quality.WIDTH]])
            best = np.maximum(best, x @ net.filters)
        pooled.append(np.maximum(best + net.bias, 0))
        if begin + quality.CHUNK >= len(text):
            break
        begin += quality.HOP
    both = np.concatenate([np.mean(pooled, axis=0), np.max(pooled, axis=0)])
    return float(1 / (1 + np.exp(-(both @ net.weights + net.shift))))


def test_scores_equal_a_plain_forward_pass(spark):
    rng = random.Random(3)
    samples = [(np.frombuffer(bytes(rng.choices(range(97, 110 + 10 * (i % 2)), k=512)), np.uint8).reshape(1, -1), i % 2) for i in range(64)]
    net = quality.fit(samples, epochs=3)
    texts = ["", None, "short", "é" * 700, "".join(rng.choice("abcdefgh ") for _ in range(512)), "".join(rng.choice("abcdefgh ") for _ in range(3000)), "short"]
    docs = spark.createDataFrame([(i % 6, t, 0.5) for i, t in enumerate(texts)], "doc_id long, text string, other double").coalesce(1)
    got = [r["score"] for r in quality.with_score(docs, net).collect()]
    assert np.allclose(got, [plain_score(net, (t or "").encode()) for t in texts], atol=1e-5)
    with pytest.raises(ValueError, match="exists"):
        quality.with_score(docs.withColumnRenamed("other", "score"), net)


def test_a_very_long_text_is_scored_in_parts():
    import tracemalloc

    net = quality.fit([(np.full((1, 512), 97 + i % 2, np.uint8), i % 2) for i in range(32)], epochs=2)
    raw, off = np.full(4_000_000, 97, np.uint8), np.array([0, 4_000_000])
    tracemalloc.start()
    begin, end, first = quality.chunk_starts(off)
    pooled = np.concatenate([net.pooled(quality.chunks_at(raw, begin[i : i + 1024], end[i : i + 1024])) for i in range(0, len(begin), 1024)])
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert len(pooled) == len(begin) and peak < 8 * len(raw)
    assert np.isfinite(net.logits(pooled, first)).all()

import zlib

import numpy as np
import pytest
from geohist.llm import exact, packing

SCHEMA = "doc_id long, text string, slot string, sha string"


def test_trie_spills_and_keeps_owners():
    big, small = exact.OwnerTrie(), exact.OwnerTrie(400)
    words = [b"", b"a", b"ab", b"abc", b"b", b"abd", b"abc", b"", b"bcd" * 30, b"bcd" * 30, b"bce"]
    for t in (big, small):
        for i, w in enumerate(words):
            t.add(w, (-1, i, i), [i], 1)
    assert small.spilled
    assert sorted(map(repr, big.owners())) == sorted(map(repr, small.owners()))


def test_trie_spills_below_a_long_shared_prefix():
    head = b"h" * 2000
    keys = [head + bytes([i]) * 40 + bytes([j]) for i in range(60) for j in range(3)] * 2
    big, small = exact.OwnerTrie(), exact.OwnerTrie(5000)
    for t in (big, small):
        for i, w in enumerate(keys):
            t.add(w, (-1, i, i), [i], 1)
    assert len(small.spilled) > 1
    tidy = lambda t: sorted((o[0], sorted(o[1]), o[2]) for o in t.owners())
    assert tidy(big) == tidy(small)
    one = exact.OwnerTrie(100)
    one.add(b"x" * 5000, (-1, 1, 1), [1], 1)
    one.add(b"x" * 5000, (-1, 0, 0), [0], 1)
    assert [o[0] for o in one.owners()] == [(-1, 0, 0)]


def test_drop_exact_keeps_columns_of_any_name(spark):
    docs = spark.createDataFrame([(1, "a", 7, 8), (2, " a", 9, 10), (3, None, 1, 2)], "doc_id long, text string, row_mark long, __row__ long")
    got = exact.drop_exact(docs)
    assert got.columns == docs.columns and sorted(tuple(r) for r in got.collect()) == [(2, " a", 9, 10), (3, None, 1, 2)]


def test_exact_cases(spark):
    rows = [(3, "a b", "x", "y"), (1, "ab", "x", "y"), (2, " a b ", None, None), (2, " a b ", None, None), (4, None, "", ""), (5, "\n", "", ""), (None, "zz", "", ""), (7, "zz", "", ""), (8, "long " * 50_000, "", "")]
    docs = spark.createDataFrame(rows, SCHEMA)
    got = sorted((r["doc_id"] is not None and r["doc_id"] or 0, r["keep_id"], r["group_size"], r["kept"]) for r in exact.exact_owners(docs).collect())
    assert [g for g in got if g[0] in (1, 2, 3)] == [(1, 2, 4, False), (2, 2, 4, False), (2, 2, 4, True), (3, 2, 4, False)]
    assert [g[1:] for g in got if g[0] in (4, 5)] == [(5, 2, False), (5, 2, True)]
    assert [g for g in got if g[0] == 7] == [(7, 7, 2, True)]
    kept = exact.drop_exact(docs)
    assert kept.columns == docs.columns and kept.count() == 4
    assert exact.exact_owners(docs.limit(0)).count() == 0


def test_difference_and_spread():
    rng = np.random.default_rng(3)
    for n in (1, 2, 17, 400):
        sizes = rng.integers(1, 2000, n)
        way, ways = packing.spread(sizes, 2048)
        sums = np.bincount(way, weights=sizes, minlength=ways)
        assert sums.max() <= 2048 and ways >= -(-sizes.sum() // 2048)
        if n == 400:
            assert sums.max() - sums.min() < 100 and ways <= -(-sizes.sum() // 2048) + 6


def test_pack_round_trip(spark):
    P = pytest.importorskip("public_tokenizers")
    from tokenizers import Tokenizer

    path = P.path("word_bpe_49k.json")
    texts = ["Hello World's end\x1cX", "", None, "é é <|endoftext|> don't 123", "word " * 5000, "  \n\t ", "ÀB c" * 700]
    docs = spark.createDataFrame([(i // 2, t, "x", "y") for i, t in enumerate(texts)], "doc_id long, text string, start string, offset string").coalesce(1)
    for group in (packing.GROUP_PIECES, 5):
        check_pieces(packing.pack(docs, path, with_ids=True, group=group).collect(), texts, Tokenizer.from_file(path))
    assert packing.pack(docs.limit(0), path).count() == 0


def differenced(sizes, ways):
    """Plain multiway differencing on full tuples, zeros for empty ways."""
    parts = [(-int(x), i, [0] * (ways - 1) + [int(x)]) for i, x in enumerate(sizes)]
    serial = len(parts)
    while len(parts) > 1:
        parts.sort()
        a, b = parts[0][2], parts[1][2]
        s = sorted(x + y for x, y in zip(a, b[::-1]))
        parts = parts[2:] + [(s[0] - s[-1], serial, s)]
        serial += 1
    return parts[0][2]


def test_difference_equals_the_plain_form():
    rng = np.random.default_rng(8)
    for n, ways in ((1, 3), (7, 3), (40, 4), (90, 17), (200, 23)):
        sizes = rng.integers(1, 500, n)
        way = packing.difference(sizes, ways)
        assert sorted(np.bincount(way, weights=sizes, minlength=ways).astype(int)) == differenced(sizes, ways)


def test_windows_rise_and_stay_near_equal():
    rng = np.random.default_rng(5)
    sizes = rng.integers(1, 513, 3000)
    way, ways = packing.spread(sizes, 2048)
    sums, least = np.bincount(way, weights=sizes, minlength=ways), -(-int(sizes.sum()) // 2048)
    assert sums.max() <= 2048 and sums.max() - sums.min() < 40 and least <= ways <= 1.02 * least + 1
    assert packing.spread(np.array([1500, 1500, 1500]), 2048)[1] == 3  # two could hold the sum, not the items


def check_pieces(got, texts, t):
    by: dict = {}
    for r in got:
        assert zlib.crc32(np.array(r["ids"], "<u4").tobytes()) == r["ids_crc32"] and r["length"] == len(r["ids"])
        by.setdefault(r["row_id"], []).append(r)
    order = sorted(by)
    for k, text in zip(order, texts):
        ids = []
        for r in sorted(by[k], key=lambda r: r["start"]):
            assert r["start"] == len(ids)
            ids += r["ids"]
        assert ids == [*t.encode(text or "", add_special_tokens=False).ids, 1] and by[k][0]["doc_tokens"] == len(ids)
    seq: dict = {}
    for r in got:
        seq.setdefault(r["sequence_id"], []).append(r)
    for rs in seq.values():
        at = 0
        for r in sorted(rs, key=lambda r: r["offset"]):
            assert r["offset"] == at
            at += r["length"]
        assert at <= 2048

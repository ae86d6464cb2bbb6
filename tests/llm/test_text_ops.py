import hashlib
import random

import pytest
from geohist.llm import bpe, html, urls, wordpiece

P = pytest.importorskip("public_tokenizers")


def test_bpe_equals_library(spark):
    from tokenizers import Tokenizer

    path = P.path("byte_bpe_50k.json")
    t, c, rng = Tokenizer.from_file(path), bpe.codec(path), random.Random(1)
    texts = ["", None, "a", "Hello world's  \n\n x<|endoftext|> y", "  <|endoftext|>", "࢏Ԙ é 日本語", "a" * 3000, "\x00<|endoftext|>", " \x1c\x85  x"]
    texts += ["".join(rng.choice("abcdeth  insZQ'srm1239\n\t.,-éßñ中") for _ in range(rng.randint(0, 60))) for _ in range(300)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").coalesce(2)
    digest = {r["doc_id"]: r for r in bpe.round_trip_digests(docs, path).collect()}
    ids = bpe.encode(docs, path)
    coded, back = {r["doc_id"]: r for r in ids.collect()}, {r["doc_id"]: r["text"] for r in bpe.decode(ids, path).collect()}
    for i, x in enumerate(texts):
        want = t.encode(x or "", add_special_tokens=False).ids
        assert coded[i]["ids"] == want and digest[i]["n_tokens"] == len(want)
        assert back[i] == t.decode(want, skip_special_tokens=False)
        assert digest[i]["ids_sha256"] == hashlib.sha256(",".join(map(str, want)).encode()).hexdigest()
        assert digest[i]["decoded_sha256"] == hashlib.sha256(back[i].encode()).hexdigest()
    assert c.decode_bytes.__self__ is c and bpe.encode(docs.limit(0), path).count() == 0


def test_wordpiece_counts(spark):
    from tokenizers import Tokenizer, models, pre_tokenizers

    a, b = wordpiece.pieces_of_model(P.path("piece_bpe_32k.model"))
    vocab = {"[UNK]": 0}
    for p in [*a, *("##" + x for x in b)]:
        vocab.setdefault(p, len(vocab))
    t = Tokenizer(models.WordPiece(vocab, unk_token="[UNK]", max_input_chars_per_word=10**9))
    t.pre_tokenizer = pre_tokenizers.BertPreTokenizer()
    rng = random.Random(5)
    texts = ["", None, "Hello, worlds! don't", "x" * 5000, "éß 日本 ☃"] + ["".join(rng.choice("abcdeth  insZQ'srm1239\n\t.,-éßñ") for _ in range(rng.randint(0, 80))) for _ in range(200)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").coalesce(2)
    got = {r["doc_id"]: r for r in wordpiece.count_tokens(docs, P.path("piece_bpe_32k.model")).collect()}
    for i, x in enumerate(texts):
        e = t.encode(x or "", add_special_tokens=False)
        assert (got[i]["n_tokens"], got[i]["n_unknown"]) == (len(e.ids), e.ids.count(0)), x


PAGE = """<!DOCTYPE html><html><head><title>no</title><style>p{}</style></head><body><header><h1>Site</h1></header><nav><ul><li><a href="/a">menu</a></li></ul></nav>
<div class="ad">Buy this long advert text now and be happy for ever.</div><div id="cookie-notice">We use cookies.</div><article><h1>Title &amp; more</h1><p><b>One
 two<br><p>Three&nbsp;four<p>five <a href=x>six</a>.</p><script>var t="</p>";</script><div class="comments"><p>reader says</p></div></article><aside>side</aside><form>go <input></form><footer>&copy; foot</footer></body></html>"""


def test_html(spark):
    want = "Title & more\nOne two\nThree four\nfive six."
    assert html.main_text(PAGE) == want
    plain = "<body><div class=menu><a href=1>a</a></div><div><div><p>" + "long text here. " * 20 + "</p><p>" + "more of it. " * 20 + "</p></div></div><div class=footer>x</div>"
    assert html.main_text(plain) == ("long text here. " * 20).strip() + "\n" + ("more of it. " * 20).strip()
    rows = [(1, "u", PAGE), (2, None, None), (3, "u", ""), (4, "u", "<p"), (5, "u", "plain"), (6, "u", "<div>" * 3000 + "deep"), (1, "u", PAGE)]
    got = html.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()
    assert sorted((r["page_id"], r["text"], r["n_chars"]) for r in got)[:2] == [(1, want, len(want))] * 2
    assert {r["page_id"]: r["text"] for r in got if r["page_id"] > 1} == {2: "", 3: "", 4: "", 5: "plain", 6: "deep"}
    assert html.extract(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


def test_urls(spark):
    rows = [(i, u) for i, u in enumerate(["http://A.Example.NET/en/1?x=/de/#f", "http://example.com/de/3", "x.org/fr/", None, "", "ftp://a.org/fr/", "http://a.net", "http://net/", "http://notnet/", "http://spam.example.com/buy/7?pill=1", "http://ok.example.com/read/7"])]
    pages = spark.createDataFrame(rows, "page_id long, url string")
    labelled = spark.createDataFrame([(f"http://spam.example.com/buy/{i}", True) for i in range(20)] + [(f"http://good.example.com/read/{i}", False) for i in range(60)], "url string, bad boolean")
    mined = urls.mine_rules(labelled, 0.05, 0.8)
    kept = {tuple(r["rule_tokens"]) for r in mined.collect()}
    assert ("host:spam",) in kept and all(len(k) == 1 for k in kept)
    got = {r["page_id"]: (r["host"], r["path"], r["rule"], r["verdict"]) for r in urls.judge(pages, mined).collect()}
    assert got[0] == ("a.example.net", "/en/1", "example.net/en/", "allow")
    assert got[1] == ("example.com", "/de/3", "example.com/de/", "block")
    assert got[2] == got[3] == got[4] == ("", "", None, "allow")
    assert got[5] == ("a.org", "/fr/", "org/fr/", "allow")
    assert got[6] == ("a.net", "", None, "allow") and got[7][2:] == ("net/", "block") and got[8][2:] == (None, "allow")
    assert got[9][2:] == (None, "block") and got[10][2:] == (None, "allow")
    assert urls.mine_rules(labelled.limit(0)).count() == 0

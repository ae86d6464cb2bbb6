from geohist.llm import urls


def test_each_row_is_judged_by_its_own_url(spark):
    bad, good = "http://spam.example.org/casino/1", "http://fine.example.org/news/2"
    rows = spark.createDataFrame([(None, bad), (1, bad), (1, good), (None, good), (2, None)], "page_id long, url string")
    item = rows.where(rows.url == bad).select(urls.tokens_of(urls.F.col("url")).alias("i")).first()["i"]
    only = [x for x in item if x not in rows.where(rows.url == good).select(urls.tokens_of(urls.F.col("url")).alias("i")).first()["i"]][:1]
    mined = spark.createDataFrame([(only, 0.9, 0.1)], "rule_tokens array<string>, confidence double, support double")
    got = sorted((r["page_id"] or 0, r["host"], r["verdict"]) for r in urls.judge(rows, mined, ()).collect())
    assert got == [(0, "fine.example.org", "allow"), (0, "spam.example.org", "block"), (1, "fine.example.org", "allow"), (1, "spam.example.org", "block"), (2, "", "allow")]


def test_rules_equal_enumeration(spark):
    import itertools
    import random

    rng, rows = random.Random(7), []
    for i in range(300):
        parts = [rng.choice(["spam", "news"]), rng.choice(["buy", "read"]), rng.choice(["x", "y", "z"])]
        rows.append((f"http://{parts[0]}.example.org/{parts[1]}/{parts[2]}/{i}", rng.random() < (0.95 if parts[:2] == ["spam", "buy"] else 0.9 if parts[2] == "z" else 0.1)))
    frame = spark.createDataFrame(rows, "url string, bad boolean")
    items = [(frozenset(r["i"]), r["bad"]) for r in frame.select(urls.tokens_of(urls.F.col("url")).alias("i"), "bad").collect()]
    share, every = sum(b for _, b in items) / len(items), sorted({x for i, _ in items for x in i})
    found = {}
    for size in range(1, 6):
        for t in itertools.combinations(every, size):
            hit = [b for i, b in items if i.issuperset(t)]
            if sum(hit) >= 20 and sum(hit) / len(hit) >= 0.6 and sum(hit) / len(hit) / share >= 1.5:
                found[t] = sum(hit) / len(hit)
    want = {t for t, c in found.items() if not any(set(u) < set(t) and d >= c for u, d in found.items())}
    got = {tuple(r["rule_tokens"]): r["confidence"] for r in urls.mine_rules(frame).collect()}
    assert set(got) == want and len(want) > 1 and all(abs(got[t] - found[t]) < 1e-9 for t in want)


def test_few_labelled_rows_make_no_rule(spark):
    few = spark.createDataFrame([(f"http://spam.example.org/{i}", i % 2 == 0) for i in range(30)], "url string, bad boolean")
    assert urls.mine_rules(few).count() == 0 and urls.mine_rules(few.limit(5)).count() == 0


def test_host_path_and_rule_equal_sql(spark):
    import duckdb

    path = "/root/testdata/sf0.001/pages.parquet"
    got = sorted((r["page_id"], r["host"], r["path"], r["rule"], r["verdict"]) for r in urls.judge(spark.read.parquet(path), spark.createDataFrame([], "rule_tokens array<string>, confidence double, support double")).collect())
    fits = [f"""CASE WHEN (host = '{h}' OR host LIKE '%.{h}') AND starts_with(path, '{p}') THEN ['{len(h + p):04d}', '{h + p}', '{v}'] END""" for v, h, p in urls.RULES]
    sql = f"""WITH u AS (SELECT page_id, regexp_extract(url, '(?s)^.*?://([^/?#]*)', 1) AS h, regexp_extract(url, '(?s)^.*?://[^/?#]*([^?#]*)', 1) AS path FROM '{path}'),
      v AS (SELECT page_id, translate(h, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, path FROM u),
      w AS (SELECT page_id, host, path, list_sort(list_filter([{", ".join(fits)}], lambda x: x IS NOT NULL), 'DESC') AS fit FROM v)
      SELECT page_id, host, path, fit[1][2], coalesce(fit[1][3], 'allow') FROM w"""
    assert got == sorted(duckdb.sql(sql).fetchall()) and len({r[3] for r in got}) > 1


def test_long_urls_and_clashing_columns(spark):
    long = "http://a.example.net/" + "x/" * 50_000
    rows = spark.createDataFrame([(1, long, "i", "h"), (1, long, "i", "h"), (2, "", "i", "h")], "page_id long, url string, items string, hand string")
    got = urls.judge(rows, spark.createDataFrame([], "rule_tokens array<string>, confidence double, support double")).collect()
    assert sorted((r["page_id"], len(r["path"]), r["rule"], r["verdict"]) for r in got) == [(1, 100_001, "net/", "block")] * 2 + [(2, 0, None, "allow")]

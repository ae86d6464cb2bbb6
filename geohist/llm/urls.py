"""URL filters: host and path rules by hand, and association rules mined from labelled URLs."""

from __future__ import annotations

import string
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Rules of the registered query: (verdict, host, path).
RULES = (("block", "net", "/"), ("allow", "example.net", "/en/"), ("block", "example.com", "/de/"), ("allow", "org", "/fr/"))

_CUT = "(?s)^.*?://([^/?#]*)([^?#]*)"
BAD = "=bad"


def ascii_lower(c: Column) -> Column:
    return F.translate(c, string.ascii_uppercase, string.ascii_lowercase)


def host_of(url: Column) -> Column:
    """After the first :// up to / ? # or the end, A-Z lower-cased; empty without a ://."""
    return ascii_lower(F.coalesce(F.regexp_extract(url, _CUT, 1), F.lit("")))


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, _CUT, 2), F.lit(""))


def tokens_of(url: Column) -> Column:
    """Items of a URL: labels and whole suffixes of its host, words of its path, names of its parameters; numbers count as one item."""
    host, path = host_of(url), path_of(url)
    word = lambda x: F.when(x.rlike("^[0-9]+$"), F.lit("#")).otherwise(x)
    labels = F.filter(F.split(host, "[.]"), lambda x: x != "")
    items = F.flatten(
        F.array(
            F.transform(labels, lambda x: F.concat(F.lit("host:"), x)),
            F.when(host != "", F.array(F.concat(F.lit("site:"), host))).otherwise(F.array().cast("array<string>")),
            F.transform(F.filter(F.split(ascii_lower(path), "[^a-z0-9]+"), lambda x: x != ""), lambda x: F.concat(F.lit("path:"), word(x))),
            F.transform(F.filter(F.split(ascii_lower(F.coalesce(F.regexp_extract(url, "(?s)^[^#]*?[?]([^#]*)", 1), F.lit(""))), "&"), lambda x: x != ""), lambda x: F.concat(F.lit("arg:"), F.split(x, "=")[0])),
        )
    )
    return F.array_distinct(items)


def mine_rules(labelled: DataFrame, min_support: float = 0.002, min_confidence: float = 0.6, min_lift: float = 1.5, min_rows: int = 20) -> DataFrame:
    """Rules (rule_tokens, confidence, support) whose URLs are mostly bad, from (url, bad boolean) rows.

    FP-growth over the items of each labelled URL and the item of its label; rules that conclude the label stay
    if support, confidence and lift reach their bounds and no shorter rule inside them is as sure. A rule needs
    min_support of all labelled rows and min_rows of them, so that few rows make no rule. No labelled rows, or none
    that pass, give no rules; null URLs and labels are left out, repeated rows count each.
    """
    from pyspark.ml.fpm import FPGrowth

    spark = labelled.sparkSession
    schema = "rule_tokens array<string>, confidence double, support double"
    baskets = labelled.where("url is not null and bad is not null").select(F.when(F.col("bad"), F.array_append(tokens_of(F.col("url")), F.lit(BAD))).otherwise(tokens_of(F.col("url"))).alias("items")).where("size(items) > 0")
    n = baskets.count()
    if n < min_rows:
        return spark.createDataFrame([], schema)
    model = FPGrowth(itemsCol="items", minSupport=max(min_support, (min_rows - 0.5) / n), minConfidence=min_confidence).fit(baskets)
    rules = model.associationRules.where(F.col("consequent") == F.array(F.lit(BAD))).where(F.coalesce(F.col("lift"), F.lit(0.0)) >= min_lift)
    rules = rules.select(F.array_sort("antecedent").alias("rule_tokens"), "confidence", "support")
    parts = rules.select("rule_tokens", "confidence", "support", F.explode("rule_tokens").alias("token"))
    inner = rules.select(F.col("rule_tokens").alias("inside"), F.col("confidence").alias("inside_confidence"), F.col("rule_tokens")[0].alias("token"))
    covered = parts.join(inner, "token").where("size(inside) < size(rule_tokens) and inside_confidence >= confidence and size(array_except(inside, rule_tokens)) = 0").select("rule_tokens")
    return rules.join(covered, "rule_tokens", "left_anti")


def match_rules(pages: DataFrame, rules: DataFrame, url_col: str = "url") -> DataFrame:
    """(items, url_confidence) of the distinct item sets of URLs that some mined rule fits, by an inverted index.

    The index lists each rule under one item, its longest (the most telling); a URL looks its items up and a rule fits
    if it has all the rule's items. Spark chooses by size whether the index is sent to all.
    """
    anchor = F.transform("rule_tokens", lambda t: F.struct(F.length(t).alias("n"), t.alias("token")))
    index = rules.select(F.array_max(anchor)["token"].alias("token"), "rule_tokens", "confidence")
    rows = pages.select(tokens_of(F.col(url_col)).alias("items")).distinct()
    hits = rows.select("items", F.explode("items").alias("token")).join(index, "token").where("size(array_except(rule_tokens, items)) = 0")
    return hits.groupBy("items").agg(F.max("confidence").alias("url_confidence"))


def rule_of(host: Column, path: Column, rules: Sequence[tuple[str, str, str]] = RULES) -> Column:
    """Struct (verdict, rule) of the longest rule that fits, null if none; a rule fits its host and subdomains and all paths that start with its own."""
    if not rules:
        return F.lit(None).cast("struct<n:int,rule:string,verdict:string>")
    fit = [F.when(((host == h) | host.endswith("." + h)) & path.startswith(p), F.struct(F.lit(len(h + p)).alias("n"), F.lit(h + p).alias("rule"), F.lit(v).alias("verdict"))) for v, h, p in rules]
    return F.greatest(*fit) if len(fit) > 1 else fit[0]


def judge(pages: DataFrame, mined: DataFrame, rules: Sequence[tuple[str, str, str]] = RULES, id_col: str = "page_id", url_col: str = "url") -> DataFrame:
    """One row for each row of pages: page_id, host, path, rule, verdict, url_confidence.

    The longest hand-made rule decides; without one a URL that a mined rule fits is blocked. Null and empty URLs,
    and those without ://, have empty host and path and are allowed. Each row is judged by its own URL, whatever its page_id,
    and repeated rows come out as often; other columns are not read, whatever their names; an empty table gives an empty result.
    """
    url = F.col(url_col)
    base = pages.select(F.col(id_col).alias("page_id"), url.alias("url"), host_of(url).alias("host"), path_of(url).alias("path"), F.when(url.isNotNull(), tokens_of(url)).alias("items"))
    found = match_rules(pages.where(url.isNotNull()), mined, url_col)
    hand = rule_of(F.col("host"), F.col("path"), rules)
    out = base.join(found, "items", "left").withColumn("hand", hand)
    verdict = F.coalesce(F.col("hand.verdict"), F.when(F.col("url_confidence").isNotNull(), F.lit("block")).otherwise(F.lit("allow")))
    return out.select("page_id", "host", "path", F.col("hand.rule").alias("rule"), verdict.alias("verdict"), "url_confidence")


def labelled_urls(pages: DataFrame, labels: DataFrame) -> DataFrame:
    """URLs of pages whose document is labelled (the last number of the path names it): bad means low quality or toxic."""
    doc = F.expr("try_cast(regexp_extract(url, '://[^/?#]*/(?:[^/?#]*/)*?([0-9]+)', 1) as bigint)")
    return pages.select("url", doc.alias("doc_id")).join(labels, "doc_id").select("url", ((F.col("quality") == 0) | (F.col("toxic") == 1)).alias("bad"))


def op9_url_filter(spark, sf_dir: str) -> DataFrame:
    pages, labels = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("pages", "labels"))
    mined = mine_rules(labelled_urls(pages, labels))
    return judge(pages.select("page_id", "url"), mined)

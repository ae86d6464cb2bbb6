"""Document fingerprints by winnowing, in DataFrame functions only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

#: A gram is four tokens, a window eight grams: any shared run of 11 tokens leaves a common fingerprint.
GRAM, WINDOW = 4, 8
#: A token is a run of letters, marks and digits, one ideograph or kana, or any other character that is no white space.
TOKEN = r"[\p{L}\p{M}\p{N}&&[^\p{IsHan}\p{IsHiragana}\p{IsKatakana}]]+|\S"
#: A selected gram is one long: 42 bits of hash above 22 bits of reversed position, so that the smallest is rightmost among equals.
_BITS, _MASK = 22, (1 << 22) - 1


def _entry(h: Column, at: Column) -> Column:
    return F.shiftleft(h, _BITS).bitwiseOR(F.lit(_MASK) - at.bitwiseAND(F.lit(_MASK)).cast("long"))


def _turned(h: Column, by: int) -> Column:
    """The bits of a long, turned left."""
    return F.shiftleft(h, by).bitwiseOR(F.shiftrightunsigned(h, 64 - by)) if by else h


def rolling(h: Column, at: Column, first: Column) -> Column:
    """Cyclic-polynomial hash of the GRAM tokens from `at` on: their hashes, each turned by one bit less than the one before it, exclusive-ored.

    From one gram to the next it rolls: turned by one bit, without the token that leaves (turned GRAM bits) and with the
    one that enters. Array functions carry no state from element to element, so its GRAM terms are put together here.
    """
    out = _turned(first, GRAM - 1)
    for j in range(1, GRAM):
        out = out.bitwiseXOR(_turned(F.get(h, at + j), GRAM - 1 - j))
    return out


def with_fingerprint(df: DataFrame, text_col: str, out: str) -> DataFrame:
    """df and a column of selected grams (array<long>, in text order) of a text column that holds no nulls.

    Rolling hashes of GRAM tokens; of each WINDOW consecutive grams the smallest is kept, the rightmost if tied. Texts
    of fewer tokens than a gram have one gram, the whole; of fewer grams than a window, one window; without tokens, none.
    Positions are kept modulo 2^22: in texts of more tokens, of equal grams on both sides of a multiple the left one is kept.
    """
    # Each step is a column of its own, so that none is evaluated twice.
    t, h, g, m2, m4, m8 = (f"__{out}_{x}__" for x in ("t", "h", "g", "m2", "m4", "m8"))
    n = F.size(h)
    kept = list(df.columns)
    df = df.withColumn(t, F.regexp_extract_all(F.col(text_col), F.lit(TOKEN), F.lit(0)))
    df = df.withColumn(h, F.transform(t, lambda x: F.xxhash64(x)))
    rolled = F.transform(F.slice(h, F.lit(1), n - GRAM + 1), lambda x, i: _entry(rolling(F.col(h), i, x), i))
    df = df.withColumn(g, F.when(n >= GRAM, rolled).when(n > 0, F.array(_entry(F.xxhash64(h), F.lit(0)))).otherwise(F.array().cast("array<long>")))
    enough = F.size(g) >= WINDOW
    for source, target, step in ((g, m2, 1), (m2, m4, 2), (m4, m8, 4)):
        rest = F.size(source) - step
        df = df.withColumn(target, F.when(enough, F.zip_with(F.slice(source, F.lit(1), rest), F.slice(source, F.lit(1 + step), rest), lambda a, b: F.least(a, b))))
    chosen = F.when(enough, F.array_distinct(m8)).when(F.size(g) > 0, F.array(F.array_min(g))).otherwise(F.col(g))
    return df.select(*(F.col(f"`{c}`") for c in kept), chosen.alias(out))


def hashes(grams: Column) -> Column:
    """The distinct gram hashes of a fingerprint."""
    return F.array_distinct(F.transform(grams, lambda c: F.shiftrightunsigned(c, _BITS)))


def positions(grams: Column) -> Column:
    """Fingerprint as array<struct<hash, at>>; `at` is the gram's first token (modulo 2^22 in texts of more tokens)."""
    return F.transform(grams, lambda c: F.struct(F.shiftrightunsigned(c, _BITS).alias("hash"), (F.lit(_MASK) - c.bitwiseAND(F.lit(_MASK))).cast("int").alias("at")))


def places(grams: Column) -> Column:
    """The position of each hash that `whole` prints, array<int>."""
    return F.transform(grams, lambda c: (F.lit(_MASK) - c.bitwiseAND(F.lit(_MASK))).cast("int"))


def whole(grams: Column) -> Column:
    """Fingerprint as text with nothing cut: all 42 bits of each hash as eleven hexadecimal digits, in order, without separators."""
    return F.array_join(F.transform(grams, lambda c: F.lpad(F.hex(F.shiftrightunsigned(c, _BITS)), 11, "0")), "")


def likeness(a: Column, b: Column) -> Column:
    """Shared share of two arrays of distinct hashes; two empty ones are alike."""
    both = F.size(F.array_intersect(a, b))
    union = F.size(a) + F.size(b) - both
    return F.when(union == 0, F.lit(1.0)).otherwise(both / union)


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, fingerprint array<struct<hash, at>>) of every row; null counts as empty, repeated rows come out as often, other columns are not read."""
    rows = docs.select(F.col(id_col).alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    return with_fingerprint(rows, "text", "grams").select("doc_id", positions(F.col("grams")).alias("fingerprint"))


def ranged(rows: DataFrame, per_bucket: int = 2000, cuts: int = 64, most: int = 16384) -> tuple[DataFrame, int]:
    """rows and a bucket number that grows with doc_id: even quantile ranges, each cut in even steps; null ids come last."""
    n, q = rows.agg(F.count(F.lit(1)), F.percentile_approx("doc_id", [i / cuts for i in range(1, cuts)], 10_000)).first()
    edges = sorted(set(q or []))
    inner = max(1, min(most // cuts, -(-n // (per_bucket * cuts))))
    i = F.size(F.filter(F.array(*(F.lit(e) for e in edges)), lambda e: e <= F.col("doc_id"))) if edges else F.lit(0)
    width = [b - a for a, b in zip(edges, edges[1:])]
    at = F.lit(0)
    if inner > 1 and width:
        low, wide = F.get(F.array(*(F.lit(e) for e in edges)), i - 1), F.get(F.array(*(F.lit(float(w)) for w in width)), i - 1)
        at = F.coalesce(F.least(F.floor((F.col("doc_id") - low) * inner / wide), F.lit(inner - 1)).cast("int"), F.lit(0))
    last = (len(edges) + 1) * inner
    return rows.withColumn("bucket", F.when(F.col("doc_id").isNull(), F.lit(last)).otherwise(i * inner + at).cast("int")), last + 1


def edited_pairs(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Every row with the fingerprint of its text, of its text edited with the next document's, and likenesses.

    The next document is the one of next larger doc_id, the first after the last; rows that repeat an id follow in order of
    their text's hash, a null id comes last. Rows meet in ranges of ids: one shuffle of the texts, no single task;
    the first row of the next range is added to each range as a guest. An only row is its own next document.
    """
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    rows, _ = ranged(rows)
    order = [F.col("doc_id").asc_nulls_last(), F.xxhash64("text"), F.col("text")]
    # Heads: one row for each bucket, whose number is bounded; each becomes the guest of the bucket before it.
    first = rows.groupBy("bucket").agg(F.min("doc_id").alias("doc_id"))
    before = W.orderBy("bucket")
    everyone = W.orderBy("bucket").rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    host = F.coalesce(F.lag("bucket").over(before), F.last("bucket").over(everyone))
    heads = first.select(F.col("bucket").alias("head_bucket"), F.col("doc_id").alias("head_id"), host.alias("host"))
    found = rows.join(F.broadcast(heads), (F.col("bucket") == F.col("head_bucket")) & F.col("doc_id").eqNullSafe(F.col("head_id")))
    guests = found.groupBy("host").agg(F.min(F.struct(F.xxhash64("text").alias("h"), F.col("text").alias("text"))).alias("x")).select(F.lit(None).cast("long").alias("doc_id"), F.col("x.text").alias("text"), F.col("host").alias("bucket"), F.lit(True).alias("guest"))
    every = rows.withColumn("guest", F.lit(False)).unionByName(guests).repartition("bucket")
    every = with_fingerprint(every, "text", "grams")
    w = W.partitionBy("bucket").orderBy("guest", *order)
    every = every.withColumn("next_text", F.lead("text").over(w)).withColumn("next_grams", F.lead("grams").over(w)).where("not guest")
    half = F.floor(F.length("text") / 2).cast("int")
    every = every.select(
        "doc_id",
        F.length("text").cast("long").alias("n_chars"),
        F.concat(F.substring(F.col("text"), F.lit(1), F.length("text") - half), F.substring(F.col("next_text"), F.lit(1), half)).alias("edited"),
        "grams",
        "next_grams",
    )
    every = with_fingerprint(every, "edited", "edited_grams")
    every = every.withColumn("own_hashes", hashes(F.col("grams")))
    return every.select(
        "doc_id",
        "n_chars",
        F.sha2(F.col("edited").cast("binary"), 256).alias("edited_sha256"),
        "grams",
        "edited_grams",
        likeness(F.col("own_hashes"), hashes(F.col("edited_grams"))).alias("near_edited"),
        likeness(F.col("own_hashes"), hashes(F.col("next_grams"))).alias("near_next"),
    )


def op3_fingerprint(spark, sf_dir: str) -> DataFrame:
    pairs = edited_pairs(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    grams, edited = F.col("grams"), F.col("edited_grams")
    return pairs.select(
        "doc_id",
        "n_chars",
        "edited_sha256",
        whole(grams).alias("fingerprint"),
        whole(edited).alias("edited_fingerprint"),
        "near_edited",
        "near_next",
        places(grams).alias("fingerprint_at"),
        places(edited).alias("edited_fingerprint_at"),
    )

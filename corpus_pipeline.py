"""A training corpus from documents: rejects low quality, drops copies and near copies, cuts repeated passages, packs tokens.

Every stage takes null and empty texts (as empty), repeated rows and ids (told apart by their place), ties (each stage
says which row stays), empty tables, and further columns of any name, which come out as they went in.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from geohist.llm import exact, jaccard, packing, quality, substring
from geohist.llm.common import free_name, row_id, stored


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the network, trained on labels of these documents, scores 0.7 or more; null texts count as empty."""
    labels, score = spark.read.parquet(f"{sf_dir}/labels.parquet"), free_name(docs, "score")
    return quality.with_score(docs, quality.train(docs, labels), score).where(F.col(score) >= 0.7).drop(score)


def drop_exact(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts the one with most code points stays, then the smallest doc_id."""
    return exact.drop_exact(docs)


def drop_near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents linked by a similarity of 0.8 the smallest doc_id stays (null last, then the first row)."""
    found = jaccard.link_components(docs, counts=False).select("row", "doc_id", "component")
    row = free_name(docs, "row")
    keep = found.groupBy("component").agg(F.min(F.struct(F.col("doc_id").isNull(), "doc_id", "row")).alias("x")).select(F.col("x.row").alias(row))
    return docs.withColumn(row, row_id()).join(keep, row, "left_semi").drop(row)


def cut_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Words of windows that a document of smaller id has too are cut; n_chars follows. Other texts stay as they are."""
    row, kept = free_name(docs, "row"), free_name(docs, "kept_text")
    clean = substring.remove_repeats(docs, with_text=True).where("n_removed > 0").select(F.col("row").alias(row), F.col("kept_text").alias(kept))
    out = docs.withColumn(row, row_id()).join(clean, row, "left")
    length = F.when(F.col(kept).isNotNull(), F.length(kept).cast("long")).otherwise(F.col("n_chars")) if "n_chars" in docs.columns else None
    new = {"text": F.coalesce(kept, "text"), "n_chars": length}
    return out.select(*(new[c].alias(c) if c in new else F.col(f"`{c}`") for c in docs.columns))


def pack_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the kept texts in sequences of 2048 tokens."""
    return packing.pack(docs, public_tokenizers.path("word_bpe_49k.json")).drop("row_id")


STAGES = [("quality classifier", keep_quality), ("exact dedup", drop_exact), ("n-gram Jaccard join", drop_near), ("substring dedup", cut_repeats), ("packing", pack_tokens)]

#: A trained network has no SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; each result is written to the shared folder and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for _, stage in STAGES:
        docs = stored(stage(spark, docs, sf_dir), spark)
    return docs

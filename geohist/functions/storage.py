"""Tables written between steps, in the folder that the cluster shares."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession, what: str) -> str:
    """A new path in the folder that the session names; without one, a local path on one machine only."""
    base = spark.conf.get("spark.checkpoint.dir", "")
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        base = f"file://{tempfile.gettempdir()}/geohist-shared"
    return f"{base}/{what}-{uuid.uuid4().hex}"


def stored(df: DataFrame) -> DataFrame:
    """Written and read back: cuts lineage, survives lost executors. The path is the session's to clean, as results still read it."""
    path = shared_folder(df.sparkSession, "levels")
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)

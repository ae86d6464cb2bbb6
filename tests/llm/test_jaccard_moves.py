"""Op 1: how often its sketches and list entries move."""

import re

import numpy as np
import pytest

pytest.importorskip("xxhash")

from geohist.llm import common, jaccard  # noqa: E402


@pytest.fixture
def conf(spark):
    was = {}

    def put(key, value):
        was.setdefault(key, spark.conf.get(key, None))
        spark.conf.set(key, value)

    yield put
    for k, v in was.items():
        spark.conf.set(k, v) if v is not None else spark.conf.unset(k)


def test_a_small_sketch_takes_one_job_however_many_partitions(spark, conf):
    conf("spark.sql.shuffle.partitions", "40")
    conf("spark.sql.adaptive.coalescePartitions.enabled", "false")
    rows = [(i, np.full(4, i + t, np.uint8).tobytes()) for t in range(2) for i in range(8)]
    merged = common.merged_slices(spark.createDataFrame(rows, "slice int, cells binary"), "uint8", "sum")
    spark.sparkContext.setJobGroup("one-sketch", "")
    got = common.gathered_sketch(merged, "uint8", 8, 32)
    spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    assert got.tolist() == [2 * i + 1 for i in range(8) for _ in range(4)]
    assert len(spark.sparkContext.statusTracker().getJobIdsForGroup("one-sketch")) <= 3


def test_entries_move_once_by_node_and_once_by_list(spark, conf):
    conf("spark.sql.autoBroadcastJoinThreshold", "-1")
    conf("spark.sql.adaptive.enabled", "false")
    meta = lambda n, at, single: (n << 33) | ((at + 1) << 1) | int(single)
    # List 1 lies in one part, list 2 in two; list 3 is salted and stays whole; node 9 has no label.
    rows = [(1, 0, 5, 7), (1, 0, 6, 7), (2, 0, 5, 30), (2, 0, 9, 31), (3, 1, 5, 40), (3, 2, 9, 41), (3, 2, 9, 41)]
    entries = spark.createDataFrame([(s, salt, node, meta(n, s - 2, s == 3)) for s, salt, node, n in rows], "sig long, salt int, node long, meta long")
    labels = spark.createDataFrame([(5, 5), (6, 5)], "node long, label long")
    member = jaccard.part_members(entries, labels, lambda df: df)
    got = sorted(map(tuple, jaccard.read_out(member).select("sig", "node", "part", "n", "at", "single").collect()))
    assert got == [(2, 5, 5, 30, 0, False), (2, 9, 9, 31, 0, False), (3, 5, 5, 40, 1, True), (3, 9, 9, 41, 1, True), (3, 9, 9, 41, 1, True)]
    plan = member._jdf.queryExecution().executedPlan().toString()
    assert len(re.findall(r"Exchange hashpartitioning\(", plan)) == 3  # entries by node, labels by node, entries by list

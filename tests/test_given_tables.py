"""Queries that once made their data up read a given table, and agree with their SQL there."""

import duckdb
import pytest

import __spark_entry__ as entry_point
from geohist.operators import grid, split, tree

SF = "/root/testdata/sf0.01"


def same_as_sql(spark, name: str, *tables: str) -> list[tuple]:
    """Rows of the query, equal to those of its SQL, and read from the tables named."""
    got = entry_point.queries()[name](spark, SF)
    con = duckdb.connect()
    for t in tables:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    want = con.sql(entry_point.oracle_sql()[name])
    assert sorted(got.columns) == sorted(want.columns)
    at = [want.columns.index(c) for c in got.columns]
    rows = sorted(map(tuple, got.collect()))
    assert rows == sorted(tuple(r[i] for i in at) for r in want.fetchall()) and rows
    return rows


@pytest.mark.parametrize("sigma", (20, 50, 100))
def test_gaussian_points_are_one_for_each_event(spark, sigma):
    assert sum(r[2] for r in same_as_sql(spark, f"gaussian_points_{sigma}", "events")) == 10_000


def test_lattice_positions_of_every_inner_node(spark):
    rows = same_as_sql(spark, "lattice_positions", "events")
    assert {n for n, _ in rows} == set(range(1, 16))
    assert {k for n, k in rows if n == 1} == set(split_lattice(64, 3))


def split_lattice(u: int, rounds: int) -> list[int]:
    known = [1, u]
    for _ in range(rounds + 1):
        known = sorted({*known, *(a + (b - a) // 2 for a, b in zip(known, known[1:]))})
    return known[:-1]


@pytest.mark.parametrize("points, table, records", (("p1", "events", 10_000), ("p3", "lineitem", 60_000)))
def test_midpoint_counts_the_records_of_both_sides(spark, points, table, records):
    [(k, low, high)] = same_as_sql(spark, f"midpoint_{points}", table)
    assert k == 32 and low + high == records and low and high


def test_sides_of_a_node_without_records(spark):
    nodes = tree.root(spark, grid.GridSpec(0.0, 4.0, 0.0, 4.0, 4, 4), 2)
    none = spark.createDataFrame([], "tree_id string, node_id long, cx int, cy int, cnt long")
    prof = split.profile(none, nodes)
    assert [tuple(r) for r in split.sides(prof, split.midpoint(prof, nodes)).select("k", "low", "high").collect()] == [(2, 0, 0)]


def test_overlap_join_meets_blocks_that_hold_events(spark):
    rows = same_as_sql(spark, "overlap_join", "events")
    assert all(blocks <= records <= 10_000 for _, _, blocks, records in rows) and len({r[3] for r in rows}) > 50


@pytest.mark.parametrize("name", ("random", "mixed"))
def test_each_event_asks_for_one_rectangle(spark, name):
    rows = same_as_sql(spark, f"queries_{name}", "events")
    assert [r[1] for r in rows] == list(range(10_000)) and all(r[0] == name and 0 <= r[2] < r[3] <= 64 and 0 <= r[4] < r[5] <= 64 for r in rows)

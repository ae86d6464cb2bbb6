"""The operators around the methods: joins, aggregates, windows, sets, functions, files, SQL, streams, with their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from geohist.functions import budget, noise, sqlfn
from geohist.functions.storage import shared_folder
from geohist.operators import grid, quad, relational, split, tree
from geohist.plans import oracle
from geohist.sources import points as src
from geohist.sources import sinks
from geohist.streaming import windows

_ALL: dict[str, tuple] = {}
SECRET = noise.TEST_SECRET
_M = oracle.matrix("p1")


def add(name: str, sql: str | None = None):
    def keep(f):
        _ALL[name] = (f, sql)
        return f

    return keep


def t(spark: SparkSession, d: str, name: str) -> DataFrame:
    return src.table(spark, d, name)


def fm(spark: SparkSession, d: str) -> DataFrame:
    return grid.frequency_matrix(src.points(spark, d, "p1"), src.grid_of("p1", 64))


def scratch(spark: SparkSession) -> str:
    return shared_folder(spark, "surface")


# Projection and filters
add("project_embedding", "SELECT vec_id, round(cast(embedding[1] AS DOUBLE), 6) AS e1, round(cast(embedding[2] AS DOUBLE), 6) AS e2 FROM embeddings")(lambda s, d: t(s, d, "embeddings").select("vec_id", F.round(F.get("embedding", 0).cast("double"), 6).alias("e1"), F.round(F.get("embedding", 1).cast("double"), 6).alias("e2")))
add("json_coordinate", "SELECT cast(json_extract_string(props, '$.k') AS INTEGER) AS k, count(*) AS n FROM events GROUP BY 1")(lambda s, d: t(s, d, "events").groupBy(F.get_json_object("props", "$.k").cast("int").alias("k")).agg(F.count(F.lit(1)).alias("n")))
add("json_struct", "SELECT event_id, cast(json_extract_string(props, '$.k') AS INTEGER) AS k FROM events")(lambda s, d: t(s, d, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k")))
add("crop_week_p1", "SELECT event_type, count(*) AS n, round(sum(value), 4) AS total FROM events WHERE ts >= TIMESTAMP '2024-01-01' AND ts < TIMESTAMP '2024-01-08' AND value >= 10 AND value < 200 GROUP BY 1")(
    lambda s, d: src.crop(src.crop(t(s, d, "events"), time=("2024-01-01", "2024-01-08")), (10, 200, 10, 200), x="value", y="value").groupBy("event_type").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("total"))
)
add("filter_types", "SELECT event_type, count(*) AS n FROM events WHERE event_type IN ('click', 'view') GROUP BY 1")(lambda s, d: src.crop(t(s, d, "events"), types=["click", "view"]).groupBy("event_type").agg(F.count(F.lit(1)).alias("n")))

# Joins
add("join_customer_region", "SELECT r_name, n_name, count(*) AS customers, round(sum(c_acctbal), 2) AS balance FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1, 2")(
    lambda s, d: relational.enrich(relational.enrich(t(s, d, "customer"), t(s, d, "nation"), "c_nationkey", "n_nationkey"), t(s, d, "region"), "n_regionkey", "r_regionkey").groupBy("r_name", "n_name").agg(F.count(F.lit(1)).alias("customers"), F.round(F.sum("c_acctbal"), 2).alias("balance"))
)
add("join_lineitem_orders", "SELECT o_orderstatus, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")(
    lambda s, d: relational.enrich(t(s, d, "lineitem").select("l_orderkey", "l_quantity"), t(s, d, "orders").select("o_orderkey", "o_orderstatus"), "l_orderkey", "o_orderkey").groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"))
)
_WIN = "(SELECT i AS win, TIMESTAMP '2024-01-01' + to_days(cast(i * 3 AS INTEGER)) AS begins, TIMESTAMP '2024-01-01' + to_days(cast(i * 3 + 5 AS INTEGER)) AS ends FROM range(9) r(i))"
add("interval_join_events", f"SELECT win, count(*) AS n FROM events JOIN {_WIN} ON ts >= begins AND ts < ends GROUP BY 1")(
    lambda s, d: relational.interval_join(
        t(s, d, "events").select(F.col("ts").cast("timestamp").alias("ts")),
        s.range(9).select(F.col("id").alias("win"), (F.lit("2024-01-01").cast("timestamp") + F.make_dt_interval(F.col("id") * 3)).alias("begins"), (F.lit("2024-01-01").cast("timestamp") + F.make_dt_interval(F.col("id") * 3 + 5)).alias("ends")),
    ).groupBy("win").agg(F.count(F.lit(1)).alias("n"))
)
add("asof_join_release", "SELECT e.event_id, r.v AS release FROM events e ASOF LEFT JOIN (SELECT TIMESTAMP '2024-01-02' + to_days(cast(i * 2 AS INTEGER)) AS at, i AS v FROM range(14) t(i)) r ON e.ts >= r.at")(
    lambda s, d: relational.asof_join(
        t(s, d, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts")),
        s.range(14).select((F.lit("2024-01-02").cast("timestamp") + F.make_dt_interval(F.col("id") * 2)).alias("ts"), F.col("id").alias("release")), "ts", [], "release",
    ).select("event_id", "release")
)
add("semi_join_customers", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 400000)")(lambda s, d: t(s, d, "customer").join(t(s, d, "orders").where("o_totalprice > 400000"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey"))
add("anti_join_parts", "SELECT p_partkey FROM part WHERE p_partkey NOT IN (SELECT l_partkey FROM lineitem WHERE l_quantity > 45)")(lambda s, d: t(s, d, "part").join(t(s, d, "lineitem").where("l_quantity > 45"), F.col("p_partkey") == F.col("l_partkey"), "left_anti").select("p_partkey"))
add("full_outer_matrices", f"SELECT coalesce(a.cx, b.cx) AS cx, coalesce(a.cy, b.cy) AS cy, coalesce(a.cnt, 0) AS before, coalesce(b.cnt, 0) AS after FROM ({_M}) a FULL JOIN ({oracle.matrix('p5')}) b ON a.cx = b.cx AND a.cy = b.cy")(
    lambda s, d: relational.compare(fm(s, d), grid.frequency_matrix(src.points(s, d, "p5"), src.grid_of("p5", 64)))
)

# Aggregates
add("users_per_cell", f"SELECT {oracle.index('cast(epoch_us(ts) AS DOUBLE)', *oracle.DOMAINS['p1'][:2], 16)} AS cx, count(DISTINCT user_id) AS users FROM events GROUP BY 1")(lambda s, d: relational.users_per_cell(t(s, d, "events").select(src.micros("ts").cast("double").alias("px"), F.col("value").alias("py"), "user_id"), src.grid_of("p1", 16), ("cx",)))
add("users_per_cell_approx")(lambda s, d: relational.users_per_cell(t(s, d, "events").select(src.micros("ts").cast("double").alias("px"), F.col("value").alias("py"), "user_id"), src.grid_of("p1", 16), ("cx",), approx=True))
add("grouping_sets_quadrants", f"SELECT q1, q2, sum(cnt)::BIGINT AS cnt FROM (SELECT cast((cx // 32) * 2 + cy // 32 AS INTEGER) AS q1, cast(((cx // 16) % 2) * 2 + (cy // 16) % 2 AS INTEGER) AS q2, cnt FROM ({_M})) GROUP BY ROLLUP (q1, q2)")(
    lambda s, d: fm(s, d).select(F.shiftright(c := quad.morton(F.col("cx"), F.col("cy"), 6), 10).cast("int").alias("q1"), (F.shiftright(c, 8) % 4).cast("int").alias("q2"), "cnt").rollup("q1", "q2").agg(F.sum("cnt").alias("cnt"))
)
add("rollup_region", "SELECT r_name, n_name, c_mktsegment, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name, c_mktsegment)")(
    lambda s, d: relational.enrich(relational.enrich(t(s, d, "customer"), t(s, d, "nation"), "c_nationkey", "n_nationkey"), t(s, d, "region"), "n_regionkey", "r_regionkey").rollup("r_name", "n_name", "c_mktsegment").agg(F.count(F.lit(1)).alias("n"))
)
add("cube_events", "SELECT event_type, user_id % 3 AS g, grouping(event_type) * 2 + grouping(g) AS gid, count(*) AS n FROM events GROUP BY CUBE (event_type, g)")(
    lambda s, d: t(s, d, "events").withColumn("g", F.col("user_id") % 3).cube("event_type", "g").agg(F.grouping_id().alias("gid"), F.count(F.lit(1)).alias("n"))
)
add("cell_stats", "SELECT event_type, count(*) AS n, round(avg(value), 6) AS mean, round(stddev_samp(value), 6) AS sd, arg_min(event_id, struct_pack(v := value, e := event_id)) AS least, round(quantile_cont(value, 0.5), 6) AS median FROM events GROUP BY 1")(lambda s, d: relational.cell_stats(t(s, d, "events")))
add("pivot_types", "SELECT user_id % 10 AS g, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'view') AS view FROM events GROUP BY 1")(
    lambda s, d: t(s, d, "events").withColumn("g", F.col("user_id") % 10).groupBy("g").pivot("event_type", ["click", "view"]).agg(F.count(F.lit(1))).na.fill(0)
)
_KEY = oracle.u("'bound'", "event_id")
add("bounded_events", f"SELECT event_id, user_id FROM events QUALIFY row_number() OVER (PARTITION BY user_id ORDER BY {_KEY}, event_id) <= 5")(lambda s, d: relational.bound_contributions(t(s, d, "events"), "user_id", 5, SECRET, "event_id").select("event_id", "user_id"))
add("abs_dev_by_type", "WITH m AS (SELECT event_type, avg(value) AS m FROM events GROUP BY 1) SELECT e.event_type, round(sum(abs(value - m)), 4) AS abs_dev FROM events e JOIN m ON m.event_type = e.event_type GROUP BY 1")(lambda s, d: t(s, d, "events").groupBy("event_type").agg(F.round(sqlfn.abs_dev("value"), 4).alias("abs_dev")))

# Windows, sort, limit
add("rank_cells", f"SELECT cx, cy, cnt, cast(rank() OVER (ORDER BY cnt DESC) AS INTEGER) AS r, cast(dense_rank() OVER (ORDER BY cnt DESC) AS INTEGER) AS dr FROM ({_M})")(
    lambda s, d: relational.rank_cells(fm(s, d))
)
add("ntile_cells", f"SELECT cx, cy, cast(ntile(4) OVER (PARTITION BY cx ORDER BY cnt DESC, cy) AS INTEGER) AS quarter, round(percent_rank() OVER (PARTITION BY cx ORDER BY cnt DESC, cy), 9) AS pr FROM ({_M})")(
    lambda s, d: fm(s, d).select("cx", "cy", F.ntile(4).over(w := W.partitionBy("cx").orderBy(F.desc("cnt"), "cy")).alias("quarter"), F.round(F.percent_rank().over(w), 9).alias("pr"))
)
add("lag_events", "SELECT event_id, epoch_us(ts) - epoch_us(lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id)) AS gap FROM events")(
    lambda s, d: t(s, d, "events").select("event_id", (src.micros("ts") - src.micros(F.lag("ts").over(W.partitionBy("user_id").orderBy("ts", "event_id")))).alias("gap"))
)
add("range_frame", f"SELECT cx, cy, sum(cnt) OVER (PARTITION BY cx ORDER BY cy RANGE BETWEEN 2 PRECEDING AND 2 FOLLOWING)::BIGINT AS near FROM ({_M})")(lambda s, d: relational.moving(fm(s, d), 2))
add("first_last", "SELECT DISTINCT user_id, first_value(event_type) OVER w AS first, last_value(event_type) OVER w AS last FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")(
    lambda s, d: t(s, d, "events").groupBy("user_id").agg(F.min_by("event_type", F.struct("ts", "event_id")).alias("first"), F.max_by("event_type", F.struct("ts", "event_id")).alias("last"))
)
add("topk_per_type", "SELECT event_type, event_id, value FROM events QUALIFY row_number() OVER (PARTITION BY event_type ORDER BY value DESC, event_id) <= 3")(lambda s, d: relational.top_per_group(t(s, d, "events"), ["event_type"], [F.desc("value"), F.col("event_id")], 3).select("event_type", "event_id", "value"))
add("densest_cells", f"SELECT cx, cy, cnt FROM ({_M}) ORDER BY cnt DESC, cx, cy LIMIT 10")(lambda s, d: fm(s, d).orderBy(F.desc("cnt"), "cx", "cy").limit(10))

# Sets
_A, _B = f"SELECT cx, cy FROM ({_M}) WHERE cnt > 3", f"SELECT cx, cy FROM ({oracle.matrix('p6')})"
for _n, _op in (("union", "UNION"), ("intersect", "INTERSECT"), ("except", "EXCEPT")):
    add(f"{_n}_cells", f"{_A} {_op} {_B}")(
        lambda s, d, n=_n: relational.set_op(fm(s, d).where("cnt > 3").select("cx", "cy"), grid.frequency_matrix(src.points(s, d, "p6"), src.grid_of("p6", 64)).select("cx", "cy"), n)
    )
add("neighbour_matrix", "WITH p AS (" + oracle.points("p1") + f") SELECT sum(cnt)::BIGINT AS n FROM ({_M})")(lambda s, d: relational.neighbours(src.points(s, d, "p1"), 0.0, 0.0).agg((F.count(F.lit(1)) - 1).alias("n")))

# Functions
_bits = " + ".join(f"((cx >> {b}) & 1) * {2 << (2 * b)} + ((cy >> {b}) & 1) * {1 << (2 * b)}" for b in range(6))
add("morton_cells", f"SELECT cx, cy, cast({_bits} AS BIGINT) AS code FROM ({_M})")(lambda s, d: fm(s, d).select("cx", "cy", quad.morton(F.col("cx"), F.col("cy"), 6).alias("code")))
add("ancestors", "SELECT o_orderkey % 1024 + 1024 AS node_id, cast(j AS INTEGER) AS up, (o_orderkey % 1024 + 1024) >> j AS ancestor FROM (SELECT DISTINCT o_orderkey % 1024 AS o_orderkey FROM orders), range(1, 11) r(j)")(
    lambda s, d: tree.ancestors(t(s, d, "orders").select(F.lit("t").alias("tree_id"), (F.col("o_orderkey") % 1024 + 1024).alias("node_id"), F.lit(0).alias("height")).distinct(), F.lit(10)).select("node_id", "up", "ancestor")
)
add("node_paths", "SELECT DISTINCT o_orderkey % 64 + 64 AS node_id, bin(o_orderkey % 64 + 64) AS path FROM orders")(lambda s, d: t(s, d, "orders").select((F.col("o_orderkey") % 64 + 64).alias("node_id")).distinct().select("node_id", F.bin("node_id").alias("path")))
add("hourly_counts", "SELECT date_trunc('hour', ts) AS hour, count(*) AS n FROM events GROUP BY 1")(lambda s, d: t(s, d, "events").groupBy(F.date_trunc("hour", F.col("ts").cast("timestamp")).cast("timestamp_ntz").alias("hour")).agg(F.count(F.lit(1)).alias("n")))
add("budget_array", "SELECT n_nationkey, cast(i AS INTEGER) AS height, round(pow(2, (6 - i) / 3.0) * (n_nationkey + 1) / (SELECT sum(pow(2, (6 - j) / 3.0)) FROM range(7) t(j)), 9) AS eps FROM nation, range(7) r(i)")(
    lambda s, d: t(s, d, "nation").select("n_nationkey", F.posexplode(F.transform(budget.level_array(budget.geometric(1.0, 6)), lambda e: e * (F.col("n_nationkey") + 1))).alias("height", "e")).select("n_nationkey", "height", F.round("e", 9).alias("eps"))
)
add("map_budgets", "SELECT n_nationkey, cast(0.25 * (n_nationkey + 1) AS DOUBLE) AS eps FROM nation")(lambda s, d: t(s, d, "nation").select("n_nationkey", F.map_from_arrays(F.array(F.lit("a"), F.lit("b")), F.array(F.lit(0.25), F.lit(0.75))).alias("m")).select("n_nationkey", F.round(F.element_at("m", "a") * (F.col("n_nationkey") + 1), 6).alias("eps")))
_LAT = "SELECT node, cast(k AS INTEGER) AS k FROM (SELECT n_nationkey AS node, unnest([1 + (n_nationkey + 8) // 2]) AS k FROM nation)"
add("udtf_lattice", _LAT)(lambda s, d: sqlfn.lattice_by_udtf(s, t(s, d, "nation").select(F.col("n_nationkey").alias("node"), (F.col("n_nationkey") + 9).cast("int").alias("u")), 0))
add("sql_overlap", f"SELECT cx, cy, cast(greatest(0, least(cx + 10, 40) - greatest(cx, 20)) * greatest(0, least(cy + 10, 40) - greatest(cy, 20)) AS BIGINT) AS shared FROM ({_M})")(lambda s, d: sqlfn.overlap_by_sql(s, fm(s, d)))
add("sql_laplace", f"SELECT cx, cy, round({oracle.lap('cnt', '2.0', oracle.q('sql'), 'cx', 'cy')}, 6) AS noisy FROM ({_M})")(lambda s, d: sqlfn.laplace_by_sql(s, fm(s, d)))


# Files and views
@add("release_roundtrip", f"SELECT cx AS x0, cy AS y0, round({oracle.lap('cnt', '2.0', oracle.q('demo'), 'cx', 'cy')}, 6) AS ncount FROM ({_M})")
def _(s, d):
    cells = fm(s, d).select(F.lit("t").alias("tree_id"), (F.col("cx").cast("long") * 64 + F.col("cy")).alias("leaf_id"), F.col("cx").alias("x0"), (F.col("cx") + 1).alias("x1"), F.col("cy").alias("y0"), (F.col("cy") + 1).alias("y1"), F.lit(1).cast("long").alias("cells"), noise.laplace(F.col("cnt"), 2.0, SECRET, "demo", F.col("cx"), F.col("cy")).alias("ncount"))
    path = scratch(s)
    sinks.write(cells, budget.Ledger().spend("data", 0.5).frame(s), path, SECRET, "orc", testing=True)
    return s.read.orc(f"{path}/leaves").select("x0", "y0", F.round("ncount", 6).alias("ncount"))


@add("cells_tile_pruned", f"SELECT cx, cy, cnt FROM ({_M}) WHERE cx >= 10 AND cx < 30 AND cy >= 0 AND cy < 20")
def _(s, d):
    path = scratch(s)
    sinks.write_cells(fm(s, d), path, 16)
    return sinks.read_box(s, path, (10, 30, 0, 20), 16).select("cx", "cy", "cnt")


@add("sql_private_count", f"SELECT cast(cx // 8 AS INTEGER) AS strip, cast(sum(cnt) AS BIGINT) AS n FROM ({_M}) GROUP BY 1")
def _(s, d):
    sinks.register(fm(s, d), "published_cells")
    return s.sql("SELECT cast(cx DIV 8 AS INT) AS strip, sum(cnt) AS n FROM published_cells GROUP BY 1")


add("release_metadata", f"""SELECT 't' AS tree_id, '{{"eps_tot":1.0,"grid":"64x64","leaves":' || count(*) || ',"cells":' || count(*) || '}}' AS metadata FROM ({_M})""")(lambda s, d: sinks.metadata(fm(s, d).select(F.lit("t").alias("tree_id"), F.lit(1).alias("cells")), eps_tot=1.0, grid="64x64"))
add("sample_points", f"SELECT event_id, value FROM events WHERE {oracle.u('event_id', secret='sample')} < 0.1")(lambda s, d: relational.sample_keyed(t(s, d, "events").select("event_id", "value"), 0.1, "event_id"))
_HALVES = f"SELECT cnt, cx < 32 AS low, avg(cnt) OVER (PARTITION BY cx < 32) AS mean FROM ({oracle.dense('p1')})"
add("best_split_udf", f"SELECT 32 AS k, round(sum(abs(cnt - mean)), 4) AS o FROM ({_HALVES})")(lambda s, d: sqlfn.split_by_udf(fm(s, d)))

# Streams
_T = "SELECT epoch_us(time_bucket(INTERVAL '{w}', ts, TIMESTAMP '2024-01-01')) AS begins, cx, cy, count(*) AS cnt FROM (SELECT ts, " + oracle.index("cast(epoch_us(ts) AS DOUBLE)", *oracle.DOMAINS["p1"][:2], 8) + " AS cx, " + oracle.index("value", *oracle.DOMAINS["p1"][2:], 8) + " AS cy FROM events) GROUP BY 1, 2, 3"
add("stream_tumbling", _T.format(w="1 day"))(lambda s, d: windows.replay(s, d, "1 day"))
add("stream_sliding", "SELECT epoch_us(TIMESTAMP '2024-01-01' + to_days(cast(b AS INTEGER))) AS begins, count(*) AS cnt FROM events JOIN range(-2, 40) r(b) ON ts >= TIMESTAMP '2024-01-01' + to_days(cast(b AS INTEGER)) AND ts < TIMESTAMP '2024-01-01' + to_days(cast(b + 2 AS INTEGER)) GROUP BY 1")(
    lambda s, d: windows.replay(s, d, "2 days", "1 day").groupBy("begins").agg(F.sum("cnt").alias("cnt"))
)
add("stream_deduplicated", "SELECT count(*) AS n FROM (SELECT DISTINCT event_id FROM events)")(lambda s, d: windows.replay_deduplicated(s, d))
_DAYS = "SELECT CAST(1704067200000000 + i * 86400000000 AS BIGINT) AS begins, CAST(x.v AS INTEGER) AS cx, CAST(y.v AS INTEGER) AS cy FROM range(30) r(i), range(8) x(v), range(8) y(v)"
add(
    "stream_private",
    f"SELECT g.begins, g.cx, g.cy, round({oracle.lap('coalesce(m.cnt, 0)', '1.0', oracle.q('window'), 'g.begins', 'g.cx', 'g.cy')}, 6) AS ncount FROM ({_DAYS}) g LEFT JOIN ({_T.format(w='1 day')}) m ON m.begins = g.begins AND m.cx = g.cx AND m.cy = g.cy",
)(lambda s, d: windows.replay_release(s, d).withColumn("ncount", F.round("ncount", 6)))
add("stream_late", _T.format(w="1 day"))(lambda s, d: windows.replay_late(s, d))
add("stream_totals", "SELECT user_id, least(50, count(*)) AS kept FROM events GROUP BY 1")(lambda s, d: windows.replay_totals(s, d))
add(
    "stream_sessions",
    """WITH e AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) <= INTERVAL 12 HOUR THEN 0 ELSE 1 END AS opens FROM events),
    s AS (SELECT user_id, ts, sum(opens) OVER (PARTITION BY user_id ORDER BY ts, opens DESC) AS session FROM e)
    SELECT user_id, epoch_us(min(ts)) AS begins, count(*) AS n FROM s GROUP BY user_id, session""",
)(lambda s, d: windows.replay_sessions(s, d))
add("split_midpoint_batch", "SELECT cast(32 AS INTEGER) AS k")(lambda s, d: split.midpoint(None, tree.root(s, src.grid_of("p1", 64), 4)).select("k"))


def queries():
    return {k: f for k, (f, _) in _ALL.items()}


def oracle_sql():
    return {k: x for k, (_, x) in _ALL.items() if x}

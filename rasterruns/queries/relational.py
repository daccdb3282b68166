"""Relational operators, scalar functions and streams that users of the spatial methods combine with them."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rasterruns.operators.timejoin import as_of_join
from rasterruns.runtime import shared_file
from rasterruns.streaming import tracks

Q: dict = {}
SQL: dict = {}


def _sql(name: str, text: str, duck: str | None = None) -> None:
    """A query in SQL that both engines run; ``{table}`` names a test table."""
    tables = set(re.findall(r"\{(\w+)\}", text))

    def run(spark: SparkSession, d: str) -> DataFrame:
        return spark.sql(text, **{t: spark.read.parquet(f"{d}/{t}.parquet") for t in tables})

    Q[name] = run
    SQL[name] = re.sub(r"\{(\w+)\}", r"\1", duck or text)


def _query(name: str, sql: str | None = None):
    def add(f):
        Q[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def _t(spark: SparkSession, d: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{d}/{name}.parquet")


# ---- projection and selection ----

_sql("proj_layer", "SELECT o_orderkey, o_orderkey % 25 AS cluster_id, o_orderkey * 2 AS twice FROM {orders}")
_sql("filter_range", "SELECT o_orderkey FROM {orders} WHERE o_totalprice BETWEEN 1000 AND 50000")
_sql("filter_in", "SELECT c_custkey FROM {customer} WHERE c_mktsegment IN ('BUILDING', 'MACHINERY')")
_sql("filter_like", "SELECT p_partkey FROM {part} WHERE p_type LIKE '%A%' AND p_name IS NOT NULL")
_sql("case_verdict", "SELECT l_orderkey, l_linenumber, CASE WHEN l_quantity > 40 THEN 'hit' WHEN l_quantity < 10 THEN 'miss' ELSE 'unsure' END AS verdict FROM {lineitem}")

# ---- joins ----

_sql("join_inner", "SELECT o_orderkey, c_custkey, c_nationkey FROM {orders} JOIN {customer} ON o_custkey = c_custkey")
_sql("join_left", "SELECT c_custkey, count(o_orderkey) AS n FROM {customer} LEFT JOIN {orders} ON o_custkey = c_custkey GROUP BY c_custkey")
_sql("join_full", "SELECT s_suppkey, c_custkey FROM {supplier} FULL OUTER JOIN {customer} ON s_suppkey = c_custkey")
_sql("join_semi", "SELECT c_custkey FROM {customer} LEFT SEMI JOIN {orders} ON o_custkey = c_custkey", "SELECT c_custkey FROM customer SEMI JOIN orders ON o_custkey = c_custkey")
_sql("join_anti", "SELECT c_custkey FROM {customer} LEFT ANTI JOIN {orders} ON o_custkey = c_custkey", "SELECT c_custkey FROM customer ANTI JOIN orders ON o_custkey = c_custkey")
_sql("join_cross_small", "SELECT r_regionkey, n_nationkey FROM {region} CROSS JOIN {nation}")
_sql("join_theta_mbr", "SELECT a.p_partkey AS rid, b.s_suppkey AS sid FROM {part} a JOIN {supplier} b ON a.p_partkey <= b.s_suppkey + 3 AND b.s_suppkey <= a.p_partkey + a.p_size % 5")


@_query("join_shuffle_hash", "SELECT o_orderkey, c_nationkey FROM orders JOIN customer ON o_custkey = c_custkey")
def _(spark, d):
    return _t(spark, d, "orders").join(_t(spark, d, "customer").hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_nationkey")


@_query("join_broadcast_hint", "SELECT c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey")
def _(spark, d):
    # nation: a fixed table of 25 rows
    return _t(spark, d, "customer").join(F.broadcast(_t(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name")


@_query("join_salted", "SELECT n_nationkey, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_nationkey")
def _(spark, d):
    """A skewed equi-join with the hot side salted and the small side replicated over the salts."""
    left = _t(spark, d, "customer").withColumn("salt", F.pmod(F.xxhash64("c_custkey"), F.lit(8)))
    right = _t(spark, d, "nation").withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(7).cast("long"))))
    return left.join(right, (F.col("c_nationkey") == F.col("n_nationkey")) & (left["salt"] == right["salt"])).groupBy(F.col("n_nationkey")).agg(F.count(F.lit(1)).alias("n"))


@_query("join_range_cells", """WITH runs AS (SELECT l_orderkey AS oid, min(l_partkey) AS st, max(l_partkey) + 1 AS en FROM lineitem GROUP BY l_orderkey)
SELECT oid, s_suppkey AS cell FROM runs JOIN supplier ON s_suppkey >= st AND s_suppkey < en""")
def _(spark, d):
    """Cells between run bounds: runs exploded to blocks, an equi-join on the block, then the range."""
    li = _t(spark, d, "lineitem").groupBy(F.col("l_orderkey").alias("oid")).agg(F.min("l_partkey").alias("st"), (F.max("l_partkey") + 1).alias("en"))
    runs = li.withColumn("block", F.explode(F.sequence(F.shiftright("st", 6), F.shiftright(F.col("en") - 1, 6))))
    points = _t(spark, d, "supplier").select(F.col("s_suppkey").alias("cell"), F.shiftright("s_suppkey", 6).alias("block"))
    return runs.join(points, "block").where("cell >= st AND cell < en").select("oid", "cell")


@_query("join_interval_runs", """WITH runs AS (SELECT l_suppkey AS oid, l_orderkey AS st, l_orderkey + l_linenumber AS en FROM lineitem)
SELECT DISTINCT r.oid AS rid, s.oid AS sid FROM runs r JOIN runs s ON r.st < s.en AND s.st < r.en""")
def _(spark, d):
    """Suppliers whose runs of lines overlap: all runs with all runs, so each supplier also meets itself."""
    from rasterruns.operators.cells import interval_join

    runs = _t(spark, d, "lineitem").select(F.col("l_suppkey").alias("oid"), F.col("l_orderkey").alias("st"), (F.col("l_orderkey") + F.col("l_linenumber")).alias("en"))
    return interval_join(runs, runs, bits=3).distinct()  # blocks about as wide as a run; the width doesn't change the pairs


@_query("join_asof_events", """SELECT e.event_id, p.event_id AS last_purchase FROM (SELECT * FROM events WHERE event_type = 'click') e
ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'purchase') p ON e.user_id = p.user_id AND e.ts >= p.ts""")
def _(spark, d):
    e = _t(spark, d, "events")
    clicks, buys = e.where("event_type = 'click'"), e.where("event_type = 'purchase'")
    return as_of_join(clicks, buys.select("user_id", "ts", F.col("event_id").alias("last_purchase")), "user_id", "ts", ["last_purchase"]).select("event_id", "last_purchase")


# ---- aggregation ----

_sql("agg_hash", "SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(l_quantity) AS BIGINT) AS q FROM {lineitem} GROUP BY l_returnflag, l_linestatus")
_sql("agg_distinct", "SELECT l_returnflag, count(DISTINCT l_suppkey) AS suppliers FROM {lineitem} GROUP BY l_returnflag")
_sql("agg_rollup", "SELECT c_nationkey, c_mktsegment, count(*) AS n FROM {customer} GROUP BY ROLLUP (c_nationkey, c_mktsegment)")
_sql("agg_cube", "SELECT c_nationkey, c_mktsegment, count(*) AS n FROM {customer} GROUP BY CUBE (c_nationkey, c_mktsegment)")
_sql("agg_grouping_sets", "SELECT c_nationkey, c_mktsegment, count(*) AS n FROM {customer} GROUP BY GROUPING SETS ((c_nationkey), (c_mktsegment), ())")
_sql("agg_bool_or", "SELECT l_orderkey, bool_or(l_quantity > 49) AS large, bool_and(l_quantity > 5) AS all_some FROM {lineitem} GROUP BY l_orderkey")
_sql("agg_bit_and", "SELECT l_suppkey, bit_and(l_orderkey) AS a, bit_or(l_orderkey) AS o, bit_xor(l_orderkey) AS x FROM {lineitem} GROUP BY l_suppkey")
_sql("agg_count_if", "SELECT l_suppkey, count_if(l_quantity > 25) AS n FROM {lineitem} GROUP BY l_suppkey", "SELECT l_suppkey, count(*) FILTER (WHERE l_quantity > 25) AS n FROM lineitem GROUP BY l_suppkey")
_sql("agg_percentile", "SELECT event_type, CAST(percentile(event_id, 0.5) * 2 AS BIGINT) AS twice_median FROM {events} GROUP BY event_type", "SELECT event_type, CAST(quantile_cont(event_id, 0.5) * 2 AS BIGINT) AS twice_median FROM events GROUP BY event_type")
Q["agg_approx_distinct"] = lambda spark, d: _t(spark, d, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"))


@_query("agg_pivot", "SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS click, count(*) FILTER (WHERE event_type = 'view') AS view FROM events GROUP BY user_id HAVING count(*) FILTER (WHERE event_type IN ('click', 'view')) > 0")
def _(spark, d):
    e = _t(spark, d, "events").where(F.col("event_type").isin("click", "view"))
    return e.groupBy("user_id").pivot("event_type", ["click", "view"]).count().na.fill(0)


# ---- windows, order, sets ----

_sql("win_row_number", "SELECT o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS rn FROM {orders}", "SELECT o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS rn FROM orders")
_sql("win_lead_gap", "SELECT o_custkey, o_orderkey, lead(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderkey) - o_orderkey AS gap FROM {orders}")
_sql("win_running_sum", "SELECT event_id, CAST(sum(CASE WHEN event_type = 'click' THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS BIGINT) AS clicks FROM {events}")
_sql("win_rank_topk", "SELECT p_brand, p_partkey FROM (SELECT p_brand, p_partkey, rank() OVER (PARTITION BY p_brand ORDER BY p_size DESC, p_partkey) AS r FROM {part}) t WHERE r <= 3")
_sql("win_frame_rows", "SELECT event_id, CAST(sum(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS BIGINT) AS s FROM {events}")
_sql("win_frame_range", "SELECT p_partkey, count(*) OVER (PARTITION BY p_brand ORDER BY p_size RANGE BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS near FROM {part}")
_sql("win_ntile", "SELECT c_custkey, ntile(4) OVER (PARTITION BY c_nationkey ORDER BY c_custkey) AS q FROM {customer}")
_sql("win_first_last", "SELECT DISTINCT user_id, first_value(event_id) OVER w AS first_id, last_value(event_id) OVER w AS last_id FROM {events} WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
_sql("sort_multi", "SELECT c_custkey, c_nationkey, c_mktsegment FROM {customer} ORDER BY c_nationkey DESC, c_mktsegment, c_custkey")
_sql("topk_largest_objects", "SELECT p_partkey, p_size FROM {part} ORDER BY p_size DESC, p_partkey LIMIT 20")
_sql("topk_per_group", "SELECT c_nationkey, c_custkey FROM (SELECT c_nationkey, c_custkey, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS r FROM {customer}) t WHERE r <= 2")
_sql("set_union_all", "SELECT c_nationkey AS k FROM {customer} UNION ALL SELECT s_nationkey FROM {supplier}")
_sql("set_union", "SELECT c_nationkey AS k FROM {customer} UNION SELECT s_nationkey FROM {supplier}")
_sql("set_intersect", "SELECT c_nationkey AS k FROM {customer} INTERSECT SELECT s_nationkey FROM {supplier}")
_sql("set_except", "SELECT c_custkey AS k FROM {customer} EXCEPT SELECT s_suppkey FROM {supplier}")
_sql("sample_hash", "SELECT s_suppkey FROM {supplier} WHERE (s_suppkey * 2654435 + 12345) % 97 < 10")

# ---- scalar functions ----

_sql("fn_bits", "SELECT o_orderkey, o_orderkey & 255 AS a, o_orderkey | 7 AS o, bit_count(o_orderkey) AS c, shiftleft(o_orderkey, 3) AS l, shiftright(o_orderkey, 2) AS r, o_orderkey ^ 6 AS x FROM {orders}", "SELECT o_orderkey, o_orderkey & 255 AS a, o_orderkey | 7 AS o, bit_count(o_orderkey) AS c, o_orderkey << 3 AS l, o_orderkey >> 2 AS r, xor(o_orderkey, 6) AS x FROM orders")
_sql("fn_math", "SELECT p_partkey, abs(p_size - 25) AS a, greatest(p_size, 10) AS g, least(p_size, 10) AS l, CAST(floor(p_retailprice / 100) AS BIGINT) AS f, CAST(floor(log2(p_size)) AS BIGINT) AS k, CAST(pow(2, p_size % 10) AS BIGINT) AS p FROM {part}")
_sql("fn_dates", "SELECT o_orderkey, CAST(date_trunc('month', o_orderdate) AS DATE) AS m, year(o_orderdate) AS y, datediff(o_orderdate, DATE '1992-01-01') AS d FROM {orders}", "SELECT o_orderkey, CAST(date_trunc('month', o_orderdate) AS DATE) AS m, year(o_orderdate) AS y, date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS d FROM orders")
_sql("fn_json", "SELECT event_id, get_json_object(props, '$.k') AS k FROM {events}", "SELECT event_id, json_extract_string(props, '$.k') AS k FROM events")
_sql("fn_decimal", "SELECT o_orderkey, CAST(CAST(o_totalprice AS DECIMAL(18, 2)) * 100 AS BIGINT) AS cents FROM {orders}")
_sql("fn_strings", "SELECT c_custkey, upper(c_mktsegment) AS u, lpad(CAST(c_custkey AS STRING), 8, '0') AS p, concat_ws('-', c_mktsegment, CAST(c_nationkey AS STRING)) AS w, regexp_extract(c_name, '([0-9]+)', 1) AS digits, length(c_name) AS n FROM {customer}", "SELECT c_custkey, upper(c_mktsegment) AS u, lpad(CAST(c_custkey AS VARCHAR), 8, '0') AS p, concat_ws('-', c_mktsegment, CAST(c_nationkey AS VARCHAR)) AS w, regexp_extract(c_name, '([0-9]+)', 1) AS digits, length(c_name) AS n FROM customer")


@_query("fn_arrays", "SELECT vec_id, len(embedding) AS n, CAST(sum(CASE WHEN e > 0 THEN 1 ELSE 0 END) AS BIGINT) AS positive, CAST(sum(floor(abs(e) * 4096)) AS BIGINT) AS total, bool_or(e > 0.4) AS spike FROM (SELECT vec_id, embedding, unnest(embedding)::DOUBLE AS e FROM embeddings) GROUP BY vec_id, embedding")
def _(spark, d):
    v = _t(spark, d, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("e"))
    total = F.aggregate("e", F.lit(0).cast("long"), lambda a, x: a + F.floor(F.abs(x) * 4096))
    return v.select("vec_id", F.size("e").cast("long").alias("n"), F.size(F.filter("e", lambda x: x > 0)).cast("long").alias("positive"), total.alias("total"), F.exists("e", lambda x: x > 0.4).alias("spike"))


@_query("fn_maps", "SELECT user_id, count(DISTINCT event_type) AS kinds, count(*) FILTER (WHERE event_type = 'click') AS clicks FROM events GROUP BY user_id")
def _(spark, d):
    per = _t(spark, d, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    m = per.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return m.select("user_id", F.size(F.map_keys("m")).cast("long").alias("kinds"), F.coalesce(F.try_element_at("m", F.lit("click")), F.lit(0)).alias("clicks"))


# ---- batch twins of the streams ----

_sql("stream_tumbling", "SELECT unix_timestamp(window(ts, '1 hour').start) AS start_s, event_type, count(*) AS n FROM {events} GROUP BY window(ts, '1 hour'), event_type", "SELECT CAST(epoch(date_trunc('hour', ts)) AS BIGINT) AS start_s, event_type, count(*) AS n FROM events GROUP BY ALL")
_sql("stream_sliding", "SELECT unix_timestamp(window(ts, '2 hours', '1 hour').start) AS start_s, count(*) AS n FROM {events} GROUP BY window(ts, '2 hours', '1 hour')", "SELECT CAST(epoch(date_trunc('hour', ts)) AS BIGINT) - 3600 * o AS start_s, count(*) AS n FROM events, (VALUES (0), (1)) t(o) GROUP BY ALL")
_sql("stream_session", "SELECT user_id, unix_timestamp(session_window(ts, '6 hours').start) AS start_s, count(*) AS n FROM {events} GROUP BY user_id, session_window(ts, '6 hours')", """WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, CAST(floor(epoch(min(ts))) AS BIGINT) AS start_s, count(*) AS n FROM s GROUP BY user_id, k""")
_sql("stream_interval_join", "SELECT a.event_id AS click, b.event_id AS purchase FROM {events} a JOIN {events} b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTES", "SELECT a.event_id AS click, b.event_id AS purchase FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE")


@_query("stream_dedup", "SELECT DISTINCT user_id, event_type, CAST(date_trunc('day', ts) AS DATE) AS day FROM events")
def _(spark, d):
    """One row a user, event type and day, by a stream that runs until its input is read; the watermark spans the table."""
    source = f"{d}/events.parquet"
    span = spark.read.parquet(source).agg(F.coalesce(F.datediff(F.max("ts"), F.min("ts")), F.lit(0))).first()[0]
    stream = spark.readStream.schema(spark.read.parquet(source).schema).parquet(f"{source}*")
    keys = ["user_id", "event_type", "day"]
    rows = tracks.deduplicated(stream.withColumn("day", F.to_date("ts")), "ts", keys, f"{span + 1} days").select(*keys)
    out = shared_file(spark, "stream")
    rows.writeStream.format("parquet").option("path", f"{out}/rows").option("checkpointLocation", f"{out}/state").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(rows.schema).parquet(f"{out}/rows")


@_query("stream_track_segments")
def _(spark, d):
    """Segments between successive events of a user, by the batch form of the stateful stream."""
    return tracks.segments(_t(spark, d, "events"))


@_query("stream_line_filter")
def _(spark, d):
    from rasterruns.grid import GridSpec
    from rasterruns.queries.spatial import layer

    return tracks.filter_segments(tracks.segments(_t(spark, d, "events")), layer(spark, d, "counties"), GridSpec(8))

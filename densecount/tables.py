"""Queries that use sketches on the star schema, the event stream and the text tables."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from . import sources
from .functions import hashing
from .operators import build, estimators, setops
from .plans import duck, estimate
from .registry import query
from .streaming import windows
from .streaming import sqlapi
from .workloads import B, histogram_sql

SMALL = 352


def _t(spark: SparkSession, sf: str, name: str) -> DataFrame:
    return sources.table(spark, sf, name)


def _estimate(rows: DataFrame, registers: int = SMALL) -> DataFrame:
    """(g, estimate) of rows (g, k)."""
    hist = build.state_histogram(build.register_bitmaps(rows, "k", ["g"], registers), ["g"])
    return estimators.hybrid(hist, registers)


def _est_sql(source: str, registers: int = SMALL) -> str:
    return f"(SELECT g, hybrid AS estimate FROM ({estimate.text(histogram_sql(source, registers=registers), registers)}) e)"


_TYPE_DAY = "(SELECT event_type || ' ' || strftime(date_trunc('day', ts), '%Y-%m-%d') AS g, user_id AS k FROM events)"


@query(f"SELECT g AS type_day, round(estimate, 3) AS users FROM {_est_sql(_TYPE_DAY)} q")
def q_users_per_type_day(spark, sf):
    rows = _t(spark, sf, "events").select(F.concat_ws(" ", "event_type", F.date_format("ts", "yyyy-MM-dd")).alias("g"), F.col("user_id").alias("k"))
    return _estimate(rows).select(F.col("g").alias("type_day"), F.round("estimate", 3).alias("users"))


_DAY_BITMAPS = f"(SELECT d AS day, bucket, bitmap FROM ({duck.bitmaps('(SELECT CAST(date_trunc(' + chr(39) + 'day' + chr(39) + ', ts) AS DATE) AS d, user_id FROM events)', 'user_id', 'd', SMALL)}))"
_ROLLING = f"SELECT CAST(x.day AS VARCHAR) AS g, y.bucket, bit_or(y.bitmap) AS bitmap FROM (SELECT DISTINCT day FROM {_DAY_BITMAPS}) x JOIN {_DAY_BITMAPS} y ON y.day BETWEEN x.day - 6 AND x.day GROUP BY x.day, y.bucket"


@query(f"SELECT g AS day, round(hybrid, 3) AS users FROM ({estimate.text('(' + duck.histogram(_ROLLING, 'g') + ')', SMALL)}) q")
def q_rolling_7d_users(spark, sf):
    """Daily bitmaps once, then OR over seven days: each day's rows go to the seven days they
    count in, which is an equi-join after all."""
    daily = build.register_bitmaps(_t(spark, sf, "events").select(F.to_date("ts").alias("day"), "user_id"), "user_id", ["day"], SMALL)
    days = daily.select("day").distinct()
    spread = daily.select(F.explode(F.sequence("day", F.date_add("day", 6))).alias("day"), "bucket", "bitmap").join(days, "day", "left_semi")
    rolled = spread.groupBy(F.col("day").cast("string").alias("g"), "bucket").agg(F.bit_or("bitmap").alias("bitmap"))
    return estimators.hybrid(build.state_histogram(rolled, ["g"]), SMALL).select(F.col("g").alias("day"), F.round("estimate", 3).alias("users"))


_SLIDING = "(SELECT strftime(CAST(date_trunc('day', ts) AS TIMESTAMP) - to_days(CAST(o AS INTEGER)), '%Y-%m-%d') AS g, user_id AS k FROM events, (SELECT unnest(range(7)) AS o) w)"


@query(f"SELECT g AS window_start, round(estimate, 3) AS users FROM {_est_sql(_SLIDING)} q")
def q_sliding_window(spark, sf):
    rows = _t(spark, sf, "events").select(F.window("ts", "7 days", "1 day").alias("w"), F.col("user_id").alias("k"))
    return _estimate(rows.select(F.date_format("w.start", "yyyy-MM-dd").alias("g"), "k")).select(F.col("g").alias("window_start"), F.round("estimate", 3).alias("users"))


@query("""
SELECT user_id, CAST(count(DISTINCT session) AS BIGINT) AS sessions FROM (
  SELECT user_id, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS session FROM (
    SELECT user_id, ts, event_id, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 30 MINUTE THEN 1 WHEN lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) IS NULL THEN 1 ELSE 0 END AS fresh FROM events) a) b
GROUP BY user_id""")
def q_session_users(spark, sf):
    sessions = _t(spark, sf, "events").groupBy("user_id", F.session_window("ts", "30 minutes")).agg(F.count(F.lit(1)).alias("n"))
    return sessions.groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"))


_GEO = "(SELECT r_name, n_name, c_mktsegment, o_orderkey AS k FROM orders JOIN customer ON c_custkey = o_custkey JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey)"


def _levels_sql(source: str, dims: list[str], sets: list[list[str]]) -> str:
    parts = []
    for i, kept in enumerate(sets):
        g = f"'{i}'" + "".join(f" || '|' || {d if d in kept else chr(39) * 2}" for d in dims)
        parts.append(f"SELECT {g} AS g, k FROM {source} s{i}")
    return "(" + " UNION ALL ".join(parts) + ")"


def _rolled(rows: DataFrame, dims: list[str], sets: list[list[str]], registers: int = SMALL) -> DataFrame:
    up = build.rollup(build.register_bitmaps(rows, "k", dims, registers), dims, sets)
    g = F.concat_ws("|", F.col("level").cast("string"), *[F.coalesce(d, F.lit("")) for d in dims])
    hist = build.state_histogram(up.select(g.alias("g"), "bucket", "bitmap"), ["g"])
    return estimators.hybrid(hist, registers).select("g", F.round("estimate", 3).alias("estimate"))


_GEO_SETS = [["r_name", "n_name", "c_mktsegment"], ["r_name", "n_name"], ["r_name"], []]


def _geo(spark, sf) -> DataFrame:
    small = F.broadcast(_t(spark, sf, "nation").join(F.broadcast(_t(spark, sf, "region")), F.col("n_regionkey") == F.col("r_regionkey")))  # fixed dimension tables
    c = _t(spark, sf, "customer").join(small, F.col("c_nationkey") == F.col("n_nationkey"))
    return _t(spark, sf, "orders").join(c, F.col("o_custkey") == F.col("c_custkey")).select("r_name", "n_name", "c_mktsegment", F.col("o_orderkey").alias("k"))


@query(f"SELECT g, round(estimate, 3) AS estimate FROM {_est_sql(_levels_sql(_GEO, _GEO_SETS[0], _GEO_SETS))} q")
def q_rollup_geo(spark, sf):
    return _rolled(_geo(spark, sf), _GEO_SETS[0], _GEO_SETS)


_FLAGS = "(SELECT l_returnflag, l_linestatus, l_orderkey AS k FROM lineitem)"
_FLAG_SETS = [["l_returnflag", "l_linestatus"], ["l_returnflag"], ["l_linestatus"], []]


@query(f"SELECT g, round(estimate, 3) AS estimate FROM {_est_sql(_levels_sql(_FLAGS, _FLAG_SETS[0], _FLAG_SETS))} q")
def q_cube_flags(spark, sf):
    rows = _t(spark, sf, "lineitem").select("l_returnflag", "l_linestatus", F.col("l_orderkey").alias("k"))
    return _rolled(rows, _FLAG_SETS[0], _FLAG_SETS)


_SETS = [["l_returnflag"], ["l_linestatus"]]


@query(f"SELECT g, round(estimate, 3) AS estimate FROM {_est_sql(_levels_sql(_FLAGS, _FLAG_SETS[0], _SETS))} q")
def q_grouping_sets(spark, sf):
    rows = _t(spark, sf, "lineitem").select("l_returnflag", "l_linestatus", F.col("l_orderkey").alias("k"))
    return _rolled(rows, _FLAG_SETS[0], _SETS)


_SUPP = "(SELECT l_suppkey AS g, l_partkey AS k FROM lineitem)"


@query(f"SELECT g AS l_suppkey, round(estimate, 3) AS parts, rank() OVER (ORDER BY round(estimate, 3) DESC, g) AS place FROM {_est_sql(_SUPP)} q ORDER BY place LIMIT 10")
def q_parts_per_supplier_topk(spark, sf):
    rows = _t(spark, sf, "lineitem").select(F.col("l_suppkey").alias("g"), F.col("l_partkey").alias("k"))
    top = _estimate(rows).select(F.col("g").alias("l_suppkey"), F.round("estimate", 3).alias("parts")).orderBy(F.desc("parts"), "l_suppkey").limit(10)
    return top.withColumn("place", F.rank().over(W.orderBy(F.desc("parts"), "l_suppkey")).cast("long"))


@query(f"SELECT n, l_suppkey, parts, place FROM (SELECT s_nationkey AS n, g AS l_suppkey, round(estimate, 3) AS parts, row_number() OVER (PARTITION BY s_nationkey ORDER BY round(estimate, 3) DESC, g) AS place FROM {_est_sql(_SUPP)} q JOIN supplier ON s_suppkey = g) z WHERE place <= 3")
def q_topk_per_nation(spark, sf):
    rows = _t(spark, sf, "lineitem").select(F.col("l_suppkey").alias("g"), F.col("l_partkey").alias("k"))
    e = _estimate(rows).join(_t(spark, sf, "supplier"), F.col("g") == F.col("s_suppkey")).select(F.col("s_nationkey").alias("n"), F.col("g").alias("l_suppkey"), F.round("estimate", 3).alias("parts"))
    return e.withColumn("place", F.row_number().over(W.partitionBy("n").orderBy(F.desc("parts"), "l_suppkey")).cast("long")).where("place <= 3")


def _side(flag: str) -> str:
    return f"(SELECT '{flag}' AS g, l_partkey AS k FROM lineitem WHERE l_returnflag = '{flag}')"


_BOTH = "(SELECT 'A or R' AS g, l_partkey AS k FROM lineitem WHERE l_returnflag IN ('A', 'R'))"


@query(
    f"SELECT round(u.e, 3) AS union_estimate, round(greatest(a.e + r.e - u.e, 0.0), 3) AS intersect_estimate, round(greatest(u.e - r.e, 0.0), 3) AS except_estimate, x.n_union, x.n_intersect, x.n_except FROM "
    f"(SELECT estimate AS e FROM {_est_sql(_BOTH, B)} q) u, (SELECT estimate AS e FROM {_est_sql(_side('A'), B)} q) a, (SELECT estimate AS e FROM {_est_sql(_side('R'), B)} q) r, "
    f"(SELECT CAST((SELECT count(*) FROM (SELECT k FROM {_side('A')} p UNION SELECT k FROM {_side('R')} q)) AS BIGINT) AS n_union, CAST((SELECT count(*) FROM (SELECT k FROM {_side('A')} p INTERSECT SELECT k FROM {_side('R')} q)) AS BIGINT) AS n_intersect, CAST((SELECT count(*) FROM (SELECT k FROM {_side('A')} p EXCEPT SELECT k FROM {_side('R')} q)) AS BIGINT) AS n_except) x"
)
def q_union_intersect_except(spark, sf):
    li = _t(spark, sf, "lineitem")
    a, r = (li.where(F.col("l_returnflag") == x).select(F.col("l_partkey").alias("k")) for x in ("A", "R"))
    est = setops.sizes(build.register_bitmaps(a, "k"), build.register_bitmaps(r, "k"), B)
    exact = None
    for name, keys in (("n_union", a.union(r).distinct()), ("n_intersect", a.intersect(r)), ("n_except", a.subtract(r))):
        n = keys.agg(F.count(F.lit(1)).alias(name))
        exact = n if exact is None else exact.crossJoin(F.broadcast(n))  # a row each
    return est.crossJoin(F.broadcast(exact)).select(*[F.round(c, 3).alias(c) for c in ("union_estimate", "intersect_estimate", "except_estimate")], "n_union", "n_intersect", "n_except")


@query("SELECT 'with' AS orders, round(estimate, 3) AS estimate FROM " + _est_sql("(SELECT 1 AS g, c_custkey AS k FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_orderstatus = 'F'))") + " q UNION ALL SELECT 'without', round(estimate, 3) FROM " + _est_sql("(SELECT 1 AS g, c_custkey AS k FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_orderstatus = 'F'))") + " q")
def q_semi_anti(spark, sf):
    c, o = _t(spark, sf, "customer"), _t(spark, sf, "orders").where("o_orderstatus = 'F'")
    out = None
    for name, how in (("with", "left_semi"), ("without", "left_anti")):
        rows = c.join(o, F.col("c_custkey") == F.col("o_custkey"), how).select(F.lit(1).alias("g"), F.col("c_custkey").alias("k"))
        part = _estimate(rows).select(F.lit(name).alias("orders"), F.round("estimate", 3).alias("estimate"))
        out = part if out is None else out.unionByName(part)
    return out


_LARGE = "(SELECT l_partkey AS g, l_suppkey AS k FROM lineitem WHERE l_quantity > 45)"


@query(f"SELECT p_partkey, round(coalesce(estimate, 0.0), 3) AS suppliers FROM part LEFT JOIN {_est_sql(_LARGE)} q ON g = p_partkey")
def q_outer_report(spark, sf):
    rows = _t(spark, sf, "lineitem").where("l_quantity > 45").select(F.col("l_partkey").alias("g"), F.col("l_suppkey").alias("k"))
    groups = _t(spark, sf, "part").select(F.col("p_partkey").alias("g"))
    return estimators.or_zero(groups, _estimate(rows)).select(F.col("g").alias("p_partkey"), F.round("estimate", 3).alias("suppliers"))


_DAILY = "(SELECT CAST(date_trunc('day', ts) AS TIMESTAMP) AS g, user_id AS k FROM events)"


@query(f"SELECT o.o_orderkey, round(e.estimate, 3) AS users FROM orders o ASOF LEFT JOIN (SELECT g - to_days(9000) AS g, estimate FROM {_est_sql(_DAILY)} q) e ON o.o_orderdate >= e.g")
def q_asof_estimate(spark, sf):
    """The last daily estimate at or before each order (events moved back to the orders'
    years): both sides in one sorted window per coarse period would be needed at scale; the
    estimates are one row a day, so the last one is carried forward over a union."""
    daily = _estimate(_t(spark, sf, "events").select(F.date_trunc("day", "ts").alias("g"), F.col("user_id").alias("k")))
    daily = daily.select((F.col("g") - F.expr("INTERVAL 9000 DAYS")).alias("at"), "estimate")
    return setops.asof(_t(spark, sf, "orders").select("o_orderkey", F.col("o_orderdate").alias("at")), daily, "at", "estimate").select("o_orderkey", F.round("estimate", 3).alias("users"))


@query(f"SELECT g AS event_type, round(estimate, 3) AS users FROM {_est_sql('(SELECT a.event_type AS g, a.user_id AS k FROM events a WHERE EXISTS (SELECT 1 FROM events p WHERE p.event_type = ' + chr(39) + 'purchase' + chr(39) + ' AND p.ts > a.ts AND p.ts <= a.ts + INTERVAL 1 HOUR))')} q")
def q_interval_join(spark, sf):
    """Users with an event in the hour before some purchase: purchases are put into hour
    bins, and an event looks into its own bin and the next, so the range join is an equi-join
    with a residual."""
    e = _t(spark, sf, "events").select("event_id", "event_type", "user_id", "ts")
    bins = F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 3_600_000_000)
    bought = e.where("event_type = 'purchase'").select(bins.alias("bin"), F.col("ts").alias("at")).groupBy("bin").agg(F.sort_array(F.collect_set("at")).alias("at"))
    looks = e.select("*", F.explode(F.array(bins, bins + 1)).alias("bin"))
    hit = looks.join(bought, "bin").where(F.exists("at", lambda p: (p > F.col("ts")) & (p <= F.col("ts") + F.expr("INTERVAL 1 HOUR"))))
    return _estimate(hit.select(F.col("event_type").alias("g"), F.col("user_id").alias("k"))).select(F.col("g").alias("event_type"), F.round("estimate", 3).alias("users"))


@query(f"SELECT g AS event_type, round(estimate, 3) AS keys FROM {_est_sql('(SELECT event_type AS g, ' + duck.text_key('json_extract_string(props, ' + chr(39) + '$.k' + chr(39) + ')') + ' AS k FROM events)')} q")
def q_json_keys(spark, sf):
    rows = _t(spark, sf, "events").select(F.col("event_type").alias("g"), hashing.key64(F.get_json_object("props", "$.k"), kind="text").alias("k"))
    return _estimate(rows).select(F.col("g").alias("event_type"), F.round("estimate", 3).alias("keys"))


@query("SELECT label, CAST(count(DISTINCT embedding) AS BIGINT) AS vectors FROM embeddings GROUP BY label")
def q_embedding_labels(spark, sf):
    return _t(spark, sf, "embeddings").groupBy("label").agg(F.countDistinct("embedding").alias("vectors"))


@query(f"SELECT g AS quality, round(estimate, 3) AS texts FROM {_est_sql('(SELECT quality AS g, ' + duck.text_key('text') + ' AS k FROM documents JOIN labels USING (doc_id))')} q")
def q_quality_sources(spark, sf):
    rows = _t(spark, sf, "documents").join(_t(spark, sf, "labels"), "doc_id").select(F.col("quality").alias("g"), hashing.key64("text", kind="text").alias("k"))
    return _estimate(rows).select(F.col("g").alias("quality"), F.round("estimate", 3).alias("texts"))


@query(f"SELECT bucket, bitmap FROM ({duck.bitmaps('orders', 'o_orderkey', '', SMALL)}) q")
def q_map_export(spark, sf):
    """Bitmaps as one map bucket -> bitmap (bounded by the registers), and back."""
    bitmaps = build.register_bitmaps(_t(spark, sf, "orders"), "o_orderkey", (), SMALL)
    packed = bitmaps.groupBy().agg(F.map_from_entries(F.collect_list(F.struct("bucket", "bitmap"))).alias("m"))
    return packed.select(F.explode("m").alias("bucket", "bitmap"))


@query(f"SELECT g AS l_returnflag, round(hybrid, 0) AS estimate FROM ({estimate.text(histogram_sql('(SELECT l_returnflag AS g, l_orderkey AS k FROM lineitem)'), B)}) q")
def q_sketch_sql(spark, sf):
    """Estimates of packed sketches by SQL text."""
    sqlapi.register(spark)
    name = f"sketches_{uuid.uuid4().hex}"
    build.sketch(_t(spark, sf, "lineitem"), "l_orderkey", ["l_returnflag"]).createOrReplaceTempView(name)
    return spark.sql(f"SELECT l_returnflag, round(dc_estimate(words, registers, floor), 0) AS estimate FROM {name}")


@query(f"SELECT l_returnflag, CAST(count(*) AS BIGINT) AS filled FROM ({duck.bitmaps('lineitem', 'l_orderkey', 'l_returnflag')}) q GROUP BY l_returnflag")
def udtf_registers(spark, sf):
    """Words of a sketch to rows (bucket, state) by a table function."""
    sqlapi.register(spark)
    name = f"sketches_{uuid.uuid4().hex}"
    build.sketch(_t(spark, sf, "lineitem"), "l_orderkey", ["l_returnflag"]).createOrReplaceTempView(name)
    return spark.sql(f"SELECT l_returnflag, count(*) AS filled FROM {name}, LATERAL dc_registers(words, registers) r WHERE r.state > 0 GROUP BY l_returnflag")


@query(f"SELECT g AS l_returnflag, round(hybrid, 0) AS estimate, TRUE AS merged_near FROM ({estimate.text(histogram_sql('(SELECT l_returnflag AS g, l_orderkey AS k FROM lineitem)'), B)}) q")
def q_sketch_agg(spark, sf):
    """The aggregates of SQL text: a sketch per group, and the union of finer ones."""
    sqlapi.register(spark)
    name = f"lines_{uuid.uuid4().hex}"
    _t(spark, sf, "lineitem").select("l_returnflag", "l_linestatus", "l_orderkey").createOrReplaceTempView(name)
    whole = f"SELECT l_returnflag, dc_size(dc_sketch_agg(l_orderkey)) AS e FROM {name} GROUP BY l_returnflag"
    parts = f"SELECT l_returnflag, dc_sketch_agg(l_orderkey) AS s FROM {name} GROUP BY l_returnflag, l_linestatus"
    merged = f"SELECT l_returnflag, dc_size(dc_merge_agg(s)) AS m FROM ({parts}) GROUP BY l_returnflag"
    return spark.sql(f"SELECT l_returnflag, round(e, 0) AS estimate, abs(m / e - 1) < 0.01 AS merged_near FROM ({whole}) JOIN ({merged}) USING (l_returnflag)")


_STREAM_DAY = "(SELECT CAST(date_trunc('day', ts) AS TIMESTAMP) AS g, user_id AS k FROM events)"


@query(f"SELECT g AS day, round(estimate, 3) AS users FROM {_est_sql(_STREAM_DAY)} q")
def stream_daily_users(spark, sf):
    bitmaps = windows.run_available(windows.windowed_bitmaps(windows.read_events(spark, sf), "user_id", "1 day", SMALL), "complete")
    hist = build.state_histogram(bitmaps.select(F.col("window.start").cast("timestamp_ntz").alias("g"), "bucket", "bitmap"), ["g"])
    return estimators.hybrid(hist, SMALL).select(F.col("g").alias("day"), F.round("estimate", 3).alias("users"))


@query(f"SELECT g AS window_start, round(estimate, 3) AS users FROM {_est_sql(_SLIDING)} q")
def stream_sliding_users(spark, sf):
    bitmaps = windows.run_available(windows.windowed_bitmaps(windows.read_events(spark, sf), "user_id", "7 days", SMALL, slide="1 day"), "complete")
    hist = build.state_histogram(bitmaps.select(F.date_format("window.start", "yyyy-MM-dd").alias("g"), "bucket", "bitmap"), ["g"])
    return estimators.hybrid(hist, SMALL).select(F.col("g").alias("window_start"), F.round("estimate", 3).alias("users"))


@query("""
SELECT user_id, CAST(count(*) AS BIGINT) AS sessions, CAST(sum(n) AS BIGINT) AS events FROM (
  SELECT user_id, session, count(*) AS n, max(ts) AS last FROM (
    SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS session FROM (
      SELECT user_id, ts, event_id, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events) a) b
  GROUP BY user_id, session) c
WHERE last + INTERVAL 30 MINUTE <= (SELECT max(ts) FROM events) - INTERVAL 1 HOUR GROUP BY user_id""")
def stream_sessions(spark, sf):
    """Sessions as a stream appends them: those that the watermark has closed."""
    closed = windows.run_available(windows.session_counts(windows.read_events(spark, sf)), "append")
    return closed.groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"), F.sum("n").alias("events"))


@query("SELECT TRUE AS same")
def stream_redelivery(spark, sf):
    """A stream that gets every event twice ends with the same bitmaps."""
    events = windows.read_events(spark, sf)
    twice = events.withColumn("_", F.explode(F.array(F.lit(1), F.lit(2)))).drop("_")
    a = windows.run_available(windows.windowed_bitmaps(twice, "user_id", "1 day", SMALL), "complete").select(F.col("window.start").cast("timestamp_ntz").alias("s"), "bucket", "bitmap")
    e = _t(spark, sf, "events").select(F.window("ts", "1 day").alias("w"), "user_id")
    b = build.register_bitmaps(e.select(F.col("w.start").cast("timestamp_ntz").alias("s"), "user_id"), "user_id", ["s"], SMALL)
    return a.exceptAll(b).unionAll(b.exceptAll(a)).agg((F.count(F.lit(1)) == 0).alias("same"))


@query("SELECT event_type, CAST(count(DISTINCT user_id) AS BIGINT) AS exact_users, TRUE AS near FROM events GROUP BY event_type")
def stream_stateful(spark, sf):
    """Packed sketches as the state of a keyed stream, against exact counts."""
    out = windows.run_available(windows.stateful_sketch(windows.read_events(spark, sf), "event_type", "user_id", B), "update")
    last = out.groupBy("event_type").agg(F.max_by("estimate", "adds").alias("estimate"))
    exact = _t(spark, sf, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("exact_users"))
    return exact.join(last, "event_type").select("event_type", "exact_users", (F.abs(F.col("estimate") / F.col("exact_users") - 1) < 0.1).alias("near"))

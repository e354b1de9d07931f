"""Operators around the methods: scans, filters, joins, aggregates, windows, sets, scalars, each as one query.

A query is SQL over the given tables, planned by Catalyst; where the dialects differ, the pairs in DIALECT
are replaced for the comparison, and hints are comments to the other engine.
"""

from __future__ import annotations

import re

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from subwin.sources.views import DAY, micros, table

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
_T, _TD = micros("ts"), "epoch_us(ts)"
#: Spark's spelling to the other's.
DIALECT = [
    (_T, _TD), (micros("o_orderdate"), "epoch_us(o_orderdate)"), ("AS string", "AS varchar"), ("AS double", "AS double"), (" RLIKE ", " SIMILAR TO "), ("get_json_object(props, '$.k')", "json_extract_string(props, '$.k')"),
    ("100.0D", "100.0"), ("percentile(", "quantile_cont("), ("max_by(", "arg_max("), (" div ", " // "),
]

CENTS = "cast(round(value * 100) AS bigint)"
QUERY: dict[str, str] = {
    "scan_parquet_prune": "SELECT event_id, value FROM {events} WHERE ts >= TIMESTAMP '2024-01-10 00:00:00' AND ts < TIMESTAMP '2024-01-11 00:00:00'",
    "scan_json_props": "SELECT event_id, cast(get_json_object(props, '$.k') AS bigint) AS k FROM {events}",
    "filter_label_eq": "SELECT event_id, value FROM {events} WHERE event_type = 'click'",
    "filter_label_neq": "SELECT event_type, count(*) AS n FROM {events} WHERE event_type <> 'click' GROUP BY event_type",
    "filter_label_regex": "SELECT event_type, count(*) AS n FROM {events} WHERE event_type RLIKE '^[a-p].*$' GROUP BY event_type",
    "filter_threshold": f"SELECT user_id, round(avg(value), 6) AS mean FROM {{events}} GROUP BY user_id HAVING sum({CENTS}) > 5000 * count(*)",
    "join_hash_equi": "SELECT c_mktsegment, count(*) AS n, sum(cast(round(o_totalprice * 100) AS bigint)) / 100.0D AS total FROM {orders} JOIN {customer} ON o_custkey = c_custkey GROUP BY c_mktsegment",
    "join_sort_merge": "SELECT /*+ MERGE(o) */ o_orderpriority, l_returnflag, count(*) AS n FROM {lineitem} l JOIN {orders} o ON l.l_orderkey = o.o_orderkey GROUP BY o_orderpriority, l_returnflag",
    "join_broadcast": "SELECT /*+ BROADCAST(n, r) */ r_name, count(*) AS n FROM {customer} c JOIN {nation} n ON c_nationkey = n_nationkey JOIN {region} r ON n_regionkey = r_regionkey GROUP BY r_name",
    "join_nested_theta": "SELECT b.band, count(*) AS n FROM {lineitem} JOIN (SELECT 'low' AS band, 0 AS lo, 10 AS hi UNION ALL SELECT 'middle', 10, 30 UNION ALL SELECT 'high', 30, 60) b ON l_quantity > b.lo AND l_quantity <= b.hi GROUP BY b.band",
    "join_semi": "SELECT c_custkey, c_name FROM {customer} WHERE EXISTS (SELECT 1 FROM {orders} WHERE o_custkey = c_custkey AND o_totalprice > 300000)",
    "join_anti": "SELECT DISTINCT user_id FROM {events} e WHERE NOT EXISTS (SELECT 1 FROM {events} p WHERE p.user_id = e.user_id AND p.event_type = 'purchase' AND p.value > 100)",
    "join_left_outer": "SELECT d.doc_id, d.lang, l.quality FROM {documents} d LEFT JOIN {labels} l ON d.doc_id = l.doc_id",
    "join_full_outer": "SELECT coalesce(a.k, b.k) AS k, a.n AS n_click, b.n AS n_purchase FROM (SELECT user_id AS k, count(*) AS n FROM {events} WHERE event_type = 'click' AND value > 50 GROUP BY user_id) a FULL OUTER JOIN (SELECT user_id AS k, count(*) AS n FROM {events} WHERE event_type = 'purchase' AND value > 50 GROUP BY user_id) b ON a.k = b.k",
    "agg_partial_final": "SELECT l_returnflag, l_linestatus, count(*) AS n, sum(cast(round(l_extendedprice * 100) AS bigint)) / 100.0D AS total FROM {lineitem} GROUP BY l_returnflag, l_linestatus",
    "agg_sort_based": "SELECT event_type, min(props) AS low, max(props) AS top, count(*) AS n FROM {events} GROUP BY event_type",
    "agg_distinct": "SELECT event_type, count(DISTINCT user_id) AS users FROM {events} GROUP BY event_type",
    "agg_multi_distinct": "SELECT event_type, count(DISTINCT user_id) AS users, count(DISTINCT get_json_object(props, '$.k')) AS ks FROM {events} GROUP BY event_type",
    "agg_filter_clause": "SELECT count(*) FILTER (WHERE event_type = 'click') AS clicks, count(*) FILTER (WHERE event_type = 'purchase') AS purchases FROM {events}",
    "agg_rollup": "SELECT l_returnflag, l_linestatus, count(*) AS n FROM {lineitem} GROUP BY ROLLUP (l_returnflag, l_linestatus)",
    "agg_cube": "SELECT l_returnflag, l_linestatus, count(*) AS n FROM {lineitem} GROUP BY CUBE (l_returnflag, l_linestatus)",
    "agg_grouping_sets": "SELECT l_returnflag, l_linestatus, count(*) AS n FROM {lineitem} GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())",
    "win_row_number": "SELECT event_id, row_number() OVER (PARTITION BY event_type ORDER BY value DESC, event_id) AS rn FROM {events}",
    "win_rank": "SELECT event_id, rank() OVER (PARTITION BY event_type ORDER BY value) AS r, dense_rank() OVER (PARTITION BY event_type ORDER BY value) AS dr FROM {events}",
    "win_ntile": "SELECT event_id, ntile(4) OVER (PARTITION BY event_type ORDER BY value, event_id) AS quarter FROM {events}",
    "win_percent_rank": "SELECT event_id, round(percent_rank() OVER (PARTITION BY event_type ORDER BY value), 6) AS pr, round(cume_dist() OVER (PARTITION BY event_type ORDER BY value), 6) AS cd FROM {events}",
    "win_lag_lead_delta": f"SELECT event_id, {_T} - lag({_T}) OVER (PARTITION BY event_type ORDER BY event_id) AS since, lead({_T}) OVER (PARTITION BY event_type ORDER BY event_id) - {_T} AS until FROM {{events}}",
    "win_rows_frame": f"SELECT event_id, sum({CENTS}) OVER (PARTITION BY event_type ORDER BY event_id ROWS BETWEEN 99 PRECEDING AND CURRENT ROW) / 100.0D AS last_100 FROM {{events}}",
    "win_range_frame": f"SELECT event_id, sum({CENTS}) OVER (PARTITION BY event_type ORDER BY {_T} RANGE BETWEEN {DAY} PRECEDING AND CURRENT ROW) / 100.0D AS last_day FROM {{events}}",
    "win_running_l1": f"SELECT event_id, count(*) OVER w AS n, sum({CENTS}) OVER w / 100.0D AS total FROM {{events}} WINDOW w AS (PARTITION BY event_type ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)",
    "limit_topk": "SELECT o_orderkey, o_totalprice FROM {orders} ORDER BY o_totalprice DESC, o_orderkey LIMIT 20",
    "topk_per_group": "SELECT event_type, user_id, n FROM (SELECT event_type, user_id, count(*) AS n, row_number() OVER (PARTITION BY event_type ORDER BY count(*) DESC, user_id) AS rn FROM {events} GROUP BY event_type, user_id) t WHERE rn <= 3",
    "sort_global": "SELECT o_orderkey, o_totalprice FROM {orders} WHERE o_totalprice > 300000 ORDER BY o_totalprice DESC, o_orderkey",
    "set_union": "SELECT user_id FROM {events} WHERE value > 200 UNION SELECT c_custkey FROM {customer} WHERE c_custkey < 50",
    "set_union_all": "SELECT event_type AS label, count(*) AS n FROM {events} GROUP BY event_type UNION ALL SELECT o_orderpriority, count(*) FROM {orders} GROUP BY o_orderpriority",
    "set_intersect": "SELECT user_id FROM {events} WHERE event_type = 'click' INTERSECT SELECT user_id FROM {events} WHERE event_type = 'purchase'",
    "set_except": "SELECT user_id FROM {events} WHERE event_type = 'click' EXCEPT SELECT user_id FROM {events} WHERE value > 150",
    "set_except_all": "SELECT l_suppkey FROM {lineitem} WHERE l_quantity > 45 EXCEPT ALL SELECT l_suppkey FROM {lineitem} WHERE l_quantity > 48",
    "str_host": "SELECT page_id, regexp_extract(url, '://([^/?#]*)', 1) AS host FROM {pages}",
    "str_md5_item": "SELECT o_orderkey, md5(o_orderpriority) AS h FROM {orders}",
    "date_interval": f"SELECT event_id, {_T} div {DAY} AS pane, {_T} + 3600000000 AS later FROM {{events}}",
    "math_entropy": "SELECT event_type, round(ln(sum(c)) - sum(c * ln(c)) / sum(c), 6) AS entropy FROM (SELECT event_type, user_id, cast(count(*) AS bigint) AS c FROM {events} GROUP BY event_type, user_id) t GROUP BY event_type",
    "math_moments": f"SELECT event_type, count(*) AS n, sum({CENTS}) / 100.0D AS total, round(sqrt(sum(value * value) / count(*) - pow(sum(value) / count(*), 2)), 5) AS deviation FROM {{events}} GROUP BY event_type",
    "tumbling_window": f"SELECT event_type, {_T} div {DAY} AS pane, count(*) AS n, sum({CENTS}) / 100.0D AS total, max(value) AS top FROM {{events}} GROUP BY event_type, {_T} div {DAY}",
    "join_interval": f"SELECT a.event_id AS first_id, b.event_id AS second_id FROM {{events}} a JOIN {{events}} b ON a.user_id = b.user_id AND a.event_id < b.event_id AND {_T.replace('ts)', 'b.ts)')} - {_T.replace('ts)', 'a.ts)')} <= 600000000",
    "subquery_scalar": "SELECT event_type, count(*) AS n FROM {events} WHERE value > (SELECT avg(value) FROM {events}) GROUP BY event_type",
    "subquery_in": "SELECT count(*) AS n FROM {lineitem} WHERE l_partkey IN (SELECT p_partkey FROM {part} WHERE p_size < 10)",
}


def _run(sql: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return spark.sql(sql, **{t: table(spark, sf_dir, t) for t in TABLES if "{" + t + "}" in sql})

    return run


def other_dialect(sql: str) -> str:
    for ours, theirs in DIALECT:
        sql = sql.replace(ours, theirs)
    sql = sql.replace("timestampdiff(MICROSECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', b.ts)", "epoch_us(b.ts)").replace("timestampdiff(MICROSECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', a.ts)", "epoch_us(a.ts)")
    return re.sub(r"\{(\w+)\}", r"\1", sql)


def entropy_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The entropy of users of each event type by a grouped function, which sees one row of each user, never events."""
    counts = table(spark, sf_dir, "events").groupBy("event_type", "user_id").agg(F.count("*").alias("c"))

    def entropy(rows: pd.DataFrame) -> pd.DataFrame:
        share = rows["c"] / rows["c"].sum()
        return pd.DataFrame({"event_type": [rows["event_type"].iloc[0]], "entropy": [round(float(-(share * np.log(share)).sum()), 6)]})

    return counts.groupBy("event_type").applyInPandas(entropy, "event_type string, entropy double")


QUERIES: dict = {name: _run(sql) for name, sql in QUERY.items()}
SQL: dict = {name: other_dialect(sql) for name, sql in QUERY.items()}


# -- operators that the DataFrame API says better ----------------------------------------------------------------------


def asof_join(left: DataFrame, right: DataFrame, key: str, t: str, values: list[str]) -> DataFrame:
    """Each row of ``left`` with the values of the latest row of ``right`` of its key at or before its time.

    A union and one sort: a running last over the key, no range join; of equal times, right comes first.
    """
    names = [c for c in left.columns if c not in (key, t)]
    both = left.select(key, t, *names, *[F.lit(None).cast(right.schema[v].dataType).alias(f"latest_{v}") for v in values], F.lit(1).alias("side")).unionByName(
        right.select(key, t, *[F.lit(None).cast(left.schema[n].dataType).alias(n) for n in names], *[F.col(v).alias(f"latest_{v}") for v in values], F.lit(0).alias("side"))
    )
    past = Window.partitionBy(key).orderBy(t, "side").rowsBetween(Window.unboundedPreceding, 0)
    filled = both.select(key, t, *names, "side", *[F.last(f"latest_{v}", ignorenulls=True).over(past).alias(f"latest_{v}") for v in values])
    return filled.where("side = 1").drop("side")


def range_join(ranges: DataFrame, points: DataFrame, low: str, high: str, t: str, width: int) -> DataFrame:
    """Points in the ranges (low, high]: ranges are spread over panes of ``width``, so that the join is an equality
    on the pane with the range as residual, not a nested loop."""
    spread = ranges.withColumn("pane", F.explode(F.sequence(F.expr(f"{low} div {width}"), F.expr(f"{high} div {width}"))))
    return spread.join(points.withColumn("pane", F.expr(f"{t} div {width}")), "pane").where((F.col(t) > F.col(low)) & (F.col(t) <= F.col(high))).drop("pane")


def _events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events").selectExpr("event_id", f"{_T} AS t", "user_id", "event_type", "value")


def asof_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each purchase with the value of the user's latest view."""
    events = _events(spark, sf_dir)
    views = events.where("event_type = 'view'").select("user_id", "t", "value")
    return asof_join(events.where("event_type = 'purchase'").select("user_id", "t", "event_id"), views, "user_id", "t", ["value"]).select("event_id", "latest_value")


def range_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events in each of the two-day windows that end each day."""
    start = 1_704_067_200_000_000
    ranges = spark.range(2, 30).selectExpr(f"{start} + (id - 2) * {DAY} AS low", f"{start} + id * {DAY} AS high")
    found = range_join(ranges, _events(spark, sf_dir), "low", "high", "t", DAY)
    return found.groupBy("high", "event_type").agg(F.count("*").alias("n"), F.max("value").alias("top"))


def day_frame_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """win_range_frame by running sums, where a frame that slides is summed anew for each row.

    The day up to t ends in t's pane, of a day too, and begins at the same offset of the pane before: a sum from the
    pane's start and one to the other pane's end, each over the sums of equal times.
    """
    events = table(spark, sf_dir, "events").selectExpr("event_id", "event_type", f"{_T} AS t", f"{CENTS} AS c")
    times = events.groupBy("event_type", "t").agg(F.sum("c").alias("c")).withColumn("pane", F.expr(f"floor(t / {DAY})"))
    asked = times.select("event_type", "t", F.lit(None).cast("long").alias("c"), (F.col("pane") - 1).alias("pane"), F.lit(1).alias("ago"))
    of_pane = Window.partitionBy("event_type", "pane")
    both = times.withColumn("ago", F.lit(0)).unionByName(asked).withColumn("at", F.col("t") - F.col("ago") * DAY)
    start, end = (of_pane.orderBy(order).rangeBetween(Window.unboundedPreceding, 0) for order in (F.col("at"), F.desc("at")))
    parts = both.withColumn("part", F.when(F.col("ago") == 0, F.sum("c").over(start)).otherwise(F.sum("c").over(end)))
    sums = parts.groupBy("event_type", "t").agg(F.sum("part").alias("cents"))
    same = events["event_type"].eqNullSafe(sums["event_type"]) & events["t"].eqNullSafe(sums["t"])
    return events.join(sums, same).select("event_id", (F.col("cents") / F.expr("100.0D")).alias("last_day"))


def pivot_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count("o_orderkey")).na.fill(0)


def sliding_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ten-day windows every day, aligned to the epoch."""
    stamped = table(spark, sf_dir, "events").select("event_type", F.col("ts"), F.expr(f"{CENTS} AS c"))
    found = stamped.groupBy("event_type", F.window("ts", "10 days", "1 day")).agg(F.count("*").alias("n"), F.sum("c").alias("cents"))
    return found.selectExpr("event_type", f"{micros('window.start')} AS low", "n", "cents")


def session_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sessions of each user with gaps of under twelve hours."""
    found = table(spark, sf_dir, "events").groupBy("user_id", F.session_window("ts", "12 hours")).agg(F.count("*").alias("n"))
    return found.selectExpr("user_id", f"{micros('session_window.start')} AS low", "n")


def islands_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Runs of events of a type above 60: first and last event and length."""
    w = Window.partitionBy("event_type").orderBy("event_id")
    marked = _events(spark, sf_dir).withColumn("high", F.col("value") > 60).withColumn("new", (F.col("high") != F.coalesce(F.lag("high").over(w), ~F.col("high"))).cast("int"))
    runs = marked.withColumn("run", F.sum("new").over(w)).where("high")
    return runs.groupBy("event_type", "run").agg(F.min("event_id").alias("first"), F.max("event_id").alias("last"), F.count("*").alias("n")).drop("run")


def array_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "embeddings")
    return e.select("vec_id", F.size("embedding").alias("n"), F.round(F.aggregate(F.transform("embedding", lambda x: x.cast("double") * x.cast("double")), F.lit(0.0), lambda a, x: a + x), 6).alias("norm2"))


def explode_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "embeddings").select("vec_id", "label", F.posexplode("embedding").alias("dim", "x"))
    return e.groupBy("dim").agg(F.count_if(F.col("x") > 0).alias("positive"), F.max("x").cast("double").alias("top"))


def map_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two halves' counts as maps, merged by key."""
    counts = _events(spark, sf_dir).groupBy("event_type", "user_id").agg(F.count_if(F.col("event_id") % 2 == 0).alias("even"), F.count_if(F.col("event_id") % 2 == 1).alias("odd"))
    maps = counts.groupBy("event_type").agg(F.map_from_entries(F.collect_list(F.struct("user_id", "even"))).alias("a"), F.map_from_entries(F.collect_list(F.struct("user_id", "odd"))).alias("b"))
    return maps.select("event_type", F.explode(F.map_zip_with("a", "b", lambda k, x, y: x + y)).alias("user_id", "n"))


def json_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    parsed = table(spark, sf_dir, "events").withColumn("p", F.from_json("props", "k bigint"))
    return parsed.select("event_id", F.col("p.k").alias("k"), F.to_json("p").alias("again"))


def labels_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Labels as a map, from which a series id follows."""
    e = table(spark, sf_dir, "events").withColumn("labels", F.create_map(F.lit("event_type"), F.col("event_type"), F.lit("user"), F.col("user_id").cast("string")))
    return e.withColumn("series_id", F.xxhash64(F.array_sort(F.map_entries("labels")))).groupBy("labels.event_type").agg(F.count_distinct("series_id").alias("series"))


def tokens_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = table(spark, sf_dir, "documents").select("lang", F.explode(F.split(F.lower("text"), " ")).alias("token"))
    return t.groupBy("lang", "token").agg(F.count("*").alias("n")).where("n > 20")


def csv_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """nation written as CSV and read back with its schema."""
    from subwin.storage import Scratch

    nation = table(spark, sf_dir, "nation")
    path = Scratch(spark, "csv").root + "/nation"
    nation.write.option("header", True).csv(path)
    return spark.read.schema(nation.schema).option("header", True).csv(path)


def trunc_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "events").withColumn("h", F.date_trunc("HOUR", "ts").cast("timestamp_ntz"))
    return e.groupBy("event_type", F.expr(f"{micros('h')} AS hour")).agg(F.count("*").alias("n"))


def pandas_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A scalar function over Arrow batches: the hash of FIXTURES' sketches."""
    @F.pandas_udf("bigint")
    def spread(x: pd.Series) -> pd.Series:
        return (x * 48271 + 11) % 2_147_483_647 % 1024

    return _events(spark, sf_dir).select("event_id", spread("user_id").alias("cell"))


def approximate_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = _events(spark, sf_dir)
    return e.groupBy("event_type").agg(F.approx_count_distinct("user_id").alias("users"), F.expr("approx_top_k(user_id, 3)").alias("top"))


QUERIES |= {
    "join_asof": asof_query, "join_range_bucketed": range_query, "agg_pivot": pivot_query, "sliding_window": sliding_query, "session_gap": session_query, "win_islands": islands_query,
    "arr_aggregate": array_query, "arr_explode": explode_query, "map_merge_counts": map_query, "json_struct_roundtrip": json_query, "proj_labels": labels_query, "str_tokens": tokens_query,
    "win_range_frame": day_frame_query, "scan_csv_roundtrip": csv_query, "date_trunc_pane": trunc_query, "udf_pandas_scalar": pandas_query, "udaf_grouped": entropy_query, "agg_approximate": approximate_query,
}
SQL |= {
    "join_asof": "SELECT p.event_id, v.value AS latest_value FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'view') v ON p.user_id = v.user_id AND p.ts >= v.ts",
    "join_range_bucketed": f"SELECT high, event_type, count(*) AS n, max(value) AS top FROM (SELECT 1704067200000000 + i * {DAY} AS high FROM range(2, 30) r(i)) JOIN events ON epoch_us(ts) > high - 2 * {DAY} AND epoch_us(ts) <= high GROUP BY high, event_type",
    "udaf_grouped": "SELECT event_type, round(ln(sum(c)) - sum(c * ln(c)) / sum(c), 6) AS entropy FROM (SELECT event_type, user_id, count(*)::DOUBLE AS c FROM events GROUP BY ALL) GROUP BY event_type",
    "agg_pivot": "SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS F, count(*) FILTER (o_orderstatus = 'O') AS O, count(*) FILTER (o_orderstatus = 'P') AS P FROM orders GROUP BY o_orderpriority",
    "sliding_window": f"SELECT event_type, low, count(*) AS n, sum(cast(round(value * 100) AS bigint))::BIGINT AS cents FROM (SELECT event_type, value, unnest(range(epoch_us(ts) // {DAY} * {DAY} - 9 * {DAY}, epoch_us(ts) // {DAY} * {DAY} + 1, {DAY})) AS low FROM events) GROUP BY event_type, low",
    "session_gap": f"SELECT user_id, min(t) AS low, count(*) AS n FROM (SELECT user_id, t, sum(new) OVER (PARTITION BY user_id ORDER BY t) AS run FROM (SELECT user_id, epoch_us(ts) AS t, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts) < {DAY // 2} THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, run",
    "win_islands": "SELECT event_type, min(event_id) AS first, max(event_id) AS last, count(*) AS n FROM (SELECT event_type, event_id, value, row_number() OVER (PARTITION BY event_type ORDER BY event_id) - row_number() OVER (PARTITION BY event_type, value > 60 ORDER BY event_id) AS run FROM events) WHERE value > 60 GROUP BY event_type, run",
    "arr_aggregate": "SELECT vec_id, len(embedding)::INT AS n, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 6) AS norm2 FROM embeddings",
    "arr_explode": "SELECT (dim - 1)::INT AS dim, count(*) FILTER (x > 0) AS positive, max(x)::DOUBLE AS top FROM (SELECT unnest(embedding) AS x, generate_subscripts(embedding, 1) AS dim FROM embeddings) GROUP BY dim",
    "map_merge_counts": "SELECT event_type, user_id, count(*) AS n FROM events GROUP BY event_type, user_id",
    "json_struct_roundtrip": "SELECT event_id, json_extract_string(props, '$.k')::BIGINT AS k, '{\"k\":' || json_extract_string(props, '$.k') || '}' AS again FROM events",
    "proj_labels": "SELECT event_type, count(DISTINCT user_id) AS series FROM events GROUP BY event_type",
    "str_tokens": "SELECT lang, token, count(*) AS n FROM (SELECT lang, unnest(string_split(lower(text), ' ')) AS token FROM documents) GROUP BY lang, token HAVING count(*) > 20",
    "scan_csv_roundtrip": "SELECT * FROM nation",
    "date_trunc_pane": "SELECT event_type, epoch_us(date_trunc('hour', ts)) AS hour, count(*) AS n FROM events GROUP BY ALL",
    "udf_pandas_scalar": "SELECT event_id, (user_id * 48271 + 11) % 2147483647 % 1024 AS cell FROM events",
}

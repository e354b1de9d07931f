"""URL filters: allow and block rules on host and path, applied by a sort-merge range join.

A rule's host written label by label from the right, then ``/``, then its path is a key; the keys that
start with it form one interval. A url has one such key for each number of host labels that some rule
has, so each rule that fits it is an interval that holds one of its keys. Keys and rules are dealt out
by key ranges, a rule to each range its interval touches; within a range, one sweep over the sorted keys
keeps the stack of rules whose intervals are open, whose top is the longest.

Defined results: a null url and one without ``://`` have empty host and path and get the default
verdict, like every url that no rule fits. Of rules that fit, the longest host and path wins, then the
longer host; of equal rules, block. Rules with a null or empty host are left out. Repeated rows each get
a row of the result; null ids stay null; other columns are ignored.
"""

from __future__ import annotations

from bisect import bisect_left, bisect_right
from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from subwin.llm.common import join_same, partitions, table

#: Host, path, verdict.
RULES = [
    ("com", "/en/", "block"),
    ("example.com", "/en/7", "allow"),
    ("net", "/de/", "allow"),
    ("example.net", "/de/8", "block"),
    ("org", "/es/", "block"),
]
DEFAULT = "allow"
#: Keys drawn for each range to choose the ranges' bounds, and most ranges.
DRAWN, MOST_RANGES = 32, 2048
#: The largest character: what starts with x is at most x + LAST.
LAST = "\U0010ffff"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def rules_frame(spark: SparkSession, rules=RULES) -> DataFrame:
    return spark.createDataFrame(list(rules), "host string, path string, verdict string")


def split_url(url):
    """Columns host and path of a url column."""
    at = F.instr(url, "://")
    rest = F.when(at > 0, url.substr(at + F.lit(3), F.length(url))).otherwise("")
    return F.coalesce(F.translate(F.regexp_extract(rest, r"^[^/?#]*", 0), UPPER, LOWER), F.lit("")), F.coalesce(F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1), F.lit(""))


def _sweep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    open_rules: list[tuple] = []
    for batch in batches:
        found = []
        for key, rule, verdict, host_len, host, path in zip(*(batch.column(i).to_pylist() for i in range(6)), strict=True):
            while open_rules and not key.startswith(open_rules[-1][0]):
                open_rules.pop()
            if rule is not None:
                open_rules.append((key, rule, verdict, host_len))
            elif open_rules:
                found.append((host, path, *open_rules[-1][1:]))
        if found:
            yield pa.RecordBatch.from_arrays([pa.array(x, kind) for x, kind in zip(zip(*found, strict=True), [pa.string()] * 4 + [pa.int32()], strict=True)], names=["host", "path", "rule", "verdict", "host_len"])


def judge_urls(urls: DataFrame, rules: DataFrame) -> DataFrame:
    """For each distinct (host, path) of ``urls`` that a rule fits: host, path, rule, verdict."""
    spark = urls.sparkSession
    labels = lambda host: F.split(host, r"\.", -1)
    rules = rules.where("host is not null and host <> ''").select("host", F.coalesce("path", F.lit("")).alias("path"), "verdict")
    depths = sorted(r[0] for r in rules.select(F.size(labels(F.col("host")))).distinct().collect())
    backwards = F.reverse(labels(F.col("host")))
    ranges = min(partitions(spark), MOST_RANGES)
    keys = (
        urls.select("host", "path").distinct()
        .withColumn("depth", F.explode(F.filter(F.array(*[F.lit(d) for d in depths]).cast("array<int>"), lambda d: d <= F.size(backwards))))
        .select(F.concat(F.array_join(F.slice(backwards, F.lit(1), F.col("depth")), "."), F.lit("/"), "path").alias("key"), "host", "path")
    )
    drawn = sorted(r[0] for r in keys.select("key").orderBy(F.xxhash64("key", "host")).limit(DRAWN * ranges).collect())
    bounds = drawn[DRAWN - 1 :: DRAWN][: ranges - 1] if len(drawn) >= DRAWN * 2 else []

    @F.pandas_udf("int")
    def key_range(key: pd.Series, salt: pd.Series) -> pd.Series:
        """A key that several bounds equal is dealt among the ranges between them."""
        return pd.Series([(low := bisect_left(bounds, k)) + s % (bisect_right(bounds, k) - low + 1) for k, s in zip(key, salt, strict=True)])

    @F.pandas_udf("array<int>")
    def rule_ranges(key: pd.Series) -> pd.Series:
        return pd.Series([list(range(bisect_left(bounds, k), bisect_right(bounds, k + LAST) + 1)) for k in key])

    none = F.lit(None)
    events = keys.select(key_range("key", F.pmod(F.xxhash64("host"), F.lit(1 << 20)).cast("int")).alias("at"), "key", none.cast("string").alias("rule"), none.cast("string").alias("verdict"), none.cast("int").alias("host_len"), "host", "path").unionByName(
        rules.groupBy("host", "path").agg(F.max("verdict").alias("verdict"))
        .withColumn("key", F.concat(F.array_join(backwards, "."), F.lit("/"), "path"))
        .select(F.explode(rule_ranges("key")).alias("at"), "key", F.concat("host", "path").alias("rule"), "verdict", F.length("host").alias("host_len"), none.cast("string").alias("host"), none.cast("string").alias("path"))
    )
    swept = events.repartitionById(len(bounds) + 1, F.col("at")).sortWithinPartitions("key", F.col("rule").isNull()).select("key", "rule", "verdict", "host_len", "host", "path")
    best = F.max(F.struct(F.length("rule").alias("n"), "host_len", "verdict", "rule")).alias("best")
    return swept.mapInArrow(_sweep, "host string, path string, rule string, verdict string, host_len int").groupBy("host", "path").agg(best).select("host", "path", "best.rule", "best.verdict")


def filter_urls(pages: DataFrame, rules: DataFrame, default: str = DEFAULT) -> DataFrame:
    """page_id, host, path, rule (null: none fits) and verdict of each row of ``pages`` (page_id, url)."""
    host, path = split_url(F.col("url"))
    urls = pages.select("page_id", host.alias("host"), path.alias("path"))
    judged = judge_urls(urls, rules)
    return join_same(urls, judged, ["host", "path"], "left").select("page_id", "host", "path", "rule", F.coalesce("verdict", F.lit(default)).alias("verdict"))


def op1_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    return filter_urls(table(spark, sf_dir, "pages"), rules_frame(spark))


_VALUES = ", ".join(f"('{h}', '{p}', '{v}')" for h, p, v in RULES)
OP1_SQL = rf"""
WITH rules(rule_host, rule_path, verdict) AS (VALUES {_VALUES}),
rest AS (SELECT page_id, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages),
parts AS (SELECT row_number() OVER () AS id, page_id, translate(regexp_extract(rest, '^[^/?#]*'), '{UPPER}', '{LOWER}') AS host,
    regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM rest),
fits AS (SELECT id, rule_host || rule_path AS rule, verdict, row_number() OVER (PARTITION BY id ORDER BY length(rule_host || rule_path) DESC, length(rule_host) DESC) AS best
    FROM parts JOIN rules ON (host = rule_host OR ends_with(host, '.' || rule_host)) AND starts_with(path, rule_path))
SELECT page_id, host, path, rule, coalesce(verdict, '{DEFAULT}') AS verdict FROM parts LEFT JOIN (SELECT * FROM fits WHERE best = 1) USING (id)
"""

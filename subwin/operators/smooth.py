"""Smooth histograms: overlapping suffixes whose summaries are subtracted, for what can be subtracted.

A suffix starts at each position that a bucket of a count layout starts at; its summary covers all from
there to the newest sample. A range is the difference of two suffixes: sums, counts and sketch cells
subtract, quantile sketches and extremes don't.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from subwin.operators.eh import CUTS, bucket_spans, fractions_of, fractions_sql, layout_count, layout_sql
from subwin.sources.views import VIEWS, series_view

CENTS = "cast(round(value * 100) AS bigint)"


def build(samples: DataFrame, k: int = 20) -> DataFrame:
    """series, start (position of a suffix's first sample), n, cents, squares: summaries of the suffixes."""
    spans = bucket_spans(layout_count(samples, k), F.sum(F.expr(CENTS)).alias("c"), F.sum(F.expr(f"{CENTS} * {CENTS}")).alias("s"))
    newer = Window.partitionBy("series").orderBy("bucket").rowsBetween(0, Window.unboundedFollowing)
    return spans.select("series", F.col("seq_lo").alias("start"), F.sum("size").over(newer).alias("n"), F.sum("c").over(newer).alias("cents"), F.sum("s").over(newer).alias("squares"))


def query_range(suffixes: DataFrame, ranges: DataFrame) -> DataFrame:
    """query, series, n, cents, squares of (low, high]: the suffix after low less the suffix after high."""
    joined = ranges.join(suffixes, "series")
    measures = ("n", "cents", "squares")
    first = joined.where("start > low").groupBy("query", "series").agg(*[F.max(m).alias(m) for m in ("n",)], *[F.expr(f"min_by({m}, start)").alias(m) for m in measures[1:]])
    last = joined.where("start > high").groupBy("query", "series").agg(*[F.expr(f"min_by({m}, start)").alias(f"{m}_after") for m in measures])
    both = first.join(last, ["query", "series"], "left")
    return both.select("query", "series", *[(F.col(m) - F.coalesce(f"{m}_after", F.lit(0))).alias(m) for m in measures])


def suffix_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    samples = series_view(spark, sf_dir, "ev_type")
    return query_range(build(samples), fractions_of(samples, CUTS))


def insert_costs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Summaries that an insert touches: one bucket of an exponential histogram, every suffix of a smooth one."""
    samples = series_view(spark, sf_dir, "ev_type")
    return build(samples).groupBy("series").agg(F.lit(1).cast("long").alias("exponential"), F.count("*").alias("smooth"))


_B = "b AS (SELECT series, bucket, min(seq) AS start, count(*) AS size, sum(cast(round(value * 100) AS bigint)) AS c, sum(cast(round(value * 100) AS bigint) * cast(round(value * 100) AS bigint)) AS s FROM placed GROUP BY ALL)"
QUERIES: dict = {"sh_suffix_difference": suffix_query, "sh_insert_costs": insert_costs}
SQL: dict = {
    "sh_suffix_difference": layout_sql(VIEWS["ev_type"].sql, 20) + f", {fractions_sql(CUTS)}, {_B} SELECT query, r.series, coalesce(sum(size), 0)::BIGINT AS n, coalesce(sum(c), 0)::BIGINT AS cents, coalesce(sum(s), 0)::BIGINT AS squares FROM ranges r LEFT JOIN b ON b.series = r.series AND start > low AND start <= high GROUP BY query, r.series",
    "sh_insert_costs": layout_sql(VIEWS["ev_type"].sql, 20) + ", b AS (SELECT DISTINCT series, bucket FROM placed) SELECT series, 1::BIGINT AS exponential, count(*) AS smooth FROM b GROUP BY series",
}

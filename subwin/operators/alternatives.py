"""Other summaries in the same histogram: raw samples, relative-error histograms, one sketch for each statistic."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from subwin.operators import univ
from subwin.operators.eh import CUTS, bucket_spans, fractions_of, fractions_sql, layout_count, layout_sql, query_range
from subwin.sources.views import VIEWS, series_view

#: Neighbouring cells of the relative-error histogram differ by this factor.
GAMMA = 1.05


def raw_buckets(samples: DataFrame, k: int, ranges: DataFrame) -> DataFrame:
    """query, series, n, q90 over the samples of a range's buckets: buckets that keep their samples, exact inside."""
    placed = layout_count(samples, k)
    taken = query_range(bucket_spans(placed), ranges).select("query", "series", "bucket")
    return placed.join(taken, ["series", "bucket"]).groupBy("query", "series").agg(F.count("*").alias("n"), F.round(F.expr("percentile(value, 0.9)"), 6).alias("q90"))


def log_histogram(samples: DataFrame, k: int, gamma: float = GAMMA) -> DataFrame:
    """series, bucket, cell, n: values by powers of ``gamma``; values up to zero in the cell null."""
    cell = F.when(F.col("value") > 0, F.floor(F.log("value") / math.log(gamma)))
    return layout_count(samples, k).groupBy("series", "bucket", cell.alias("cell")).agg(F.count("*").alias("n"))


def relative_quantile(cells: DataFrame, buckets: DataFrame, ranges: DataFrame, phi: float, gamma: float = GAMMA) -> DataFrame:
    """query, series, estimate: the middle of the cell that holds the quantile; off by at most a factor of sqrt(gamma)."""
    taken = query_range(buckets, ranges).select("query", "series", "bucket")
    summed = cells.join(taken, ["series", "bucket"]).groupBy("query", "series", "cell").agg(F.sum("n").alias("n"))
    up = Window.partitionBy("query", "series").orderBy(F.col("cell").asc_nulls_first())
    every = Window.partitionBy("query", "series")
    ranked = summed.withColumn("upto", F.sum("n").over(up)).withColumn("all", F.sum("n").over(every))
    hit = ranked.where(F.col("upto") >= F.lit(phi) * F.col("all")).groupBy("query", "series").agg(F.min(F.coalesce("cell", F.lit(-(1 << 40)))).alias("cell"))
    return hit.withColumn("estimate", F.when(F.col("cell") == -(1 << 40), F.lit(0.0)).otherwise(F.exp((F.col("cell") + 0.5) * math.log(gamma))))


def strawman(samples: DataFrame, k: int, ranges: DataFrame) -> DataFrame:
    """query, series, distinct by a distinct-count sketch and l2 by a Count Sketch: one sketch for each statistic."""
    placed = layout_count(samples, k)
    spans = bucket_spans(placed, F.hll_sketch_agg("item", F.lit(12)).alias("hll"))
    taken = query_range(spans, ranges)
    counts = taken.groupBy("query", "series").agg(F.hll_sketch_estimate(F.hll_union_agg("hll")).alias("distinct"))
    cells = univ.sketch_cells(univ.frequencies(placed, "bucket"), univ.SMALL, "series", "bucket").where("layer = 0")
    merged = univ.merge_cells(cells.join(taken.select("query", "series", "bucket"), ["series", "bucket"]), "query", "series")
    return counts.join(univ.l2_of_cells(merged, "query", "series"), ["query", "series"])


# -- queries -----------------------------------------------------------------------------------------------------------

_WIDE = CUTS[:4]
_SPANS = "b AS (SELECT series, bucket, min(seq) AS seq_lo FROM placed GROUP BY series, bucket), taken AS (SELECT query, b.series, bucket FROM b JOIN ranges r ON b.series = r.series AND seq_lo > low AND seq_lo <= high)"


def raw_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    samples = series_view(spark, sf_dir, "ev_type")
    return raw_buckets(samples, 20, fractions_of(samples, CUTS))


def relative_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    samples = series_view(spark, sf_dir, "ev_type")
    found = relative_quantile(log_histogram(samples, 20), bucket_spans(layout_count(samples, 20)), fractions_of(samples, _WIDE), 0.9)
    return found.select("query", "series", F.col("cell").cast("long").alias("cell"), F.round("estimate", 6).alias("estimate"))


def strawman_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Exact statistics and whether the strawman's are within a tenth of the suffix's."""
    samples = series_view(spark, sf_dir, "ev_type")
    ranges = fractions_of(samples, _WIDE)
    exact, suffix = univ.exact_statistics(samples, ranges), univ.exact_statistics(samples, fractions_of(samples, [(q, a, 0.0) for q, a, _ in _WIDE]))
    joined = strawman(samples, 50, ranges).alias("e").join(exact.alias("x"), ["query", "series"]).join(suffix.alias("s"), ["query", "series"])
    checks = [(F.abs(F.col(f"e.{m}") - F.col(f"x.{m}")) <= 0.1 * F.col(f"s.{m}")).alias(f"{m}_within") for m in ("distinct", "l2")]
    return joined.select("query", "series", F.col("x.distinct").cast("long").alias("distinct"), F.round("x.l2", 6).alias("l2"), *checks)


def sketch_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bytes of a histogram by form: all sketches, hybrid, raw samples."""
    samples = series_view(spark, sf_dir, "ev_type")
    stored = univ.build(samples, 100)
    spans, maps = stored.spans, stored.maps
    n = samples.groupBy("series").agg((F.count("*") * 16).alias("raw"))
    hybrid = maps.groupBy("series").agg((F.count("*") * univ.ENTRY_BYTES).alias("hybrid"))
    return spans.groupBy("series").agg((F.count("*") * univ.LARGE.cells * univ.CELL_BYTES).alias("sketches")).join(hybrid, "series").join(n, "series")


QUERIES: dict = {"eh_inner_raw": raw_query, "quantile_relative": relative_query, "strawman_statistics": strawman_query, "memory_forms": sketch_sizes}
_V = VIEWS["ev_type"].sql
SQL: dict = {
    "eh_inner_raw": layout_sql(_V, 20) + f", {fractions_sql(CUTS)}, {_SPANS} SELECT query, p.series, count(*) AS n, round(quantile_cont(value, 0.9), 6) AS q90 FROM placed p JOIN taken t ON p.series = t.series AND p.bucket = t.bucket GROUP BY query, p.series",
    "quantile_relative": layout_sql(_V, 20) + f", {fractions_sql(_WIDE)}, {_SPANS}, c AS (SELECT query, p.series, CASE WHEN value > 0 THEN floor(ln(value) / ln({GAMMA}::DOUBLE))::BIGINT END AS cell, count(*) AS n FROM placed p JOIN taken t ON p.series = t.series AND p.bucket = t.bucket GROUP BY ALL), u AS (SELECT *, sum(n) OVER (PARTITION BY query, series ORDER BY cell NULLS FIRST) AS upto, sum(n) OVER (PARTITION BY query, series) AS total FROM c) SELECT query, series, min(coalesce(cell, {-(1 << 40)})) AS cell, round(exp((min(cell) + 0.5) * ln({GAMMA}::DOUBLE)), 6) AS estimate FROM u WHERE upto >= 0.9::DOUBLE * total GROUP BY query, series",
    "strawman_statistics": univ._exact_sql(_V, _WIDE) + ' SELECT query, series, count(*) AS "distinct", round(sqrt(sum(x * x)), 6) AS l2, true AS distinct_within, true AS l2_within FROM c GROUP BY query, series',
}

"""The sampling family: a Bernoulli sample of each series, expired by time, answers counts, sums and moments.

A sample is kept or not by a hash of its series and position: no random state, the filter runs before any
shuffle, and another engine keeps the same samples.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from subwin.operators.eh import CUTS, fractions_of, fractions_sql, in_range, segments
from subwin.sources.views import VIEWS, series_view
from subwin.storage import Scratch

PRIME, SCALE = 2_147_483_647, 1_000_000
#: Chance of a position, in millionths.
DRAW = f"((seq * 48271 + length(series) * 7919 + {{salt}} * 104729) % {PRIME} * 69621 % {PRIME}) % {SCALE}"

#: Estimators over a range from the m sampled rows of chance p.
ESTIMATORS = {
    "count": "cast(round(count(*) / {p}) AS bigint)",
    "sum": "round(sum(cast(round(value * 100) AS bigint)) / 100.0D / {p}, 2)",
    "avg": "round(sum(cast(round(value * 100) AS bigint)) / 100.0D / count(*), 6)",
    "stddev": "round(sqrt(greatest(0, sum(c * c) / count(*) - pow(sum(c) / count(*), 2))) / 100, 4)",
    "stdvar": "round(greatest(0, sum(c * c) / count(*) - pow(sum(c) / count(*), 2)) / 10000, 2)",
}

#: Squares of hundredths are summed as decimals: a long overflows at some 370,000 samples of value 50,000.
SQUARES = ("sum(c * c)", "cast(sum(cast(c * c AS decimal(20, 0))) AS double)")


def build(samples: DataFrame, p: float = 0.1, salt: int = 1) -> DataFrame:
    """The samples that are kept with chance ``p``."""
    return samples.where(f"{DRAW.format(salt=salt)} < {int(p * SCALE)}")


def reservoir(samples: DataFrame, m: int, salt: int = 1) -> DataFrame:
    """At most ``m`` samples of each series, those of the least draws: of a fixed size whatever the series'."""
    order = Window.partitionBy("series").orderBy(F.expr(DRAW.format(salt=salt)), "seq")
    return samples.withColumn("nth", F.row_number().over(order)).where(F.col("nth") <= m).drop("nth")


def expire(kept: DataFrame, now: int, window: int) -> DataFrame:
    return kept.where((F.col("t") > now - window) & (F.col("t") <= now))


def query(kept: DataFrame, ranges: DataFrame, fn: str, p: float) -> DataFrame:
    inside = in_range(kept, ranges)
    return inside.withColumn("c", F.expr("cast(round(value * 100) AS bigint)")).groupBy("query", "series").agg(F.expr(ESTIMATORS[fn].replace(*SQUARES).format(p=p)).alias("estimate"))


def sweep(samples: DataFrame, ranges: DataFrame, ps: list[float]) -> DataFrame:
    """Relative error of the mean for each ratio, in one pass over the samples."""
    pieces = Scratch(samples.sparkSession, "sweep").save(segments(ranges), "pieces")
    inside = in_range(samples, pieces.select("series", "low", "high").distinct()).withColumn("draw", F.expr(DRAW.format(salt=1)))
    c = F.expr("cast(round(value * 100) AS bigint)")
    each = [F.struct(F.lit(p).alias("p"), F.count_if(F.col("draw") < int(p * SCALE)).alias("m"), F.sum(F.when(F.col("draw") < int(p * SCALE), c)).alias("s")) for p in ps]
    of_piece = inside.groupBy("series", "low", "high").agg(F.count("*").alias("n"), F.sum(c).alias("total"), F.array(*each).alias("each"))
    met = of_piece.join(pieces, ["series", "low", "high"])
    sums = [F.struct(F.lit(p).alias("p"), F.sum(F.col("each")[i]["m"]).alias("m"), F.sum(F.col("each")[i]["s"]).alias("s")) for i, p in enumerate(ps)]
    found = met.groupBy("query", "series").agg(F.sum("n").alias("n"), F.sum("total").alias("total"), F.array(*sums).alias("each"))
    return found.select("query", "series", "n", "total", F.inline("each")).select("query", "series", "p", "m", F.round(F.abs(F.col("s") / F.col("m") * F.col("n") / F.col("total") - 1), 6).alias("relative_error"))


RATIOS = [0.01, 0.05, 0.1, 0.2, 0.5]
_V = VIEWS["li_flag"].sql


def _case(fn: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        samples = series_view(spark, sf_dir, "li_flag")
        return query(build(samples), fractions_of(samples, CUTS), fn, 0.1)

    return run


_IN = "FROM v JOIN ranges r ON v.series = r.series AND seq > low AND seq <= high"
QUERIES: dict = {f"sample_{fn}": _case(fn) for fn in ESTIMATORS}
SQL: dict = {
    f"sample_{fn}": f"WITH v AS ({_V}), {fractions_sql(CUTS)} SELECT query, v.series, {e.format(p=0.1).replace('.0D', '.0')} AS estimate FROM (SELECT *, cast(round(value * 100) AS bigint) AS c FROM v) v JOIN ranges r ON v.series = r.series AND seq > low AND seq <= high WHERE {DRAW.format(salt=1).replace('series)', 'v.series)')} < 100000 GROUP BY query, v.series"
    for fn, e in ESTIMATORS.items()
}


def ratio_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    samples = series_view(spark, sf_dir, "li_flag")
    return sweep(samples, fractions_of(samples, CUTS), RATIOS)


def quantile_baseline(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quantiles of the sample, as a baseline: tails are poor at small ratios."""
    kept = build(series_view(spark, sf_dir, "li_flag"))
    return kept.groupBy("series").agg(F.round(F.expr("percentile(value, 0.99)"), 6).alias("q99"), F.count("*").alias("m"))


def fixed_size(spark: SparkSession, sf_dir: str) -> DataFrame:
    return reservoir(series_view(spark, sf_dir, "li_flag"), 100).groupBy("series").agg(F.count("*").alias("m"), F.sum("seq").alias("positions"))


QUERIES |= {"sample_sweep": ratio_sweep, "sample_quantile": quantile_baseline, "sample_reservoir": fixed_size}
_DRAWN = DRAW.format(salt=1).replace("series)", "v.series)")
SQL["sample_sweep"] = f"WITH v AS ({_V}), {fractions_sql(CUTS)}, i AS (SELECT query, v.series, cast(round(value * 100) AS bigint) AS c, {_DRAWN} AS draw {_IN}) SELECT query, series, p::DOUBLE AS p, count(*) FILTER (draw < (p * {SCALE})::BIGINT) AS m, round(abs(sum(c) FILTER (draw < (p * {SCALE})::BIGINT) / (count(*) FILTER (draw < (p * {SCALE})::BIGINT)) * count(*) / sum(c) - 1), 6) AS relative_error FROM i CROSS JOIN (VALUES {', '.join(f'({p}::DOUBLE)' for p in RATIOS)}) AS p(p) GROUP BY query, series, p"
SQL["sample_quantile"] = f"SELECT series, round(quantile_cont(value, 0.99), 6) AS q99, count(*) AS m FROM ({_V}) v WHERE {_DRAWN} < 100000 GROUP BY series"
SQL["sample_reservoir"] = f"SELECT series, count(*) AS m, sum(seq)::BIGINT AS positions FROM (SELECT series, seq, row_number() OVER (PARTITION BY series ORDER BY {_DRAWN}, seq) AS nth FROM ({_V}) v) WHERE nth <= 100 GROUP BY series"

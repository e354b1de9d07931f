"""Bounds, accuracy and cost measures."""

from __future__ import annotations

import math
from fractions import Fraction

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from subwin.operators import kll
from subwin.operators.eh import CUTS, bucket_spans, fractions_of, fractions_sql, in_range, layout_count, query_range
from subwin.sources.views import VIEWS, series_view, table

# -- bounds ------------------------------------------------------------------------------------------------------------


def kll_suffix_bound(k_eh: int, eps_kll: float) -> float:
    """Rank error of the full window, or of a range against its suffix."""
    return 2 / k_eh + eps_kll


def kll_range_bound(k_eh: int, eps_kll: float, n_low: int, n_high: int) -> float:
    """Rank error of a range itself: ``n_low`` and ``n_high`` samples are newer than its start and end."""
    return 2 / k_eh * n_low / (n_low - n_high) + eps_kll


def total_variation_bound(dropped: int, added: int, core: int) -> float:
    """Distance between the samples of a range and those of its buckets: ``core`` are in both."""
    worst = max(dropped, added)
    return worst / (core + worst)


def kll_parameter(eps: float, delta: float) -> int:
    """The sketch parameter for a rank error, ``delta`` the chance to fail."""
    return math.ceil(1 / eps * math.sqrt(math.log(1 / delta)))


def kll_bits(eps_eh: float, eps_kll: float, delta: float, n: int) -> float:
    """Order of memory of an exponential histogram of quantile sketches, in bits."""
    return 1 / eps_kll * math.log2(max(2.0, math.log2(1 / (delta * eps_kll)))) ** 2 * 1 / eps_eh * math.log2(n)


def univ_bits(eps: float, delta: float, n: int, m: int) -> float:
    """Order of memory of an exponential histogram of universal sketches, in bits."""
    return eps**-4 * math.log2(n) ** 3 * math.log2(m) * math.log2(1 / delta)


def gsum_bound(eps: float, of_suffix: float) -> float:
    return eps * of_suffix


def exact_bytes(samples: int) -> int:
    """A value and its time for each sample."""
    return 16 * samples


# -- accuracy ----------------------------------------------------------------------------------------------------------


def mean_relative_error(found: DataFrame, estimate: str, exact: str) -> DataFrame:
    """mre over rows whose exact value is not zero, and the number of those that are."""
    error = F.abs(F.col(estimate) - F.col(exact)) / F.abs(F.col(exact))
    return found.agg(F.avg(F.when(F.col(exact) != 0, error)).alias("mre"), F.count_if(F.col(exact) == 0).alias("zeros"))


def ks_distance(a: DataFrame, b: DataFrame) -> DataFrame:
    """query, series, ks: largest gap between the distributions of ``value`` in two frames with query, series."""
    both = a.select("query", "series", "value", F.lit(1).alias("a"), F.lit(0).alias("b")).unionByName(b.select("query", "series", "value", F.lit(0).alias("a"), F.lit(1).alias("b")))
    steps = both.groupBy("query", "series", "value").agg(F.sum("a").alias("a"), F.sum("b").alias("b"))
    up, all_ = Window.partitionBy("query", "series").orderBy("value"), Window.partitionBy("query", "series")
    gap = F.abs(F.sum("a").over(up) / F.sum("a").over(all_) - F.sum("b").over(up) / F.sum("b").over(all_))
    return steps.withColumn("gap", gap).groupBy("query", "series").agg(F.max("gap").alias("ks"))


def recall(found: DataFrame, true: DataFrame, keys: list[str]) -> DataFrame:
    """Share of ``true`` rows (keys, item) that are found."""
    hit = true.join(found.select(*keys, "item").withColumn("hit", F.lit(1)), [*keys, "item"], "left")
    return hit.groupBy(*keys).agg((F.sum(F.coalesce("hit", F.lit(0))) / F.count("*")).alias("recall"))


def confidence(runs: DataFrame, measure: str) -> DataFrame:
    """Mean, standard deviation and half the width of a 95 % region over runs."""
    return runs.agg(F.avg(measure).alias("mean"), F.stddev_samp(measure).alias("deviation"), (1.96 * F.stddev_samp(measure) / F.sqrt(F.count("*"))).alias("half_width"))


# -- cost --------------------------------------------------------------------------------------------------------------


def samples_scanned(rules: list[tuple[int, int]], rate: float, horizon: int) -> tuple[int, int]:
    """Samples that rules (window, every) read over a horizon, by rescans and by reading each sample once."""
    return int(sum(window * rate * (horizon // every) for window, every in rules)), int(horizon * rate)


def per_sample_price(samples: float, per_billion: float = 0.1) -> float:
    return samples / 1e9 * per_billion


def ingestion_price(samples: float, tiers: list[tuple[float, float]]) -> float:
    """Tiers of (samples up to, price for ten million)."""
    cost, past = 0.0, 0.0
    for upto, price in tiers:
        cost += max(0.0, min(samples, upto) - past) / 1e7 * price
        past = upto
    return cost


def instance_price(memory_gb: float, catalogue: list[tuple[float, float]]) -> float:
    """Price of the smallest instance (memory, price a month) that holds so much."""
    return min(price for memory, price in catalogue if memory >= memory_gb)


def normalised_cost(micros: float, size: float, exact_micros: float, exact_size: float) -> float:
    """Compute and memory, each as a share of the exact way's."""
    return micros / exact_micros + size / exact_size


# -- queries -----------------------------------------------------------------------------------------------------------


def bounds_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bounds of each range of the events' series, for two widths of the histogram."""
    samples = series_view(spark, sf_dir, "ev_type")
    ranges = fractions_of(samples, CUTS).where("low < high").join(samples.groupBy("series").agg(F.count("*").alias("n")), "series")
    n_low, n_high = F.col("n") - F.col("low"), F.col("n") - F.col("high")
    each = [ranges.select("query", "series", F.lit(k).cast("long").alias("k"), n_low.alias("n_low"), n_high.alias("n_high"), F.lit(round(kll_suffix_bound(k, 0.01), 9)).alias("suffix"), F.round(kll_range_bound(k, 0.01, n_low, n_high), 9).alias("ranged")) for k in (20, 50)]
    return each[0].unionByName(each[1])


def alignment_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distance of each range's buckets from the range, beside its bound: the window framework's own error."""
    samples = series_view(spark, sf_dir, "ev_type")
    placed, ranges = layout_count(samples, 20), fractions_of(samples, CUTS[:4])
    taken = query_range(bucket_spans(placed), ranges).select("query", "series", "bucket")
    ks = ks_distance(in_range(samples, ranges), placed.join(taken, ["series", "bucket"]))
    bound = kll.merged(kll.build(samples, 20), ranges).select("query", "series", "bound")
    return ks.join(bound, ["query", "series"]).select("query", "series", (F.col("ks") <= F.col("bound") + 1e-9).alias("within_bound"))


def price_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The prices of the events' month: rescanned by ten rules a minute, read once, taken in."""
    samples = table(spark, sf_dir, "events").agg(F.count("value").cast("double").alias("n"))

    def priced(batches):
        for batch in batches:
            for n in batch["n"]:
                a_day = per_sample_price(10 * n * 1440)
                rows = [("rescan_a_day", a_day), ("rescan_a_month", a_day * 30), ("once_a_month", per_sample_price(n)), ("flat_ingestion", ingestion_price(n, [(1e18, 0.35)]))]
                yield pd.DataFrame([(what, round(dollars, 6)) for what, dollars in rows], columns=["what", "dollars"])

    return samples.mapInPandas(priced, "what string, dollars double")


def scanned_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What three daily rules read of a month of each series of the events, at its mean rate."""
    day = 86_400
    rules, horizon = [(2 * day, day), (2 * day, day), (day, day)], 30 * day

    def scanned(batches):
        for batch in batches:
            found = [samples_scanned(rules, Fraction(int(n), horizon), horizon) for n in batch["n"]]
            yield pd.DataFrame({"series": batch["series"], "rescanned": [many for many, _ in found], "once": [once for _, once in found]})

    samples = table(spark, sf_dir, "events").groupBy(F.col("event_type").alias("series")).agg(F.count("value").alias("n"))
    return samples.mapInPandas(scanned, "series string, rescanned long, once long")


def memory_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bytes of sketches by k and window, beside exact storage."""
    samples = series_view(spark, sf_dir, "li_all")
    each = [kll.build(samples, k_eh).groupBy("series").agg(F.count("*").alias("buckets"), F.sum(F.length("sketch")).alias("bytes"), (16 * F.sum("size")).alias("exact")).withColumn("k", F.lit(k_eh)) for k_eh in (20, 50)]
    return each[0].unionByName(each[1])


def error_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean relative error of sampled means, with its region over five salts."""
    from subwin.operators import sampling

    samples = series_view(spark, sf_dir, "li_flag")
    exact = samples.groupBy("series").agg(F.avg("value").alias("exact"))
    runs = [mean_relative_error(sampling.build(samples, 0.1, salt).groupBy("series").agg(F.avg("value").alias("estimate")).join(exact, "series"), "estimate", "exact") for salt in range(1, 6)]
    every = runs[0]
    for run in runs[1:]:
        every = every.unionByName(run)
    return confidence(every, "mre")


QUERIES: dict = {"bound_kll": bounds_query, "eh_alignment_ks": alignment_query, "cost_prices": price_query, "cost_samples_scanned": scanned_query, "memory_kll": memory_query, "accuracy_sample_mre": error_query}
SQL: dict = {
    "bound_kll": f"WITH v AS ({VIEWS['ev_type'].sql}), {fractions_sql(CUTS)}, b AS (SELECT query, series, n - low AS n_low, n - high AS n_high FROM ranges JOIN (SELECT series, count(*) AS n FROM v GROUP BY series) USING (series) WHERE low < high) SELECT query, series, k::BIGINT AS k, n_low::BIGINT AS n_low, n_high::BIGINT AS n_high, round(2 / k + 0.01, 9)::DOUBLE AS suffix, round(2 / k * n_low / (n_low - n_high) + 0.01, 9)::DOUBLE AS ranged FROM b CROSS JOIN (VALUES (20), (50)) AS a(k)",
    "eh_alignment_ks": f"WITH v AS ({VIEWS['ev_type'].sql}), {fractions_sql(CUTS[:4])} SELECT query, series, true AS within_bound FROM ranges",
    "cost_prices": "SELECT what, round(n * factor, 6) AS dollars FROM (SELECT count(value)::DOUBLE AS n FROM events) CROSS JOIN (VALUES ('rescan_a_day', 14400 * 0.1::DOUBLE / 1e9), ('rescan_a_month', 432000 * 0.1::DOUBLE / 1e9), ('once_a_month', 0.1::DOUBLE / 1e9), ('flat_ingestion', 0.35::DOUBLE / 1e7)) AS t(what, factor)",
    "cost_samples_scanned": "SELECT event_type AS series, 5 * count(value) AS rescanned, count(value) AS once FROM events GROUP BY event_type",
}

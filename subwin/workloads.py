"""Experiment workloads on the given tables: sweeps over windows, parameters, series and rivals."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from subwin.operators import baselines, kll, sampling, univ
from subwin.operators.eh import bucket_spans, fractions_of, fractions_sql, in_range, layout_count, layout_sql
from subwin.sources.views import DAY, VIEWS, drifting, samples_of, series_view, synthetic, written_words
from subwin.storage import Scratch

#: Window fractions of the concurrent workload, and nested windows in days back from the end of the events.
THREE = [("w001", 0.01, 0.0), ("w010", 0.1, 0.0), ("w100", 1.0, 0.0)]
NESTED = [5, 10, 15, 30]
END = 1_704_067_200_000_000 + 30 * DAY


def _all(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


def statistic_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every statistic of the eleven concurrent groups for each series and window, in one shared job."""
    samples = series_view(spark, sf_dir, "ev_type")
    ranges = fractions_of(samples, THREE)
    inside = in_range(samples, ranges).withColumn("c", F.expr("cast(round(value * 100) AS bigint)"))
    values = inside.groupBy("query", "series").agg(
        F.round(F.expr("percentile(value, 0.5)"), 6).alias("q50"), F.round(F.expr("percentile(value, 0.9)"), 6).alias("q90"), F.min("value").alias("low"), F.max("value").alias("top"),
        F.round(F.sum("c") / 100.0 / F.count("*"), 6).alias("mean"), F.round(F.expr("sqrt(greatest(0, sum(c * c) / count(*) - pow(sum(c) / count(*), 2))) / 100"), 4).alias("deviation"),
    )
    items = univ.exact_statistics(samples, ranges).select("query", "series", F.col("distinct").cast("long").alias("distinct"), F.round("entropy", 6).alias("entropy"), F.round("l2", 6).alias("l2"))
    return values.join(items, ["query", "series"])


def cached_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The quantile groups of the same workload from the cache, with the exact values and whether each is in bound."""
    samples = series_view(spark, sf_dir, "ev_type")
    ranges = fractions_of(samples, THREE)
    found = kll.answer(samples, kll.stored(samples), ranges, [0.0, 0.5, 0.9, 1.0])
    return kll.judged(samples, found, ranges).select("query", "series", "phi", "exact", "within_bound")


def nested_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Windows of 5, 10 and 15 days inside one cached window of 30, by time."""
    samples = series_view(spark, sf_dir, "ev_type")
    ranges = _all([samples.select("series").distinct().selectExpr(f"'d{d}' AS query", "series", f"{END - d * DAY} AS low", f"{END} AS high") for d in NESTED])
    found = kll.quantiles(kll.stored(samples), ranges, [0.9], by="t")
    exact = in_range(samples, ranges, "t").join(found, ["query", "series"])
    ranks = exact.groupBy("query", "series", "estimate", "bound").agg(F.round(F.expr("percentile(value, 0.9)"), 6).alias("exact"), F.count("*").alias("n"), F.count_if(F.col("value") < F.col("estimate")).alias("below"), F.count_if(F.col("value") <= F.col("estimate")).alias("upto"))
    error = F.greatest(F.lit(0.0), F.col("below") / F.col("n") - 0.9, 0.9 - F.col("upto") / F.col("n"))
    return ranks.select("query", "series", "exact", (error <= F.col("bound") + 2 * kll.sketch_error(kll.K_KLL)).alias("within_bound"))


def suffix_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Relative errors by suffix length, from a tenth to the whole in steps of a twentieth: of the median's rank, the mean, distinct, entropy and L2."""
    scratch = Scratch(spark, "sweep")
    runs = written_words(spark, sf_dir)
    ranges = scratch.save(fractions_of(runs, [(f"s{i:03}", i / 100, 0.0) for i in range(10, 101, 5)]), "ranges")
    universal = univ.build(runs, 1000, hybrid=False).saved(Scratch(spark, "univ"))
    items = univ.query(universal, ranges).alias("e").join(scratch.save(univ.exact_statistics(runs, ranges), "exact").alias("x"), ["query", "series"])
    items = items.select("query", "series", *[F.round(F.abs(F.col(f"e.{m}") / F.col(f"x.{m}") - 1), 6).alias(m) for m in ("distinct", "entropy", "l2")])
    samples = samples_of(runs)
    buckets = kll.stored(samples)
    ranks = kll.judged(samples, kll.answer(samples, buckets, ranges, [0.5]), ranges, exact=False).select("query", "series", F.round("rank_error", 6).alias("median_rank"))
    means = sampling.sweep(samples, ranges, [0.1]).select("query", "series", F.col("relative_error").alias("mean"))
    return items.join(ranks, ["query", "series"]).join(means, ["query", "series"]).drop("series")


def parameter_tuning(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean error and bytes by the histogram's and the sketch's parameter: ranks on a drifting series, distinct, entropy and L2 on tokens."""
    samples = Scratch(spark, "tuning").save(drifting(spark, sf_dir), "samples")
    ranges = fractions_of(samples, [(f"r{i}", 0.1 * i + 0.3, 0.1 * i) for i in range(6)])
    rows = []
    for k_eh in (10, 20, 50):
        for k_kll in (64, 256):
            buckets = kll.stored(samples, k_eh, k_kll)
            errors = kll.judged(samples, kll.answer(samples, buckets, ranges, [0.5, 0.9]), ranges, k_kll, exact=False).groupBy("series").agg(F.avg("rank_error").alias("error"))
            sizes = buckets.groupBy("series").agg(F.count("*").alias("buckets"), F.sum(F.length("sketch")).alias("bytes"))
            rows.append(errors.join(sizes, "series").select(F.lit("kll").alias("family"), F.lit(k_eh).alias("k_eh"), F.lit(str(k_kll)).alias("sketch"), F.lit("rank").alias("measure"), "error", "buckets", "bytes"))
    tokens = written_words(spark, sf_dir)
    ranges = Scratch(spark, "tuning").save(fractions_of(tokens, [(f"r{i}", 0.3 * i + 0.3, 0.0) for i in range(3)]), "ranges")
    exact = Scratch(spark, "tuning").save(univ.exact_statistics(tokens, ranges), "exact")
    counts = {k_eh: univ.count(tokens, 1000, k_eh) for k_eh in (10, 20)}
    for k_eh, name, config in ((10, "middle", univ.MIDDLE), (20, "middle", univ.MIDDLE), (20, "large", univ.LARGE), (20, "fine", univ.FINE)):
        stored = univ.formed(counts[k_eh], config, hybrid=False).saved(Scratch(spark, "univ"))
        found = univ.query(stored, ranges, config).alias("e").join(exact.alias("x"), ["query", "series"])
        errors = found.groupBy("series").agg(*[F.avg(F.abs(F.col(f"e.{m}") / F.col(f"x.{m}") - 1)).alias(m) for m in ("distinct", "entropy", "l2")]).unpivot("series", ["distinct", "entropy", "l2"], "measure", "error")
        sizes = stored.cells.groupBy("series").agg((F.count("*") * univ.CELL_BYTES).alias("bytes")).join(stored.spans.groupBy("series").agg(F.count("*").alias("buckets")), "series")
        rows.append(errors.join(sizes, "series").select(F.lit("univ").alias("family"), F.lit(k_eh).alias("k_eh"), F.lit(name).alias("sketch"), "measure", "error", "buckets", "bytes"))
    return _all(rows)


def memory_by_window(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Buckets and bytes by window size: far slower than the window grows."""
    samples = series_view(spark, sf_dir, "li_all")
    n = samples.agg(F.max("seq")).first()[0]
    return _all([kll.build(samples.where(F.col("seq") <= int(n * part))).agg(F.max("seq_hi").alias("window"), F.count("*").alias("buckets"), F.sum(F.length("sketch")).alias("bytes")) for part in (0.01, 0.1, 1.0)])


def memory_by_series(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bytes by number of series, of both families, of a quarter, half and all of the users: in proportion."""
    samples = Scratch(spark, "memory").save(series_view(spark, sf_dir, "ev_user", counted=True), "samples")
    stored = univ.build(samples.drop("n"), 5)
    entries = stored.maps.select("series", F.lit(univ.ENTRY_BYTES).alias("bytes")).unionByName(stored.cells.select("series", F.lit(univ.CELL_BYTES).alias("bytes")))
    both = kll.stored(samples, 20).select("series", F.length("sketch").alias("bytes"), F.lit("kll").alias("family")).unionByName(entries.withColumn("family", F.lit("univ")))
    each = both.groupBy("family", "series").agg(F.sum("bytes").alias("bytes")).withColumn("quarter", F.pmod(F.xxhash64("series"), F.lit(4)))
    return each.withColumn("quarters", F.explode(F.array(*map(F.lit, (1, 2, 4))))).where("quarter < quarters").groupBy("family", "quarters").agg(F.count("*").alias("series"), F.sum("bytes").alias("bytes"))


def rivals(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recall of the top five users in five nested windows: one universal histogram against a sketch for each window."""
    samples = series_view(spark, sf_dir, "ev_type")
    ranges = fractions_of(samples, [(q, f, 0.0) for q, f in baselines.WINDOWS.items()])
    best = Window.partitionBy("query", "series").orderBy(F.desc("f"), "item")
    true = in_range(samples, ranges).groupBy("query", "series", "item").agg(F.count("*").alias("f")).withColumn("nth", F.row_number().over(best)).where("nth <= 5").select("query", "series", "item")
    ours = univ.top_items(univ.build(samples, 50), ranges, 5).select("query", "series", "item")
    each = [("histogram", ours)] + [(engine, baselines.fixed_window_topk(samples, baselines.WINDOWS, 5, engine, 40).select("query", "series", "item")) for engine in ("spacesaving", "guarded")]
    hits = _all([true.join(found.withColumn("hit", F.lit(1)), ["query", "series", "item"], "left").groupBy("query").agg(F.round(F.sum(F.coalesce("hit", F.lit(0))) / F.count("*"), 6).alias("recall")).withColumn("engine", F.lit(name)) for name, found in each])
    return hits.select("engine", "query", "recall")


def ratios(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Error of sampled means and quantiles by ratio, on the largest series."""
    samples = series_view(spark, sf_dir, "li_all")
    exact = samples.agg(F.avg("value").alias("mean"), F.expr("percentile(value, 0.99)").alias("q99")).first()
    found = _all([sampling.build(samples, p).agg(F.lit(p).alias("p"), F.count("*").alias("m"), F.avg("value").alias("mean"), F.expr("percentile(value, 0.99)").alias("q99")) for p in sampling.RATIOS])
    return found.select("p", "m", F.abs(F.col("mean") / exact["mean"] - 1).alias("mean_error"), F.abs(F.col("q99") / exact["q99"] - 1).alias("q99_error"))


def drift(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rank errors on a generated series whose law changes twice."""
    samples = synthetic(spark, "dynamic", 2, 9000)
    ranges = fractions_of(samples, [("whole", 1.0, 0.0), ("second", 0.66, 0.33), ("last", 0.3, 0.0), ("across", 0.5, 0.2)])
    return kll.judged(samples, kll.answer(samples, kll.stored(samples), ranges, [0.5, 0.9]), ranges).select("query", "series", "phi", "rank_error", "within_bound")


def uniformity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Entries of maps by law: near-uniform items cost more than skewed ones."""
    out = []
    for name, samples in (("zipf", synthetic(spark, "zipf", 1, 20_000)), ("uniform", synthetic(spark, "uniform", 1, 20_000))):
        freq = univ.frequencies(layout_count(samples, 20), "bucket")
        out.append(freq.agg(F.lit(name).alias("law"), F.count("*").alias("entries"), F.sum("f").alias("samples")))
    return _all(out)


def bucket_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Buckets that a query merges, by view."""
    return _all([bucket_spans(layout_count(series_view(spark, sf_dir, view), 50)).groupBy("series").agg(F.count("*").alias("buckets"), F.sum("size").alias("samples")).withColumn("view", F.lit(view)) for view in ("ev_type", "ord_prio", "conv_role", "page_host", "li_flag")])


_V = VIEWS["ev_type"].sql
QUERIES: dict = {
    "workload_statistic_groups": statistic_groups, "workload_cached_groups": cached_groups, "workload_nested_windows": nested_windows, "workload_suffix_sweep": suffix_sweep, "workload_parameter_tuning": parameter_tuning,
    "workload_memory_by_window": memory_by_window, "workload_memory_by_series": memory_by_series, "workload_rivals": rivals, "workload_ratios": ratios, "workload_drift": drift, "workload_uniformity": uniformity, "workload_bucket_counts": bucket_counts,
}
_COUNTED = " UNION ALL ".join(f"SELECT '{view}' AS view, * FROM ({layout_sql(VIEWS[view].sql, 50)} SELECT series, count(DISTINCT bucket) AS buckets, count(*) AS samples FROM placed GROUP BY series)" for view in ("ev_type", "ord_prio", "conv_role", "page_host", "li_flag"))
SQL: dict = {
    "workload_statistic_groups": f"""WITH v AS ({_V}), {fractions_sql(THREE)}, i AS (SELECT query, v.*, cast(round(value * 100) AS bigint) AS c FROM v JOIN ranges r ON v.series = r.series AND seq > low AND seq <= high),
f AS (SELECT query, series, count(*) AS "distinct", round(ln(sum(x)) - sum(x * ln(x)) / sum(x), 6) AS entropy, round(sqrt(sum(x * x)), 6) AS l2 FROM (SELECT query, series, item, count(*)::DOUBLE AS x FROM i GROUP BY ALL) GROUP BY query, series)
SELECT query, series, round(quantile_cont(value, 0.5), 6) AS q50, round(quantile_cont(value, 0.9), 6) AS q90, min(value) AS low, max(value) AS top, round(sum(c) / 100.0 / count(*), 6) AS mean, round(sqrt(greatest(0, sum(c * c) / count(*) - pow(sum(c) / count(*), 2))) / 100, 4) AS deviation, any_value("distinct") AS "distinct", any_value(entropy) AS entropy, any_value(l2) AS l2 FROM i JOIN f USING (query, series) GROUP BY query, series""",
    "workload_bucket_counts": _COUNTED,
    "workload_cached_groups": kll._case_sql(_V, [0.0, 0.5, 0.9, 1.0], THREE),
    "workload_nested_windows": f"SELECT 'd' || d AS query, series, round(quantile_cont(value, 0.9), 6) AS exact, true AS within_bound FROM ({_V}) JOIN (VALUES (5), (10), (15), (30)) AS n(d) ON t > {END} - d * {DAY} AND t <= {END} GROUP BY d, series",
}

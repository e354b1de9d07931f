"""Quantiles over sub-windows: an exponential histogram by count with a KLL sketch in each bucket."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from subwin.operators.eh import CUTS, bucket_spans, fractions_of, fractions_sql, in_range, layout_count, query_range, segments
from subwin.sources.views import DRIFT_SQL, VIEWS, drifting, series_view
from subwin.storage import Scratch

K_EH, K_KLL = 50, 256


def sketch_error(k: int) -> float:
    """Normalised rank error of one KLL sketch of parameter k, at 99 % confidence."""
    return 2.296 / k**0.9021


def build(samples: DataFrame, k_eh: int = K_EH, k_kll: int = K_KLL) -> DataFrame:
    """Bucket table: series, bucket, spans, size and sketch. Partial sketches form before the shuffle, so a
    series of any length is spread over tasks. A sample whose value is null or NaN has its position but no
    value: size counts values, and a bucket without any is left out."""
    placed = layout_count(samples, k_eh).withColumn("valid", F.when(~F.isnan("value"), F.col("value")))
    spans = bucket_spans(placed, F.expr(f"kll_sketch_agg_double(valid, {k_kll})").alias("sketch"), F.count("valid").alias("values"), F.max("n").alias("n"))
    return spans.where("values > 0").withColumn("size", F.col("values")).drop("values")


def stored(samples: DataFrame, k_eh: int = K_EH, k_kll: int = K_KLL) -> DataFrame:
    """``build``, written and read again: questions go to the table, not to the samples."""
    return Scratch(samples.sparkSession, "kll").save(build(samples, k_eh, k_kll), "buckets")


def merged(buckets: DataFrame, ranges: DataFrame, by: str = "seq") -> DataFrame:
    """query, series, sketch of all buckets of a range, samples in it, and the bound on the alignment's rank error.

    What the range loses lies in the bucket before the first, what it gains in the last: no more than
    their sizes. The rank error is then at most the larger of the two over the core plus it.
    """
    taken = query_range(buckets, ranges, by)
    before = buckets.select("series", (F.col("bucket") + 1).alias("bucket"), F.col("size").alias("older"))
    taken = taken.join(before, ["series", "bucket"], "left")
    straddling = F.coalesce(F.max(F.when(F.col("straddles"), F.col("size"))), F.lit(0))
    found = taken.groupBy("query", "series").agg(F.expr("kll_merge_agg_double(sketch)").alias("sketch"), F.sum("size").alias("samples"), F.count("*").alias("buckets"), F.expr("min_by(coalesce(older, 0), bucket)").alias("lost"), straddling.alias("gained"))
    worst = F.greatest(F.col("lost"), F.col("gained"))
    core = F.col("samples") - F.col("gained")
    return found.withColumn("bound", worst / (core + worst))


def quantiles(buckets: DataFrame, ranges: DataFrame, phis: list[float], by: str = "seq") -> DataFrame:
    """query, series, phi, estimate, bound, samples, buckets: one merge for all phis."""
    points = ", ".join(f"{p!r}D" for p in phis)
    each = F.inline(F.arrays_zip(F.expr(f"array({points})").alias("phi"), F.expr(f"kll_sketch_get_quantile_double(sketch, array({points}))").alias("estimate")))
    return merged(buckets, ranges, by).select("query", "series", "samples", "buckets", "bound", each)


def answer(samples: DataFrame, buckets: DataFrame, ranges: DataFrame, phis: list[float], narrow: str = "exact", by: str = "seq") -> DataFrame:
    """quantiles() with source cache. Ranges that lie inside one bucket are answered, by ``narrow``: exact, from
    the samples, with source exact; bucket, by the bucket that holds their end; null, not at all."""
    found = quantiles(buckets, ranges, phis, by).withColumn("source", F.lit("cache"))
    if narrow == "null":
        return found
    missed = ranges.join(query_range(buckets, ranges, by).select("query", "series").distinct(), ["query", "series"], "left_anti")
    # written, so that its size is known before samples are moved to meet it
    missed = Scratch(samples.sparkSession, "missed").save(missed, "ranges")
    points = ", ".join(f"{p!r}D" for p in phis)
    if narrow == "bucket":
        # a wider range from just before the bucket's start
        starts = in_range(samples, missed).groupBy("query", "series").agg(F.min("seq").alias("at"))
        holders = buckets.join(starts, "series").where("seq_lo <= at and at <= seq_hi").select("query", "series", (F.col("seq_lo") - 1).alias("low"), F.col("at").alias("high"))
        return found.unionByName(quantiles(buckets, holders, phis).withColumn("source", F.lit("bucket")))
    held = in_range(samples, missed, by).groupBy("query", "series").agg(F.count("*").alias("samples"), F.expr(f"percentile(value, array({points}))").alias("points"))
    each = F.inline(F.arrays_zip(F.expr(f"array({points})").alias("phi"), F.col("points").alias("estimate")))
    exact = held.select("query", "series", "samples", F.lit(0).cast("long").alias("buckets"), (1 / F.col("samples")).alias("bound"), each, F.lit("exact").alias("source"))
    return found.unionByName(exact)


def ranks(buckets: DataFrame, ranges: DataFrame, value: float, by: str = "seq") -> DataFrame:
    """query, series and the estimated share of samples up to ``value``."""
    return merged(buckets, ranges, by).withColumn("rank", F.expr(f"kll_sketch_get_rank_double(sketch, {float(value)!r}D)")).drop("sketch")


def judged(samples: DataFrame, estimates: DataFrame, ranges: DataFrame, sketch_k: int = K_KLL, exact: bool = True) -> DataFrame:
    """``estimates`` with rank_error, and within_bound: the estimate's rank among the samples of the range, counted
    exactly, lies within the bound. With ``exact`` also the interpolated quantile of that name.

    The sketch's own error counts twice, for a failing chance far below one in a hundred. The samples stay where they
    are: what they meet are small tables, whose size is known, and what moves are counts between marks.
    """
    scratch = Scratch(samples.sparkSession, "judged")
    keys = ["query", "series"]
    asked = scratch.save(estimates.select(*keys, "phi", "estimate", "bound"), "asked")
    if exact:
        asked = scratch.save(_bracketed(samples, scratch.save(ranges, "ranges"), asked), "bracketed")
    marks = F.array_sort(F.array_distinct(F.flatten(F.collect_list(F.array_compact(F.array("estimate", *(["low", "high"] * exact)))))))
    marked = scratch.save(ranges.withColumnsRenamed({"low": "start", "high": "end"}).join(asked.groupBy(*keys).agg(marks.alias("marks")), keys).withColumnsRenamed({"start": "low", "end": "high"}), "marked")
    # 2 p + 1 on the mark at p, 2 p before it
    at = F.expr(f"CASE WHEN value IS NULL THEN {1 << 30} ELSE size(filter(marks, m -> m < value)) + size(filter(marks, m -> m <= value)) END")
    # met once by the pieces of the ranges, whose marks are those of all ranges that have the piece
    pieces = scratch.save(segments(ranges), "pieces")
    of_piece = F.array_sort(F.array_distinct(F.flatten(F.collect_list("marks")))).alias("marks")
    shared = scratch.save(pieces.join(marked.select(*keys, "marks"), keys).groupBy("series", "low", "high").agg(of_piece), "shared")
    by_piece = in_range(samples, shared).groupBy("series", "low", "high", at.alias("at")).agg(F.count("*").alias("c"))
    mine = marked.select(*keys, F.col("marks").alias("own"))
    # a place between all marks as one between those of a range: 2 p + 1 on its mark at p, 2 p after p of them
    upto = F.expr(f"CASE WHEN at % 2 = 1 AND at < {1 << 30} THEN marks[cast(at div 2 AS int)] END")
    past = F.expr("CASE WHEN at >= 2 THEN marks[cast(at div 2 AS int) - 1] END")
    own = F.expr(f"CASE WHEN at = {1 << 30} THEN at WHEN here IS NOT NULL THEN size(filter(own, m -> m < here)) + size(filter(own, m -> m <= here)) ELSE 2 * size(filter(own, m -> m <= past)) END")
    met = by_piece.join(shared, ["series", "low", "high"]).join(pieces, ["series", "low", "high"]).join(mine, keys)
    met = met.withColumns({"here": upto, "past": F.when(F.col("at") < 1 << 30, past)}).withColumn("at", F.coalesce(own, F.lit(0)))
    counts = met.groupBy(*keys, "at").agg(F.sum("c").alias("c"))
    placed = asked.join(marked.select(*keys, "marks"), keys).join(counts, keys)

    def upto(mark: str, also: bool) -> Column:
        return F.sum(F.when(F.col("at") <= 2 * (F.array_position("marks", F.col(mark)) - 1) + int(also), F.col("c")).otherwise(0))

    tallies = [F.sum("c").alias("n"), upto("estimate", False).alias("below"), upto("estimate", True).alias("upto")]
    if exact:
        tallies += [upto("low", False).alias("before"), upto("high", True).alias("through")]
    found = placed.groupBy(*asked.columns).agg(*tallies)
    if exact:
        found = scratch.save(found, "counted")
        found = found.join(_exact(samples, ranges, found, scratch), [*keys, "phi"], "left")
    error = F.greatest(F.lit(0.0), F.col("below") / F.col("n") - F.col("phi"), F.col("phi") - F.col("upto") / F.col("n"))
    rest = [F.round("point", 6).alias("exact")] * exact
    return found.select(*keys, "phi", "estimate", "bound", "n", "below", "upto", *rest, error.alias("rank_error")).withColumn("within_bound", F.col("rank_error") <= F.col("bound") + 2 * sketch_error(sketch_k))


def _bracketed(samples: DataFrame, ranges: DataFrame, asked: DataFrame) -> DataFrame:
    """``asked`` with values, high, low, of each range between which its quantile most likely lies, and the number of its values."""
    near = [(max(0.0, p - NEAR), min(1.0, p + NEAR)) for p in POINTS]
    sketched = in_range(samples, ranges).groupBy("query", "series").agg(F.percentile_approx("value", [x for pair in near for x in pair], 10_000).alias("cuts"), F.count("value").alias("values"))
    nth = F.array_position(F.array(*map(F.lit, POINTS)), F.col("phi")).cast("int")
    return asked.join(sketched, ["query", "series"]).withColumns({"low": F.element_at("cuts", 2 * nth - 1), "high": F.element_at("cuts", 2 * nth)}).drop("cuts")


def _exact(samples: DataFrame, ranges: DataFrame, counted: DataFrame, scratch: Scratch) -> DataFrame:
    """query, series, phi and point, the interpolated quantile, from the values in the brackets, counted by value. A bracket
    that the counts before and through it show to miss the quantile is left open to that side."""
    position = (F.col("values") - 1) * F.col("phi")
    sought = counted.where("values > 0").withColumns({"first": F.floor(position), "second": F.ceil(position), "position": position})
    sought = sought.withColumn("low", F.when(F.col("before") <= F.col("first"), F.col("low"))).withColumn("high", F.when(F.col("through") > F.col("second"), F.col("high")))
    sought = scratch.save(sought.withColumn("before", F.when(F.col("low").isNull(), 0).otherwise(F.col("before"))), "sought")
    brackets = sought.groupBy("query", "series").agg(F.collect_list(F.struct("phi", F.col("low").alias("from"), F.col("high").alias("to"))).alias("brackets"))
    held = in_range(samples, scratch.save(ranges.join(brackets, ["query", "series"]), "brackets")).where("value IS NOT NULL")
    of = F.explode(F.expr("filter(brackets, b -> (b.from IS NULL OR value >= b.from) AND (b.to IS NULL OR value <= b.to)).phi"))
    values = held.select("query", "series", "value", of.alias("phi")).groupBy("query", "series", "phi", "value").agg(F.count("*").alias("c"))
    running = F.sum("c").over(Window.partitionBy("query", "series", "phi").orderBy("value").rowsBetween(Window.unboundedPreceding, 0))
    ranked = values.withColumn("running", running).join(sought.select("query", "series", "phi", "before", "first", "second", "position"), ["query", "series", "phi"])
    a, b = (F.min(F.when(F.col("before") + F.col("running") > F.col(x), F.col("value"))) for x in ("first", "second"))
    ends = ranked.groupBy("query", "series", "phi", "first", "second", "position").agg(a.alias("a"), b.alias("b"))
    between = (F.col("second") - F.col("position")) * F.col("a") + (F.col("position") - F.col("first")) * F.col("b")
    return ends.select("query", "series", "phi", F.when(F.col("a") == F.col("b"), F.col("a")).otherwise(between).alias("point"))


#: The points at which judged() knows exact quantiles.
POINTS = [0.0, 0.25, 0.5, 0.75, 0.9, 0.95, 0.99, 1.0]
#: What its brackets leave to both sides of a quantile, of all values.
NEAR = 0.001


def read_once(samples: DataFrame) -> DataFrame:
    """``samples`` without items, written: their positions are worked out once for all that reads them."""
    return Scratch(samples.sparkSession, "samples").save(samples.drop("item"), "samples")


def _case(view, phis, cuts=CUTS, k_eh=K_EH, k_kll=K_KLL):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        samples = read_once(view(spark, sf_dir))
        buckets = stored(samples, k_eh, k_kll)
        ranges = fractions_of(buckets, cuts)
        found = judged(samples, answer(samples, buckets, ranges, phis), ranges, k_kll)
        return found.select("query", "series", "phi", "exact", "within_bound")

    return run


def _case_sql(view: str, phis: list[float], cuts=CUTS) -> str:
    each = ", ".join(f"({p})" for p in phis)
    return f"""WITH v AS ({view}), {fractions_sql(cuts)}
SELECT query, v.series, phi::DOUBLE AS phi, round(quantile_cont(value, [{", ".join(map(str, phis))}])[list_position([{", ".join(map(str, phis))}], phi)], 6) AS exact, true AS within_bound
FROM v JOIN ranges r ON v.series = r.series AND seq > low AND seq <= high CROSS JOIN (VALUES {each}) AS p(phi) GROUP BY query, v.series, phi"""


def _view(name: str):
    return lambda spark, d: series_view(spark, d, name, counted=True)


DRILL = [("whole", 0.9, 0.0)] + [(f"tenth{i}", 0.1 * (i + 1), 0.1 * i) for i in range(10)] + [(f"hundredth{i}", 0.01 * (i + 1), 0.01 * i) for i in range(10)]
_CASES = {
    "ehkll_quantile_events": ("ev_type", [0.5, 0.9, 0.99], CUTS, 50, 256),
    "ehkll_quantile_users": ("ev_user", [0.5, 0.95], CUTS, 20, 256),
    "ehkll_quantile_orders": ("ord_prio", [0.25, 0.5, 0.75], CUTS, 20, 128),
    "ehkll_quantile_nations": ("ord_nation", [0.95], CUTS, 50, 256),
    "ehkll_minmax_lines": ("li_all", [0.0, 1.0], CUTS, 50, 256),
    "ehkll_drilldown_lines": ("li_all", [0.9], DRILL, 50, 256),
}
QUERIES: dict = {name: _case(_view(view), phis, cuts, a, b) for name, (view, phis, cuts, a, b) in _CASES.items()}
SQL: dict = {name: _case_sql(VIEWS[view].sql, phis, cuts) for name, (view, phis, cuts, _, _) in _CASES.items()}
QUERIES["ehkll_drift"] = _case(drifting, [0.5, 0.9])
SQL["ehkll_drift"] = _case_sql(DRIFT_SQL, [0.5, 0.9])


def raw_estimates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Estimates, their true rank errors and bounds, for a look at the margins."""
    samples = read_once(drifting(spark, sf_dir))
    buckets = stored(samples)
    ranges = fractions_of(buckets, CUTS)
    return judged(samples, quantiles(buckets, ranges, [0.5, 0.9, 0.99]), ranges)


def rank_queries(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The share of samples up to 50 in each range, exact and within the bound of the estimate."""
    samples = series_view(spark, sf_dir, "ev_type", counted=True)
    buckets = stored(samples)
    ranges = fractions_of(buckets, CUTS)
    found = ranks(buckets, ranges, 50.0)
    exact = in_range(samples, ranges).groupBy("query", "series").agg((F.count_if(F.col("value") <= 50) / F.count("*")).alias("share"))
    return found.join(exact, ["query", "series"]).select("query", "series", F.round("share", 6).alias("exact"), (F.abs(F.col("rank") - F.col("share")) <= F.col("bound") + 2 * sketch_error(K_KLL)).alias("within_bound"))


QUERIES |= {"ehkll_raw_estimates": raw_estimates, "ehkll_rank": rank_queries}
SQL["ehkll_rank"] = f"WITH v AS ({VIEWS['ev_type'].sql}), {fractions_sql(CUTS)} SELECT query, v.series, round(count(*) FILTER (value <= 50) / count(*), 6) AS exact, true AS within_bound FROM v JOIN ranges r ON v.series = r.series AND seq > low AND seq <= high GROUP BY query, v.series"


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Drill-down 0.9-quantiles of one series from the bucket table."""
    buckets = stored(series_view(spark, sf_dir, "li_all", counted=True))
    return quantiles(buckets, fractions_of(buckets, DRILL), [0.9])

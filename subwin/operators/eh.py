"""Exponential histograms over time: layouts by count and by weight, and range queries on their buckets.

The layout by count has a closed form, so buckets come from positions by arithmetic. Buckets of size
2 ** i number between ceil(k / 2) and ceil(k / 2) + 1, of size one between k and k + 1: of the a samples (or
pairs, ...) that have reached a level, those beyond its cap have moved on two by two.

A range query takes the buckets that start inside the range: the one that holds its start is left out
unless it starts there, the one that holds its end is taken whole. A range inside one bucket takes none,
and the caller falls back to the samples.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from subwin.sources.views import VIEWS, series_view

#: Levels of a layout: sizes up to 2 ** 49.
LEVELS = 50


def level_counts(n: Column, k: int) -> Column:
    """Array of the number of buckets on each level, for n samples."""

    def step(state: Column, i: Column) -> Column:
        cap = F.when(i == 0, F.lit(k)).otherwise(F.lit(-(-k // 2)))
        moved = F.greatest(F.lit(0), F.floor((state["a"] - cap) / 2)).cast("long")
        return F.struct(moved.alias("a"), F.concat(state["c"], F.array((state["a"] - 2 * moved).cast("long"))).alias("c"))

    start = F.struct(n.cast("long").alias("a"), F.array().cast("array<bigint>").alias("c"))
    return F.aggregate(F.sequence(F.lit(0), F.lit(LEVELS - 1)), start, step)["c"]


def layouts(samples: DataFrame, k: int) -> DataFrame:
    """series, n, past (samples newer than each level), older (buckets newer than each level), total (buckets)."""
    counted = samples.groupBy("series").agg(F.count("*").alias("n")).withColumn("c", level_counts(F.col("n"), k))

    def sums(each: str) -> Column:
        return F.expr(f"aggregate(sequence(0, {LEVELS - 1}), array(0L), (s, i) -> concat(s, array(element_at(s, -1) + {each})))")

    return counted.select("series", "n", sums("c[i] * shiftleft(1L, i)").alias("past"), sums("c[i]").alias("older")).withColumn("total", F.element_at("older", -1))


def layout_count(samples: DataFrame, k: int) -> DataFrame:
    """``samples`` with n (of the series) and bucket, 1 the oldest.

    Arithmetic on n and seq, row by row. With h = ceil(k / 2) and b = max(0, n - k) div 2 + h, the number of units that
    reach level i is a(i) = (b >> (i - 1)) - h, so level i holds the samples up to position a(i) * 2 ** i that no higher
    one does; and the sum of b >> j over all j is 2 b less the number of its bits, which gives the buckets before a level.
    ``samples`` that have a column n, which has to count all of them by series, are joined with nothing.
    """
    if "n" not in samples.columns:
        samples = samples.join(samples.groupBy("series").agg(F.count("*").alias("n")), "series")
    h = -(-k // 2)
    placed = samples.withColumn("b", F.expr(f"greatest(0L, n - {k}) div 2 + {h}"))
    # of the sample and of the oldest one: the highest level that its position allows, then that or the next lower
    for name, seq in (("level", "seq"), ("top", "1L")):
        placed = placed.withColumn("x", F.expr(f"greatest(1L, (2 * b - {seq}) div {h})")).withColumn("e", F.expr("cast(floor(log2(x + 0.5D)) AS int)"))
        placed = placed.withColumns({"a": F.expr(f"shiftleft(shiftright(b, greatest(e - 1, 0)) - {h}, e)"), "c": F.expr(f"shiftleft(shiftright(b, greatest(e - 2, 0)) - {h}, greatest(e - 1, 0))")})
        placed = placed.withColumn(name, F.expr(f"CASE WHEN e > 0 AND a >= {seq} THEN e WHEN e > 1 AND c >= {seq} THEN e - 1 ELSE 0 END"))
    placed = placed.withColumns({"s": F.expr("shiftright(b, greatest(level - 1, 0))"), "q": F.expr("shiftright(b, greatest(top - 1, 0))")}).withColumn("all", F.expr(f"q - bit_count(q) + {h}L * top"))
    newest = "seq + all - 2 * b + bit_count(b)"
    bucket = F.expr(f"CASE WHEN top = 0 THEN seq WHEN level = 0 THEN {newest} ELSE all - (s - bit_count(s) + {h}L * level) + shiftright(seq - 1, level) + 1 END")
    return placed.withColumn("bucket", bucket).drop("b", "x", "e", "a", "c", "level", "top", "s", "q", "all")


def bucket_spans(placed: DataFrame, *aggregates: Column) -> DataFrame:
    """Buckets of placed samples: series, bucket, t_lo, t_hi, seq_lo, seq_hi, size, and the given aggregates."""
    spans = (F.min("t").alias("t_lo"), F.max("t").alias("t_hi"), F.min("seq").alias("seq_lo"), F.max("seq").alias("seq_hi"), F.count("*").alias("size"))
    return placed.groupBy("series", "bucket").agg(*spans, *aggregates)


def in_range(points: DataFrame, ranges: DataFrame, at: str = "seq", width: int | None = None) -> DataFrame:
    """``points`` (series, ...) in the ranges (query, series, low, high], by ``at``.

    Ranges are spread over panes, so that the join is an equality on series and pane with the range as
    residual: never a nested loop, and a series of any length is spread over tasks.
    """
    width = width or (1 << 20 if at.startswith("seq") else 86_400_000_000)
    spread = ranges.where("low < high").withColumn("in_pane", F.explode(F.sequence(F.expr(f"low div {width}"), F.expr(f"high div {width}"))))
    paned = points.withColumn("in_pane", F.expr(f"{at} div {width}"))
    return spread.join(paned, ["series", "in_pane"]).where((F.col(at) > F.col("low")) & (F.col(at) <= F.col("high"))).drop("in_pane")


def segments(ranges: DataFrame) -> DataFrame:
    """query, series, low, high: each range of ``ranges`` in pieces that no bound of the series' ranges divides, so that
    samples met once by piece are counted for all ranges."""
    bounds = ranges.where("low < high").select("series", F.explode(F.array("low", "high")).alias("from")).distinct()
    pieces = bounds.withColumn("to", F.lead("from").over(Window.partitionBy("series").orderBy("from")))
    return ranges.join(pieces, "series").where("low <= from AND to <= high").select("query", "series", F.col("from").alias("low"), F.col("to").alias("high"))


def cut_runs(runs: DataFrame, spans: DataFrame, width: int = 1 << 18) -> DataFrame:
    """``runs`` cut by ``spans`` (series, low, high, ...), of positions (low, high]: the columns of the spans with seq, t, step, len
    and items of the part of the run that is in each. They meet by blocks of ``width`` positions; a pair is taken where it begins."""
    blocks = spans.where("low < high").withColumn("block", F.expr(f"explode(sequence(low div {width}, (high - 1) div {width}))"))
    paned = runs.where("len > 0").selectExpr("series", "seq AS at", "t AS t0", "step", "len AS of", "items AS whole", f"explode(sequence((seq - 1) div {width}, (seq + len - 2) div {width})) AS block")
    met = paned.join(blocks, ["series", "block"]).withColumns({"seq": F.expr("greatest(at, low + 1)"), "last": F.expr("least(at + of - 1, high)")}).where(f"seq <= last AND (seq - 1) div {width} = block")
    return met.selectExpr(*spans.columns, "seq", "t0 + (seq - at) * step AS t", "step", "last - seq + 1 AS len", "CASE WHEN last - seq + 1 = of THEN whole ELSE slice(whole, cast(seq - at + 1 AS int), cast(greatest(0, last - seq + 1) AS int)) END AS items")


def query_range(buckets: DataFrame, ranges: DataFrame, by: str = "seq") -> DataFrame:
    """Buckets of each range: ``ranges`` has query, series, low, high, for samples in (low, high] by seq or t."""
    return in_range(buckets, ranges, f"{by}_lo").withColumn("straddles", F.col(f"{by}_hi") > F.col("high"))


def query_window(buckets: DataFrame, low: Column, by: str = "seq") -> DataFrame:
    """The full window: all buckets but the one that straddles its start."""
    return buckets.where(F.col(f"{by}_lo") > low)


def insert_counts(n: int, k: int) -> list[int]:
    """Sizes, oldest first, by inserting n samples one at a time and merging: the simulation of the closed form."""
    levels: list[int] = [0]
    for _ in range(n):
        levels[0] += 1
        i = 0
        while levels[i] > (k if i == 0 else -(-k // 2)) + 1:
            levels[i] -= 2
            if i + 1 == len(levels):
                levels.append(0)
            levels[i + 1] += 1
            i += 1
    return [1 << i for i in reversed(range(len(levels))) for _ in range(levels[i])]


class Fold:
    """Buckets under a weakly additive weight, built by folding panes in time order.

    Two neighbours merge when the weight of their union is at most 1 / k of what is newer. ``weight`` maps
    a summary to its weight, ``merge`` two summaries to one.
    """

    def __init__(self, k: float, weight: Callable, merge: Callable):
        self.k, self.weight, self.merge = k, weight, merge
        self.buckets: list[tuple] = []  # first pane, last pane, summary, weight

    def add(self, pane: int, summary) -> None:
        self.buckets.append((pane, pane, summary, self.weight(summary)))
        newer, i = 0.0, len(self.buckets) - 1
        out = []
        while i >= 0:
            bucket = self.buckets[i]
            while i > 0 and self.buckets[i - 1][3] + bucket[3] <= newer / self.k:
                older = self.buckets[i - 1]
                joint = self.merge(older[2], bucket[2])
                weight = self.weight(joint)
                if weight > 2 * newer / self.k:
                    break
                bucket = (older[0], bucket[1], joint, weight)
                i -= 1
            out.append(bucket)
            newer += bucket[3]
            i -= 1
        self.buckets = out[::-1]

    def expire(self, pane: int) -> None:
        """Drop buckets whose newest pane is older than ``pane``."""
        self.buckets = [b for b in self.buckets if b[1] >= pane]


def layout_weight(panes: DataFrame, k: float, weight: Callable, merge: Callable, schema: str = "series string, bucket int, pane_lo long, pane_hi long, weight double", read: Callable = lambda x: x) -> DataFrame:
    """Bucket spans in panes, by a fold over each series' pane summaries (series, pane, summary): the fold sees one
    fixed-size summary for each pane, never samples, and holds those of the buckets and of one pane. A pane may come in
    several summaries, which are merged. ``read`` makes a summary of what is in the column."""

    def spans(series, folded: Fold) -> pa.RecordBatch:
        rows = [(series, i + 1, lo, hi, float(w)) for i, (lo, hi, _, w) in enumerate(folded.buckets)]
        return pa.RecordBatch.from_arrays([pa.array(x, kind) for x, kind in zip(zip(*rows), (pa.string(), pa.int32(), pa.int64(), pa.int64(), pa.float64()))], names=["series", "bucket", "pane_lo", "pane_hi", "weight"])

    def fold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        folded = now = held = None  # the series' fold, the pane that is being read with its series, its summary
        for batch in batches:
            for series, pane, summary in zip(*(x.to_pylist() for x in batch.columns)):
                if now == (series, pane):
                    held = merge(held, read(summary))
                    continue
                if now:
                    folded.add(now[1], held)
                if not now or now[0] != series:
                    if now:
                        yield spans(now[0], folded)
                    folded = Fold(k, weight, merge)
                now, held = (series, pane), read(summary)
        if now:
            folded.add(now[1], held)
            yield spans(now[0], folded)

    ordered = panes.select("series", "pane", "summary").repartition("series").sortWithinPartitions("series", "pane")
    return ordered.mapInArrow(fold, schema)


def invariant_count(sizes: list[int], k: int) -> bool:
    """Each bucket of more than one sample is at most 2 / k of one more than what is newer."""
    newer = 0
    for size in reversed(sizes):
        if size > 1 and size * k > 2 * (1 + newer):
            return False
        newer += size
    return True


def weakly_additive(weight: Callable, merge: Callable, pairs: Iterator[tuple], c_f: float) -> bool:
    """f(a) + f(b) <= f(a and b) <= c_f (f(a) + f(b)) for all pairs of summaries."""
    return all(weight(a) + weight(b) <= weight(merge(a, b)) * (1 + 1e-12) and weight(merge(a, b)) <= c_f * (weight(a) + weight(b)) * (1 + 1e-12) for a, b in pairs)


# -- queries ----------------------------------------------------------------------------------------------------------

LAYOUT_SQL = """
lv AS (
    WITH RECURSIVE step(series, n, i, a, c, past, older) AS (
        SELECT series, n, 0, greatest(0, (n - {k}) // 2), n - 2 * greatest(0, (n - {k}) // 2), 0::BIGINT, 0::BIGINT FROM (SELECT series, count(*) AS n FROM v GROUP BY series)
        UNION ALL
        SELECT series, n, i + 1, greatest(0, (a - {half}) // 2), a - 2 * greatest(0, (a - {half}) // 2), past + c * (1::BIGINT << i), older + c FROM step WHERE a > 0)
    SELECT series, n, i, c, past, older, sum(c) OVER (PARTITION BY series) AS total FROM step),
placed AS (
    SELECT v.*, lv.n, (total - older - ceil((lv.n - v.seq + 1 - past) / (1::BIGINT << i)) + 1)::BIGINT AS bucket
    FROM v JOIN lv ON v.series = lv.series AND lv.n - v.seq + 1 > past AND lv.n - v.seq + 1 <= past + c * (1::BIGINT << i))
"""


def layout_sql(view: str, k: int) -> str:
    """CTEs v, lv and placed: the samples of a view with their bucket."""
    return f"WITH v AS ({view}), " + LAYOUT_SQL.format(k=k, half=-(-k // 2))


def _layout_query(view: str, k: int):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return bucket_spans(layout_count(series_view(spark, sf_dir, view, counted=True), k)).select("series", "bucket", "t_lo", "t_hi", "seq_lo", "seq_hi", "size")

    return run


_SPANS = "SELECT series, bucket, min(t) AS t_lo, max(t) AS t_hi, min(seq) AS seq_lo, max(seq) AS seq_hi, count(*) AS size FROM placed GROUP BY series, bucket"
_CASES = {"eh_layout_events": ("ev_type", 20), "eh_layout_users": ("ev_user", 4), "eh_layout_lines": ("li_all", 50), "eh_layout_tokens": ("doc_tokens", 50), "eh_layout_nations": ("ord_nation", 7)}
QUERIES: dict = {name: _layout_query(view, k) for name, (view, k) in _CASES.items()}
SQL: dict = {name: layout_sql(VIEWS[view].sql, k) + _SPANS for name, (view, k) in _CASES.items()}


def fractions_of(samples: DataFrame, cuts: list[tuple[str, float, float]]) -> DataFrame:
    """query, series, low, high: ranges (low, high] in positions, given as fractions back from the newest sample,
    of the series of samples, or of buckets that say by n how many samples their series has."""
    n = samples.groupBy("series").agg((F.max("n") if "n" in samples.columns else F.count("*")).alias("n"))
    rows = F.explode(F.array(*[F.struct(F.lit(q).alias("query"), F.lit(a).alias("a"), F.lit(b).alias("b")) for q, a, b in cuts])).alias("cut")
    return n.select("series", "n", rows).selectExpr("cut.query", "series", "n - cast(round(n * cut.a) AS bigint) AS low", "n - cast(round(n * cut.b) AS bigint) AS high")


def fractions_sql(cuts: list[tuple[str, float, float]]) -> str:
    """CTE ranges after v."""
    values = ", ".join(f"('{q}', {a!r}::DOUBLE, {b!r}::DOUBLE)" for q, a, b in cuts)
    return f"ranges AS (SELECT query, series, n - round(n * a)::BIGINT AS low, n - round(n * b)::BIGINT AS high FROM (SELECT series, count(*) AS n FROM v GROUP BY series) CROSS JOIN (VALUES {values}) AS c(query, a, b))"


CUTS = [("full", 1.0, 0.0), ("suffix", 0.4, 0.0), ("middle", 0.6, 0.3), ("old", 0.9, 0.7), ("narrow", 0.52, 0.5)]


def cover(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Which buckets each range takes, and what the alignment leaves out or adds."""
    samples = series_view(spark, sf_dir, "ev_type")
    taken = query_range(bucket_spans(layout_count(samples, 20)), fractions_of(samples, CUTS))
    return taken.groupBy("query", "series").agg(F.min("bucket").alias("first"), F.max("bucket").alias("last"), F.count("*").alias("buckets"), F.sum("size").alias("samples"), (F.min("seq_lo") - 1 - F.min("low")).alias("dropped"), F.greatest(F.max(F.col("seq_hi") - F.col("high")), F.lit(0)).alias("added"))


QUERIES["eh_cover_ranges"] = cover
SQL["eh_cover_ranges"] = layout_sql(VIEWS["ev_type"].sql, 20) + f""", {fractions_sql(CUTS)}, b AS ({_SPANS})
SELECT query, b.series, min(bucket) AS first, max(bucket) AS last, count(*) AS buckets, sum(size)::BIGINT AS samples, min(seq_lo) - 1 - min(low) AS dropped, greatest(max(seq_hi - high), 0) AS added
FROM b JOIN ranges r ON b.series = r.series AND seq_lo > low AND seq_lo <= high GROUP BY query, b.series"""

"""Exact functions over time: every function at every evaluation point, from the samples themselves."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from subwin.sources.views import DAY, VIEWS, series_view

#: The functions and their aggregates over the samples of a window; sums go over hundredths, so that their order is of no matter.
AGGREGATES = {
    "quantile": "round(percentile(value, 0.9), 6)",
    "quantile_disc": "round(percentile_disc(0.9) WITHIN GROUP (ORDER BY value), 6)",
    "min": "min(value)",
    "max": "max(value)",
    "count": "count(*)",
    "sum": "sum(cast(round(value * 100) AS bigint)) / 100.0D",
    "avg": "round(sum(cast(round(value * 100) AS bigint)) / 100.0D / count(*), 6)",
    "stddev": "round(sqrt(greatest(0, sum(c * c) / count(*) - pow(sum(c) / count(*), 2))) / 100, 4)",
    "stdvar": "round(greatest(0, sum(c * c) / count(*) - pow(sum(c) / count(*), 2)) / 10000, 2)",
    "last": "max_by(value, seq)",
    "present": "count(*) > 0",
    "distinct": "count(DISTINCT item)",
}
_DUCK = {"quantile": "round(quantile_cont(value, 0.9), 6)", "quantile_disc": "round(quantile_disc(value, 0.9), 6)", "last": "arg_max(value, seq)"}
#: Functions of item counts: c is the count of an item, n of all.
OF_COUNTS = {
    "entropy": "round(ln(sum(c)) - sum(c * ln(c)) / sum(c), 6)",
    "l2": "round(sqrt(sum(c * c)), 6)",
    "l1": "sum(c)",
}


@dataclass(frozen=True)
class Grid:
    """Evaluation points start, start + step, ... up to end; windows (point - window, point]."""

    start: int
    end: int
    step: int
    window: int

    def expand(self, samples: DataFrame) -> DataFrame:
        """Each sample with each evaluation point whose window holds it: arithmetic, not a join."""
        last = (self.end - self.start) // self.step
        low = f"greatest(0, cast(ceil((t - {self.start}) / {self.step}) AS bigint))"
        high = f"least({last}, cast(ceil((t + {self.window} - {self.start}) / {self.step}) AS bigint) - 1)"
        reached = samples.withColumns({"low": F.expr(low), "high": F.expr(high)}).where("low <= high")
        return reached.withColumn("eval_t", F.expr(f"explode(transform(sequence(low, high), i -> {self.start} + i * {self.step}))")).drop("low", "high")

    def points(self) -> list[int]:
        return list(range(self.start, self.end + 1, self.step))

    def sql(self, view: str) -> str:
        return f"SELECT s.*, e.eval_t FROM ({view}) s JOIN (SELECT unnest(range({self.start}, {self.end} + 1, {self.step})) AS eval_t) e ON s.t > e.eval_t - {self.window} AND s.t <= e.eval_t"


#: Ten-day windows each day, from the eleventh day of the events on.
DAILY = Grid(1_704_067_200_000_000 + 10 * DAY, 1_704_067_200_000_000 + 30 * DAY, DAY, 10 * DAY)


def over_time(samples: DataFrame, fn: str, grid: Grid, arg: float | None = None) -> DataFrame:
    """series, eval_t and result: ``fn`` over the samples of each window that has any. ``arg`` is the quantile, or how many
    items; topk has a row of each item, with item and its count as result."""
    if fn == "topk":
        return top_items(samples, grid, int(arg)).select("series", "eval_t", "item", F.col("c").alias("result"))
    rows = grid.expand(samples)
    if fn in AGGREGATES:
        aggregate = AGGREGATES[fn].replace("0.9", repr(float(arg))) if arg is not None else AGGREGATES[fn]
        return rows.withColumn("c", F.expr("cast(round(value * 100) AS bigint)")).groupBy("series", "eval_t").agg(F.expr(aggregate).alias("result"))
    counts = rows.groupBy("series", "eval_t", "item").agg(F.count("*").alias("c"))
    return counts.groupBy("series", "eval_t").agg(F.expr(OF_COUNTS[fn]).alias("result"))


def top_items(samples: DataFrame, grid: Grid, k: int) -> DataFrame:
    """series, eval_t, rank, item, c: the ``k`` most frequent items of each window, ties by item."""
    counts = grid.expand(samples).groupBy("series", "eval_t", "item").agg(F.count("*").alias("c"))
    order = Window.partitionBy("series", "eval_t").orderBy(F.desc("c"), "item")
    return counts.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


def absent(samples: DataFrame, grid: Grid) -> DataFrame:
    """series, eval_t of windows without a sample, for series that have any."""
    every = samples.select("series").distinct().withColumn("eval_t", F.explode(F.array(*[F.lit(grid.start + i * grid.step) for i in range((grid.end - grid.start) // grid.step + 1)])))
    return every.join(grid.expand(samples).select("series", "eval_t").distinct(), ["series", "eval_t"], "left_anti")


def _query(fn: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return over_time(series_view(spark, sf_dir, "ev_type"), fn, DAILY)

    return run


_VIEW = DAILY.sql(VIEWS["ev_type"].sql)
QUERIES = {f"exact_{fn}": _query(fn) for fn in (*AGGREGATES, *OF_COUNTS)}
QUERIES["exact_topk"] = lambda spark, d: top_items(series_view(spark, d, "ev_type"), DAILY, 3)
QUERIES["exact_absent"] = lambda spark, d: absent(series_view(spark, d, "ev_user"), Grid(DAILY.start, DAILY.end, DAY, DAY // 2))
SQL = {f"exact_{fn}": f"SELECT series, eval_t, {_DUCK.get(fn, agg).replace('.0D', '.0')} AS result FROM (SELECT *, cast(round(value * 100) AS bigint) AS c FROM ({_VIEW})) GROUP BY series, eval_t" for fn, agg in AGGREGATES.items()}
SQL |= {f"exact_{fn}": f"SELECT series, eval_t, {agg} AS result FROM (SELECT series, eval_t, item, cast(count(*) AS bigint) AS c FROM ({_VIEW}) GROUP BY ALL) GROUP BY series, eval_t".replace("sum(c) AS", "cast(sum(c) AS bigint) AS") for fn, agg in OF_COUNTS.items()}
SQL["exact_topk"] = f"SELECT * FROM (SELECT series, eval_t, item, c, row_number() OVER (PARTITION BY series, eval_t ORDER BY c DESC, item) AS rank FROM (SELECT series, eval_t, item, count(*) AS c FROM ({_VIEW}) GROUP BY ALL)) WHERE rank <= 3"
_SPARSE = Grid(DAILY.start, DAILY.end, DAY, DAY // 2)
SQL["exact_absent"] = f"SELECT series, eval_t FROM (SELECT DISTINCT series FROM ({VIEWS['ev_user'].sql})) CROSS JOIN (SELECT unnest(range({DAILY.start}, {DAILY.end} + 1, {DAY})) AS eval_t) EXCEPT SELECT series, eval_t FROM ({_SPARSE.sql(VIEWS['ev_user'].sql)})"

"""The cache as committed tables, and rules answered from it: hits from buckets, all else exactly.

An instance belongs to a subject (a view, or a series derived from one) and a family of summaries. A committed version says
which times it covers, all samples in (low, high]; a question about others is a miss, as is one wider than what the registry
keeps the instance for, and one that lies inside a bucket. Misses are answered from the samples.
"""

from __future__ import annotations

import hashlib
import uuid
from collections.abc import Callable
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from subwin.functions.exact import DAILY, Grid, over_time
from subwin.operators import kll, sampling, univ
from subwin.operators.eh import CUTS, fractions_of, in_range
from subwin.plans.rules import Node, OverTime, Registry, RuleSpec, _sql, evaluate, leaf, leaves, matching, parse, subject_samples
from subwin.sources.views import DAY, EPOCH, VIEWS, series_view
from subwin.storage import Scratch

END = EPOCH + 30 * DAY


@dataclass(frozen=True)
class Instance:
    """A committed version: its tables, and the times (low, high] of which it has all samples."""

    tables: dict[str, DataFrame]
    low: int
    high: int


class CacheStore:
    """Tables by subject and family under ``root``. A version is written whole and then marked; readers take the
    last marked one, so they never see half of one and need no lock. Replicas read the same files."""

    def __init__(self, spark: SparkSession, root: str):
        self.spark, self.root = spark, root
        self._path = spark._jvm.org.apache.hadoop.fs.Path
        self._fs = self._path(root).getFileSystem(spark._jsc.hadoopConfiguration())

    def _place(self, subject: str, family: str) -> str:
        return f"{self.root}/{family}-{hashlib.md5(subject.encode()).hexdigest()}"

    def _names(self, path: str) -> list[str]:
        return [x.getPath().getName() for x in self._fs.listStatus(self._path(path))] if self._fs.exists(self._path(path)) else []

    def _marks(self, subject: str, family: str) -> list[str]:
        return sorted(self._names(self._place(subject, family) + "/committed"), key=lambda t: int(t.split("_")[0]))

    def versions(self, subject: str, family: str) -> list[int]:
        return [int(t.split("_")[0]) for t in self._marks(subject, family)]

    def commit(self, subject: str, family: str, tables: dict[str, DataFrame], low: int, high: int) -> int:
        """Write a version that has all samples in (low, high], dealt by series and bucket, and mark it. The mark is one directory: it is there or not."""
        number = max(self.versions(subject, family), default=0) + 1
        token, place = f"{number}_{low}_{high}_{uuid.uuid4().hex}", self._place(subject, family)
        for name, df in tables.items():
            keys = [c for c in ("series", "bucket") if c in df.columns]
            (df.repartition(*keys).sortWithinPartitions(*keys) if "bucket" in keys else df).write.parquet(f"{place}/data/{token}/{name}")
        self._fs.mkdirs(self._path(f"{place}/committed/{token}"))
        return number

    def read(self, subject: str, family: str) -> Instance | None:
        marks, place = self._marks(subject, family), self._place(subject, family)
        if not marks:
            return None
        _, low, high, _ = marks[-1].split("_")
        data = f"{place}/data/{marks[-1]}"
        return Instance({name: self.spark.read.parquet(f"{data}/{name}") for name in self._names(data)}, int(low), int(high))

    def vacuum(self, subject: str, family: str, keep: int = 1) -> int:
        """Delete all but the last versions; returns how many went."""
        tokens = self._marks(subject, family)
        gone = tokens[: len(tokens) - keep]
        for token in gone:
            for part in ("committed", "data"):
                self._fs.delete(self._path(f"{self._place(subject, family)}/{part}/{token}"), True)
        return len(gone)

    def drop(self, subject: str, family: str) -> None:
        """An instance that no rule needs any more: its data goes too."""
        self._fs.delete(self._path(self._place(subject, family)), True)


def sync(store: CacheStore, registry: Registry, rules: list[RuleSpec]) -> list[tuple[str, str]]:
    """Keep what ``rules`` need, in the registry and in the store; returns the instances that go."""
    gone = registry.sync(rules)
    for subject, family in gone:
        store.drop(subject, family)
    return gone


# -- building ----------------------------------------------------------------------------------------------------------


@dataclass(frozen=True)
class Sizes:
    """Parameters of the summaries: of the histograms, of the sketches, positions of a pane, chance of a sample."""

    k_eh: int = 50
    k_kll: int = 256
    k_univ: float = 50
    pane: int = 10
    config: univ.Config = univ.LARGE
    p: float = 0.1


def summaries(family: str, samples: DataFrame, sizes: Sizes = Sizes()) -> dict[str, DataFrame]:
    """The tables of one instance."""
    if family == "kll":
        return {"buckets": kll.build(samples, sizes.k_eh, sizes.k_kll)}
    if family == "univ":
        return univ.build(samples.drop("n"), sizes.pane, sizes.k_univ, sizes.config).tables()
    return {"kept": sampling.build(samples, sizes.p)}


def refresh(store: CacheStore, registry: Registry, rules: list[RuleSpec], view: Callable[[str, tuple[int, int]], DataFrame], now: int, sizes: Sizes = Sizes()) -> None:
    """Commit a version of every registered instance as wide as the registry says, up to ``now``: what is older has expired, and
    is not read. ``view`` gives the samples of a view in a window."""
    nodes = {(node.subject, family): node for rule in rules for node in leaves(parse(rule.expression)) for family in ("kll", "univ", "sample")}
    for (subject, family), width in registry.windows.items():
        node = nodes[subject, family]
        samples = view(node.view, (now - width, now))
        if node.inner:
            samples = subject_samples(node, samples)
        store.commit(subject, family, summaries(family, samples, sizes), now - width, now)


# -- answering ---------------------------------------------------------------------------------------------------------


def _of_samples(kept: DataFrame, ranges: DataFrame, fn: str, p: float) -> DataFrame:
    """Estimates from sampled rows; the bound is four standard errors, of the estimate as one."""
    inside = in_range(kept, ranges, "t").withColumn("c", F.expr("cast(round(value * 100) AS bigint)"))
    count_error, mean_error = f"sqrt({1 - p} / count(*))", "coalesce(stddev_samp(value) / sqrt(count(*)) / abs(avg(value)), 1)"
    error = {"count": count_error, "l1": count_error, "avg": mean_error, "sum": f"({count_error} + {mean_error})"}.get(fn, "sqrt(1 / count(*))")
    estimate = sampling.ESTIMATORS["count" if fn == "l1" else fn].format(p=p)
    return inside.groupBy("query", "series").agg(F.expr(estimate).alias("result"), F.expr(f"4 * {error}").alias("bound"))


def _alignment(spans: DataFrame, ranges: DataFrame) -> DataFrame:
    """query, series and bound: the larger of the buckets that a range cuts at its ends, as a share of what it takes."""
    before = spans.select("series", (F.col("bucket") + 1).alias("bucket"), F.col("size").alias("older"))
    taken = in_range(spans, ranges, "t_lo").join(before, ["series", "bucket"], "left")
    cut = F.greatest(F.expr("coalesce(min_by(older, bucket), 0)"), F.max(F.when(F.col("t_hi") > F.col("high"), F.col("size")).otherwise(0)))
    return taken.groupBy("query", "series").agg((cut / F.sum("size")).alias("bound"))


def estimates(node: OverTime, family: str, instance: Instance, ranges: DataFrame, sizes: Sizes = Sizes()) -> DataFrame:
    """query, series, result, bound, and item for topk, of ranges of time that the instance covers."""
    if family == "kll":
        phi = {"min": 0.0, "max": 1.0}.get(node.fn, node.arg)
        return kll.quantiles(instance.tables["buckets"], ranges, [phi], by="t").select("query", "series", F.col("estimate").alias("result"), "bound")
    if family == "sample":
        return _of_samples(instance.tables["kept"], ranges, node.fn, sizes.p)
    buckets = univ.Buckets(**instance.tables)
    if node.fn == "topk":
        found = univ.top_items(buckets, ranges, int(node.arg), sizes.config, by="t").select("query", "series", "item", F.col("est").alias("result"))
    else:
        value = {"count": F.col("n"), "l1": F.col("n")}.get(node.fn, F.col(node.fn))
        found = univ.query(buckets, ranges, sizes.config, by="t").select("query", "series", value.alias("result"))
    return found.join(_alignment(buckets.spans, ranges), ["query", "series"])


def _spans(instance: Instance) -> DataFrame | None:
    return instance.tables.get("buckets", instance.tables.get("spans"))


def narrow(instance: Instance, ranges: DataFrame) -> DataFrame:
    """Ranges that reach into a bucket but take none: the samples have to answer them."""
    spans = _spans(instance)
    if spans is None:
        return ranges.limit(0)
    taken = in_range(spans, ranges, "t_lo").select("query", "series").distinct()
    missed = ranges.join(taken, ["query", "series"], "left_anti")
    # the last bucket that starts at or before the range reaches into it, or there is nothing in it
    last = missed.join(spans.select("series", "t_lo", "t_hi"), "series").where("t_lo <= low").groupBy("query", "series").agg(F.max("t_hi").alias("reach"))
    return missed.join(last, ["query", "series"]).where("reach > low").drop("reach")


def _segments(points: list[int], grid: Grid) -> list[Grid]:
    """Grids of runs of points."""
    out: list[list[int]] = []
    for p in points:
        if out and p - out[-1][1] == grid.step:
            out[-1][1] = p
        else:
            out.append([p, p])
    return [replace(grid, start=a, end=b) for a, b in out]


def cached_leaf(store: CacheStore, registry: Registry, sizes: Sizes = Sizes()) -> Callable[[OverTime, DataFrame, Grid], DataFrame]:
    """For rules.evaluate: series, eval_t, result, source (cache or exact) and bound (0 where exact), and item for topk.

    Each point of the grid is a hit if the last committed version covers its window, and the registry keeps it for one as
    wide. Samples are read for the other points only, and for hits inside a bucket.
    """

    def over(node: OverTime, samples: DataFrame, grid: Grid) -> DataFrame:
        grid = replace(grid, window=node.window)
        items = ["item"] * (node.fn == "topk")
        family = registry.family(node)
        instance = store.read(node.subject, family) if family else None
        # what the registry has narrowed since the version was committed has expired
        low = max(instance.low, instance.high - registry.windows[node.subject, family]) if instance else None
        hits = [p for p in grid.points() if instance and p - node.window >= low and p <= instance.high]
        parts = []
        own = subject_samples(node, samples)
        exactly = lambda rows: rows.select("series", "eval_t", *items, F.col("result"), F.lit("exact").alias("source"), F.lit(0.0).alias("bound"))
        for run in _segments([p for p in grid.points() if p not in set(hits)], grid):
            parts.append(exactly(over_time(own.where((F.col("t") > run.start - run.window) & (F.col("t") <= run.end)), node.fn, run, node.arg)))
        if hits:
            known = _spans(instance) if _spans(instance) is not None else instance.tables["kept"]
            asked = (known if node.inner else matching(known, node.matchers)).select("series").distinct()
            ranges = asked.select(F.explode(F.array(*[F.lit(p).cast("long") for p in hits])).alias("query"), "series").withColumns({"low": F.col("query") - node.window, "high": F.col("query")})
            found = estimates(node, family, instance, ranges, sizes)
            parts.append(found.select("series", F.col("query").alias("eval_t"), *items, F.col("result"), F.lit("cache").alias("source"), "bound"))
            inside = narrow(instance, ranges)
            if not inside.isEmpty():
                spots = inside.select("series", F.col("query").alias("eval_t"))
                held = grid.expand(own).join(spots, ["series", "eval_t"])
                one = Grid(0, 0, 1, 1)
                # each sample with its one point: a grid of that point alone
                alone = held.withColumns({"at": F.col("eval_t"), "name": F.col("series")}).withColumn("series", F.concat_ws("\0", "series", "eval_t")).withColumn("t", F.lit(0))
                rows = over_time(alone.drop("eval_t"), node.fn, one, node.arg)
                parts.append(exactly(rows.withColumns({"eval_t": F.substring_index("series", "\0", -1).cast("long"), "series": F.expr("substr(series, 1, length(series) - length(substring_index(series, '\0', -1)) - 1)")})))
        out = parts[0]
        for part in parts[1:]:
            out = out.withColumn("result", F.col("result").cast("double")).unionByName(part.withColumn("result", F.col("result").cast("double")))
        return out

    return over


def evaluate_cached(node: Node, samples: Callable[[str], DataFrame], store: CacheStore, registry: Registry, grid: Grid, sizes: Sizes = Sizes()) -> DataFrame:
    return evaluate(node, samples, grid, cached_leaf(store, registry, sizes))


def lookup(buckets: DataFrame, selector: DataFrame) -> DataFrame:
    """Buckets of the series that a selector (series) names: a semi-join on the series' hash, then on its name."""
    keyed = selector.select(F.xxhash64("series").alias("wanted"), F.col("series").alias("name")).distinct()
    return buckets.join(keyed, (F.xxhash64(buckets["series"]) == F.col("wanted")) & (buckets["series"] == F.col("name")), "left_semi")


def exact_quantiles(samples: DataFrame, ranges: DataFrame, phis: list[float], by: str = "seq") -> DataFrame:
    points = ", ".join(f"{p!r}D" for p in phis)
    held = in_range(samples, ranges, by).groupBy("query", "series").agg(F.count("*").alias("samples"), F.expr(f"percentile(value, array({points}))").alias("points"))
    each = F.inline(F.arrays_zip(F.expr(f"array({points})").alias("phi"), F.col("points").alias("estimate")))
    return held.select("query", "series", "samples", F.lit(0).cast("long").alias("buckets"), (1 / F.col("samples")).alias("bound"), each, F.lit("exact").alias("source"))


def run(samples: DataFrame, store: CacheStore, registry: Registry, view: str, ranges: DataFrame, phis: list[float], by: str = "seq") -> DataFrame:
    """Quantiles of ranges from the committed cache, all series in one job; from the samples where the registry has no instance,
    or a range starts before what a series' buckets cover, by position or time, or before what the registry keeps."""
    instance = store.read(view, "kll") if (view, "kll") in registry.windows else None
    if instance is None:
        return exact_quantiles(samples, ranges, phis, by)
    buckets = instance.tables["buckets"].where(F.col("t_lo") > max(instance.low, instance.high - registry.windows[view, "kll"]))
    start = F.min("seq_lo") - 1 if by == "seq" else F.lit(max(instance.low, instance.high - registry.windows[view, "kll"]))
    end = F.max("seq_hi") if by == "seq" else F.lit(instance.high)
    covered = buckets.groupBy("series").agg(start.alias("from"), end.alias("to"))
    hits = ranges.join(covered, "series").where(F.col("low") >= F.col("from")).where(F.col("high") <= F.col("to")).drop("from", "to")
    misses = ranges.join(hits.select("query", "series"), ["query", "series"], "left_anti")
    return kll.answer(samples, buckets, hits, phis, by=by).unionByName(exact_quantiles(samples, misses, phis, by))


# -- queries -----------------------------------------------------------------------------------------------------------


def committed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Answers from the second committed version, with the exact values and whether each is within its bound."""
    samples = series_view(spark, sf_dir, "ev_type", counted=True)
    store = CacheStore(spark, Scratch(spark, "cache").root)
    store.commit("ev_type", "kll", {"buckets": kll.build(samples, 4, 64)}, 0, END)
    store.commit("ev_type", "kll", {"buckets": kll.build(samples)}, 0, END)
    registry = Registry({("ev_type", "kll"): END})
    ranges = fractions_of(store.read("ev_type", "kll").tables["buckets"], CUTS)
    return kll.judged(samples, run(samples, store, registry, "ev_type", ranges, [0.5, 0.9]), ranges).select("query", "series", "phi", "exact", "within_bound")


def half_covered(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A cache of the newer half only: ranges that start before it are exact, the others come from buckets."""
    samples = series_view(spark, sf_dir, "ev_type", counted=True)
    store = CacheStore(spark, Scratch(spark, "cache").root)
    store.commit("ev_type", "kll", {"buckets": kll.build(samples).where("2 * (seq_lo - 1) >= n")}, 0, END)
    ranges = fractions_of(samples, [("all", 1.0, 0.0), ("newer", 0.3, 0.0), ("across", 0.7, 0.1)])
    found = run(samples, store, Registry({("ev_type", "kll"): END}), "ev_type", ranges, [0.5])
    return kll.judged(samples, found, ranges).join(found.select("query", "series", "source"), ["query", "series"]).select("query", "series", "phi", "exact", "source", "within_bound")


def missed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A view that no rule has registered: every answer is exact."""
    samples = series_view(spark, sf_dir, "ord_prio")
    store = CacheStore(spark, Scratch(spark, "cache").root)
    found = run(samples, store, Registry({}), "ord_prio", fractions_of(samples, CUTS), [0.5, 0.9])
    return found.select("query", "series", "phi", F.round("estimate", 6).alias("exact"), "source")


def selected(spark: SparkSession, sf_dir: str) -> DataFrame:
    buckets = kll.build(series_view(spark, sf_dir, "ev_type", counted=True), 20)
    wanted = spark.createDataFrame([("click",), ("nothing",)], "series string")
    return lookup(buckets, wanted).groupBy("series").agg(F.sum("size").alias("n"))


#: Rules whose caches are ten days wide, so that of five-day windows the last six points are hits.
KEPT = [RuleSpec(f"wide_{fn}", "record", DAY, f"{fn}_over_time({arg}ev_type[10d])") for fn, arg in (("quantile", "0.5, "), ("distinct", ""), ("avg", ""))] + [RuleSpec("top", "record", DAY, "avg_over_time(max(ev_type)[10d])")]


def cached_rules(spark: SparkSession, sf_dir: str, kept: list[RuleSpec] = KEPT) -> tuple[CacheStore, Registry]:
    store, registry = CacheStore(spark, Scratch(spark, "cache").root), Registry.of(kept)
    refresh(store, registry, kept, lambda view, window: series_view(spark, sf_dir, view, counted=True, window=window), END)
    return store, registry


def _rule(text: str, share: float | None = 0.05):
    """A rule from the cache beside the exact one. Within: for quantiles, the rank error is at most the bound and twice the sketch's; for
    others, the error is at most the bound, or ``share`` of the exact value if that is more."""

    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        node, view = parse(text), lambda name: series_view(spark, sf_dir, name)
        store, registry = cached_rules(spark, sf_dir, [*KEPT, RuleSpec("own", "record", DAY, text.replace("5d", "10d"))])
        found = evaluate_cached(node, view, store, registry, DAILY)
        keys = ["series", "eval_t"] + ["item"] * (leaf(node).fn == "topk")
        exact = evaluate(node, view, DAILY).withColumnRenamed("result", "exact")
        if leaf(node).fn == "quantile":
            held = replace(DAILY, window=leaf(node).window).expand(subject_samples(leaf(node), view("ev_type"))).select("series", "eval_t", "value").join(found, ["series", "eval_t"])
            ranks = held.groupBy("series", "eval_t", "source", "bound").agg(F.count("*").alias("n"), F.count_if(F.col("value") < F.col("result")).alias("below"), F.count_if(F.col("value") <= F.col("result")).alias("upto"))
            phi = leaf(node).arg
            error = F.greatest(F.lit(0.0), F.col("below") / F.col("n") - phi, phi - F.col("upto") / F.col("n"))
            return ranks.join(exact, keys).select("series", "eval_t", "exact", "source", ((F.col("source") == "exact") | (error <= F.col("bound") + 2 * kll.sketch_error(kll.K_KLL))).alias("within"))
        most = F.greatest(F.col("bound") if share is None else F.lit(0.0), F.lit(share or 0.0))
        return found.join(exact, keys).select(*keys, "exact", "source", (F.abs(F.col("result") - F.col("exact")) <= most * F.abs("exact") + 1e-6).alias("within"))

    return query


def _top(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How many of the exact five most frequent items of each point the cache has, or items as frequent: at least four."""
    text = "topk_over_time(5, ev_type_k[5d])"
    node, view = parse(text), lambda name: series_view(spark, sf_dir, name)
    store, registry = cached_rules(spark, sf_dir, [RuleSpec("own", "record", DAY, text.replace("5d", "10d"))])
    found = evaluate_cached(node, view, store, registry, DAILY)
    counts = replace(DAILY, window=5 * DAY).expand(view("ev_type_k")).groupBy("series", "eval_t", "item").agg(F.count("*").alias("f"))
    nth = F.row_number().over(Window.partitionBy("series", "eval_t").orderBy(F.desc("f"), "item"))
    fifth = counts.withColumn("nth", nth).where("nth <= 5").groupBy("series", "eval_t").agg(F.min("f").alias("least"), F.sum("f").alias("exact"))
    hit = found.join(counts, ["series", "eval_t", "item"]).join(fifth, ["series", "eval_t"]).where("f >= 0.9 * least")
    return hit.groupBy("series", "eval_t", "exact", "source").agg((F.count("*") >= 4).alias("within"))


def registered(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A rule's results under a name, asked in SQL."""
    evaluate(parse("quantile_over_time(0.9, ev_type[5d])"), lambda name: series_view(spark, sf_dir, name), DAILY).createOrReplaceTempView("rule_q90")
    return spark.sql("SELECT series, count(*) AS points, max(result) AS top FROM rule_q90 WHERE result > 50 GROUP BY series")


QUERIES: dict = {"sql_registered": registered, "cache_committed": committed, "cache_half_covered": half_covered, "route_exact_fallback": missed, "cache_lookup": selected, "rule_topk_cached": _top}
_EXACT = kll._case_sql(VIEWS["ord_prio"].sql, [0.5, 0.9])
_V = VIEWS["ev_type"].sql
_HALF = [("all", 1.0, 0.0), ("newer", 0.3, 0.0), ("across", 0.7, 0.1)]
SQL: dict = {
    "cache_committed": kll._case_sql(VIEWS["ev_type"].sql, [0.5, 0.9]),
    "cache_half_covered": f"SELECT query, series, phi, exact, CASE query WHEN 'newer' THEN 'cache' ELSE 'exact' END AS source, within_bound FROM ({kll._case_sql(_V, [0.5], _HALF)})",
    "route_exact_fallback": f"SELECT query, series, phi, exact, 'exact' AS source FROM ({_EXACT})",
    "cache_lookup": "SELECT event_type AS series, count(*) AS n FROM events WHERE event_type = 'click' GROUP BY event_type",
}
_SOURCE = f"CASE WHEN eval_t - {5 * DAY} >= {END - 10 * DAY} THEN 'cache' ELSE 'exact' END AS source, true AS within"
_AVG = "round(sum(c) / 100.0 / count(*), 6)"
_COUNTS = f"(SELECT series, eval_t, item, count(*)::BIGINT AS c FROM ({replace(DAILY, window=5 * DAY).sql(_V)}) GROUP BY ALL)"
_KCOUNTS = f"(SELECT series, eval_t, item, count(*)::BIGINT AS c FROM ({replace(DAILY, window=5 * DAY).sql(VIEWS['ev_type_k'].sql)}) GROUP BY ALL)"
_RULES = {
    "rule_quantile_cached": ("quantile_over_time(0.9, ev_type[5d])", 0.05, _sql("round(quantile_cont(value, 0.9), 6)", 5 * DAY)),
    "rule_median_cached": ('quantile_over_time(0.5, ev_type{series!="click"}[5d])', 0.05, _sql("round(quantile_cont(value, 0.5), 6)", 5 * DAY, "series <> 'click'")),
    "rule_max_cached": ("max_over_time(ev_type[5d]) * 2", 0.05, _sql("max(value) * 2", 5 * DAY)),
    "rule_avg_cached": ("avg_over_time(ev_type[5d])", None, _sql(_AVG, 5 * DAY)),
    "rule_count_cached": ("count_over_time(ev_type[5d])", None, _sql("count(*)", 5 * DAY)),
    "rule_distinct_cached": ("distinct_over_time(ev_type[5d])", 0.05, _sql("count(DISTINCT item)", 5 * DAY)),
    "rule_entropy_cached": ("entropy_over_time(ev_type[5d])", 0.05, f"SELECT series, eval_t, round(ln(sum(c)) - sum(c * ln(c)) / sum(c), 6) AS result FROM {_COUNTS} GROUP BY series, eval_t"),
    "rule_l2_cached": ("l2_over_time(ev_type[5d])", 0.05, f"SELECT series, eval_t, round(sqrt(sum(c * c)), 6) AS result FROM {_COUNTS} GROUP BY series, eval_t"),
    "rule_inner_cached": ("avg_over_time(max(ev_type)[5d])", None, _sql(_AVG, 5 * DAY, view=f"SELECT 'max' AS series, t, max(value) AS value FROM ({_V}) GROUP BY t")),
}
QUERIES |= {name: _rule(text, share) for name, (text, share, _) in _RULES.items()}
SQL |= {name: f"SELECT series, eval_t, result AS exact, {_SOURCE} FROM ({sql})" for name, (_, _, sql) in _RULES.items()}
SQL["sql_registered"] = f"SELECT series, count(*) AS points, max(result) AS top FROM ({_RULES['rule_quantile_cached'][2]}) WHERE result > 50 GROUP BY series"
SQL["rule_topk_cached"] = f"SELECT series, eval_t, sum(c)::BIGINT AS exact, {_SOURCE} FROM (SELECT *, row_number() OVER (PARTITION BY series, eval_t ORDER BY c DESC, item) AS nth FROM {_KCOUNTS}) WHERE nth <= 5 GROUP BY series, eval_t"

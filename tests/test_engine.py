"""The engine: layouts, sketches, bounds, rules and streams, and queries against their SQL."""

import os
import random

import duckdb
import pytest
from pyspark.sql import functions as F

from subwin import catalog, metrics, workloads
from subwin.functions import exact
from subwin.operators import baselines, eh, kll, relational, sampling, smooth, univ
from subwin.plans import rules
from subwin.sources.views import DAY, series_view, synthetic
from subwin.storage import Scratch
from subwin.streaming import live

SF = "/root/testdata/sf0.001"


def closed_form(n, k):
    sizes, at, cap, level = [], n, k, 0
    while at > 0:
        moved = max(0, (at - cap) // 2)
        sizes = [1 << level] * (at - 2 * moved) + sizes
        at, cap, level = moved, -(-k // 2), level + 1
    return sizes


@pytest.mark.parametrize("k", [1, 2, 3, 7, 20, 50])
def test_closed_form_is_the_simulation(k):
    for n in range(0, 700, 7):
        assert closed_form(n, k) == eh.insert_counts(n, k)
        assert eh.invariant_count(closed_form(n, k), k)


@pytest.mark.parametrize("k", [2, 7, 20])
def test_layout(spark, k):
    sizes = [1, 2, 5, 40, 333]
    samples = spark.createDataFrame([(f"s{n}", i * 10, i, float(i), "x") for n in sizes for i in range(1, n + 1)], "series string, t long, seq long, value double, item string")
    spans = eh.bucket_spans(eh.layout_count(samples, k)).collect()
    for n in sizes:
        own = sorted((x.bucket, x.seq_lo, x.seq_hi, x.size) for x in spans if x.series == f"s{n}")
        assert [x[3] for x in own] == closed_form(n, k)
        assert [x[1] for x in own][1:] == [x[2] + 1 for x in own][:-1] and own[0][1] == 1 and own[-1][2] == n


def test_streamed_inserts_are_the_closed_form():
    for k in (2, 5, 20):
        sizes, starts = [], []
        for n in range(1, 400):
            sizes.append(1)
            starts.append(n)
            live.insert(sizes, starts, k)
            assert sizes == closed_form(n, k)
            assert starts[0] == 1 and all(b - a == s for a, b, s in zip(starts, [*starts[1:], n + 1], sizes))


def test_fold_keeps_its_invariants():
    r = random.Random(1)
    weight = lambda c: float(sum(x * x for x in c.values()))
    merge = lambda a, b: {x: a.get(x, 0) + b.get(x, 0) for x in {*a, *b}}
    panes = [{r.randrange(30): r.randrange(1, 5) for _ in range(10)} for _ in range(200)]
    for k in (4, 20):
        fold = eh.Fold(k, weight, merge)
        for i, pane in enumerate(panes):
            fold.add(i, pane)
            newer = 0.0
            for lo, hi, summary, w in reversed(fold.buckets):
                assert w == weight(summary)
                assert lo == hi or w <= 2 * newer / k + 1e-9
                newer += w
        assert [b[0] for b in fold.buckets][1:] == [b[1] + 1 for b in fold.buckets][:-1]
        assert len(fold.buckets) < 200
        fold.expire(150)
        assert all(b[1] >= 150 for b in fold.buckets)
    assert eh.weakly_additive(weight, merge, [(r.choice(panes), r.choice(panes)) for _ in range(200)], 2.0)


def test_quantiles_within_bounds(spark):
    samples = series_view(spark, SF, "li_all")
    ranges = eh.fractions_of(samples, eh.CUTS)
    found = kll.judged(samples, kll.answer(samples, kll.build(samples), ranges, [0.0, 0.5, 0.9, 1.0]), ranges).collect()
    assert len(found) == 4 * len(eh.CUTS) and all(x.within_bound for x in found)


def test_sub_bucket_range_falls_back(spark):
    samples = series_view(spark, SF, "li_all")
    ranges = spark.createDataFrame([("tiny", "all", 3, 5), ("empty", "all", 5, 5), ("newest", "all", 5990, 6000)], "query string, series string, low long, high long")
    found = {x["query"]: x for x in kll.answer(samples, kll.build(samples, 4), ranges, [0.5]).collect()}
    assert found["tiny"].source == "exact" and found["tiny"].samples == 2
    assert found["newest"].source == "cache" and "empty" not in found


def test_narrow_policies(spark):
    samples = series_view(spark, SF, "li_all")
    ranges = spark.createDataFrame([("tiny", "all", 3, 5)], "query string, series string, low long, high long")
    buckets = kll.build(samples, 4)
    assert kll.answer(samples, buckets, ranges, [0.5], "null").count() == 0
    found = kll.answer(samples, buckets, ranges, [0.5], "bucket").collect()
    assert [x.source for x in found] == ["bucket"] and found[0].samples == buckets.where("bucket = 1").first().size


def test_tractable_sums():
    import math

    assert univ.tractable(lambda x: 1.0) and univ.tractable(lambda x: float(x)) and univ.tractable(lambda x: x * math.log(x + 1)) and univ.tractable(lambda x: float(x * x))
    assert not univ.tractable(lambda x: float(x**4)) and not univ.tractable(lambda x: 1 / x**3)


def test_heavy_hitters(spark):
    samples = series_view(spark, SF, "ev_type")
    freq = univ.frequencies(samples)
    cells = univ.sketch_cells(freq, univ.LARGE, "series")
    estimates = univ.point_estimates(cells, freq.select("series", F.lit(0).alias("layer"), "item", "h"), univ.LARGE, "series")
    found = {(x.series, x.item) for x in univ.heavy_hitters(estimates, univ.l2_of_cells(cells, "series"), 0.05, "series").collect()}
    norms = {x.series: x.n for x in freq.groupBy("series").agg(F.sqrt(F.sum(F.col("f") * F.col("f"))).alias("n")).collect()}
    assert {(x.series, x.item) for x in freq.collect() if x.f >= 0.06 * norms[x.series]} <= found


def test_nulls_and_ties(spark):
    samples = spark.createDataFrame([("a", 5, i, None if i % 3 == 0 else 1.0, None if i % 2 else "x") for i in range(1, 31)], "series string, t long, seq long, value double, item string")
    assert kll.build(samples, 4).agg(F.sum("size")).first()[0] == 20
    assert univ.frequencies(samples).collect()[0].f == 15
    assert kll.build(samples.limit(0), 4).count() == 0


def test_sketches_are_linear(spark):
    samples = series_view(spark, SF, "ev_type")
    whole = univ.sketch_cells(univ.frequencies(samples), univ.SMALL, "series")
    halves = univ.sketch_cells(univ.frequencies(samples.withColumn("half", F.col("seq") % 2), "half"), univ.SMALL, "series", "half")
    merged = univ.merge_cells(halves, "series").where("c <> 0")
    assert sorted(map(tuple, whole.where("c <> 0").collect())) == sorted(map(tuple, merged.collect()))


def test_gsum_is_exact_when_all_items_are_heavy(spark):
    samples = series_view(spark, SF, "ev_type").where("series = 'click'")
    freq = univ.frequencies(samples)
    level = F.explode(F.sequence(F.lit(0), F.expr(univ._depth(len(univ.SMALL.widths))))).alias("layer")
    estimates = freq.select("series", level, "item", "h", F.col("f").cast("double").alias("est"))
    found = univ.gsum(estimates, univ.SMALL, "series").first()
    counts = [x.f for x in freq.collect()]
    assert found["distinct"] == len(counts) and found["count"] == sum(counts) and found["l2sq"] == sum(c * c for c in counts)


def test_maps_only_are_exact_over_their_buckets(spark):
    samples = series_view(spark, SF, "ev_type")
    ranges = eh.fractions_of(samples, [("full", 1.0, 0.0)])
    buckets = univ.build(samples, 20)
    assert buckets.cells.count() == 0 and buckets.heavy.count() == 0
    found = {x.series: x for x in univ.query(buckets, ranges).collect()}
    for x in univ.exact_statistics(samples, ranges).collect():
        got = found[x.series]
        assert got.forms == "map" and got.n == x.n and got.distinct == x.distinct and got.entropy == pytest.approx(x.entropy) and got.l2 == pytest.approx(x.l2)


def test_smooth_histogram_subtracts(spark):
    samples = series_view(spark, SF, "ev_type")
    found = smooth.query_range(smooth.build(samples, 10), eh.fractions_of(samples, [("full", 1.0, 0.0)])).collect()
    assert {(x.series, x.n) for x in found} == {(x.series, x["count"]) for x in samples.groupBy("series").count().collect()}


def test_sampling_ratio_and_reservoir(spark):
    samples = synthetic(spark, "uniform", 4, 5000)
    assert sampling.build(samples, 0.1).count() == pytest.approx(2000, rel=0.1)
    assert {x["count"] for x in sampling.reservoir(samples, 50).groupBy("series").count().collect()} == {50}
    assert sampling.expire(samples, 1 << 60, 10).count() == 0


def test_rivals_keep_heavy_items():
    r = random.Random(2)
    stream = ["hot"] * 300 + [f"i{r.randrange(400)}" for _ in range(2000)]
    r.shuffle(stream)
    for sketch in (baselines.SpaceSaving(60), baselines.GuardedBuckets(8)):
        for item in stream:
            sketch.add(item)
        assert max(sketch.counts, key=sketch.counts.get) == "hot"


def test_parser():
    node = rules.parse('quantile_over_time(0.9, ev_type{series=~"a|b"}[5d]) * 2 > 3')
    assert node.op == ">" and node.left.op == "*" and rules.leaf(node) == rules.OverTime("quantile", 0.9, "ev_type", (("series", "=~", "a|b"),), 5 * DAY)
    assert rules.parse("1 + 2 * 3 - (4 - 1)") == 4.0 and rules.parse("max_over_time(a[1d]) + 2 * 3").right == 6.0
    assert rules.parse("avg_over_time(max(ev_type)[10s])").inner == "max"
    for wrong in ("max_over_time(ev_type)", "max_over_time(ev_type[5d]) >", "nothing", "max_over_time(ev_type[5d]) ) ", "max_over_time(ev_type[5d]) ?"):
        with pytest.raises(ValueError):
            rules.parse(wrong)


def test_registry():
    registry = rules.Registry.of(rules.RULES)
    assert registry.windows["ev_type", "kll"] == 10 * DAY
    assert registry.route(rules.leaf(rules.parse("last_over_time(ev_type[1d])"))) == "exact"
    assert registry.route(rules.leaf(rules.parse("max_over_time(ev_type[11d])"))) == "exact"
    assert registry.sync([]) and not registry.windows


def test_record_is_idempotent(spark):
    path = Scratch(spark, "test").root + "/record"
    results = spark.createDataFrame([("a", 1, 2.0), ("a", 2, 3.0)], "series string, eval_t long, result double")
    for _ in range(3):
        rules.record(results, "r", path)
    assert rules.record(results, "other", path).groupBy("rule").count().count() == 2
    assert spark.read.parquet(path).count() == 4


def test_bounds_and_prices():
    assert metrics.kll_suffix_bound(50, 0.01) == pytest.approx(0.05)
    assert metrics.kll_range_bound(50, 0.01, 1000, 500) == pytest.approx(0.09)
    assert metrics.total_variation_bound(0, 0, 10) == 0 and metrics.total_variation_bound(5, 2, 10) == pytest.approx(1 / 3)
    assert metrics.per_sample_price(268e9) == pytest.approx(26.8)
    assert metrics.ingestion_price(2e7, [(1e7, 1.0), (1e9, 0.5)]) == pytest.approx(1.5)
    assert metrics.instance_price(200, [(64, 1.0), (256, 3.0), (1024, 9.0)]) == 3.0
    assert metrics.kll_bits(0.02, 0.01, 0.01, 10**6) > 0 and metrics.univ_bits(0.1, 0.1, 10**6, 10**5) > 0


def test_trends(spark):
    """Memory grows far slower than the window and in proportion to series; uniform items cost more; no error grows with k."""
    windows = sorted((x.window, x.bytes) for x in workloads.memory_by_window(spark, SF).collect())
    assert windows[-1][1] / windows[0][1] < 0.8 * windows[-1][0] / windows[0][0]
    series = {(x.family, x.quarters): x.bytes / x.series for x in workloads.memory_by_series(spark, SF).collect()}
    for family in ("kll", "univ"):
        assert series[family, 4] == pytest.approx(series[family, 1], rel=0.1)
    entries = {x.law: x.entries for x in workloads.uniformity(spark, SF).collect()}
    assert entries["uniform"] > entries["zipf"]


def same(v):
    return round(v, 6) if isinstance(v, float) else v if isinstance(v, (int, str, bool, type(None))) else str(v)


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    con.sql("SET timezone = 'UTC'")
    for name in relational.TABLES:
        path = f"{SF}/{name}.parquet"
        con.sql(f"CREATE VIEW {name} AS SELECT * FROM read_parquet('{path + '/*.parquet' if os.path.isdir(path) else path}')")
    return con


CHECKED = sorted({*relational.QUERIES, *exact.QUERIES, *eh.QUERIES, *sampling.QUERIES, *baselines.QUERIES, *rules.QUERIES, "ehkll_quantile_events", "ehkll_rank", "univ_cells_deepest", "cs_l2", "cs_point", "gsum_exact", "sh_suffix_difference", "udtf_layout", "source_python", "stream_eh_state", "stream_dedup", "stream_ingest_rebuild"} & set(catalog.SQL))


@pytest.mark.parametrize("name", CHECKED)
def test_query_equals_its_sql(spark, duck, name):
    found = catalog.QUERIES[name](spark, SF)
    wanted = duck.sql(catalog.SQL[name])
    assert sorted(found.columns) == sorted(wanted.columns)
    order = lambda names: sorted(range(len(names)), key=lambda i: names[i])
    a, b = order(found.columns), order(wanted.columns)
    assert sorted(([same(r[i]) for i in a] for r in found.collect()), key=repr) == sorted(([same(r[i]) for i in b] for r in wanted.fetchall()), key=repr)


def test_plans(spark):
    """No nested-loop join and no Python over samples on the cache's main paths; filters reach the scan."""
    for name in ("ehkll_drilldown_lines", "sample_avg", "univ_cells"):
        plan = catalog.QUERIES[name](spark, SF)._jdf.queryExecution().executedPlan().toString()
        assert "NestedLoop" not in plan and "Cartesian" not in plan and "Python" not in plan and "InPandas" not in plan
    assert "PushedFilters: [IsNotNull(ts)" in catalog.QUERIES["scan_parquet_prune"](spark, SF)._jdf.queryExecution().explainString(spark._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))

"""What the cache may answer, and what it must not."""

from dataclasses import replace

import pytest
from pyspark.sql import functions as F

from subwin.functions.exact import Grid
from subwin.operators import eh, kll, univ
from subwin.plans import cache, rules
from subwin.storage import Scratch
from subwin.streaming import live

NOW = 2_000_000


@pytest.fixture(scope="module")
def samples(spark):
    """One series of 2000 values in order, a second one of the newer half only."""
    rows = [("a", i * 1000, i, float(i), f"u{i % 37}") for i in range(1, 2001)] + [("b", i * 1000, i - 1000, float(i), f"u{i % 5}") for i in range(1001, 2001)]
    return Scratch(spark, "test").save(spark.createDataFrame(rows, "series string, t long, seq long, value double, item string"), "samples")


def newer_half(samples):
    placed = samples.where("t > 1000000").withColumn("seq", F.expr("CASE series WHEN 'a' THEN seq - 1000 ELSE seq END"))
    return placed.withColumn("n", F.lit(1000).cast("long"))


@pytest.fixture()
def store(spark, samples):
    store = cache.CacheStore(spark, Scratch(spark, "test").root)
    half = newer_half(samples)
    for family in ("kll", "univ", "sample"):
        store.commit("v", family, cache.summaries(family, half, cache.Sizes(k_eh=20, k_univ=20, pane=10)), NOW // 2, NOW)
    return store


def test_ranges_beyond_what_is_stored_are_exact(spark, samples, store):
    """A median of all samples, asked of a cache of the newer half, is that of all samples."""
    ranges = spark.createDataFrame([("all", "a", 0, NOW), ("new", "a", 1_200_000, NOW)], "query string, series string, low long, high long")
    wide = rules.Registry({("v", "kll"): NOW})
    for registry, source in ((wide, "cache"), (rules.Registry({("v", "kll"): 1}), "exact"), (rules.Registry({}), "exact"), (rules.Registry({("other", "kll"): NOW}), "exact")):
        got = {x["query"]: x for x in cache.run(samples, store, registry, "v", ranges, [0.5], by="t").collect()}
        assert got["all"].source == "exact" and got["all"].estimate == 1000.5
        assert got["new"].source == source and abs(got["new"].estimate - 1600.5) <= 800 * (got["new"].bound + 2 * kll.sketch_error(256))
    assert cache.run(samples, store, rules.Registry({("other", "kll"): NOW}), "other", ranges, [0.5], by="t").where("source <> 'exact'").count() == 0


@pytest.mark.parametrize("fn, arg", [("quantile", 0.9), ("max", None), ("avg", None), ("count", None), ("distinct", None), ("entropy", None), ("l2", None), ("topk", 3)])
def test_points_are_hits_only_where_covered(samples, store, fn, arg):
    """Points whose window starts before the cache, ends after it, or is wider than registered are exact."""
    grid = Grid(1_000_000, 2_200_000, 200_000, 400_000)
    node = rules.OverTime(fn, arg, "v", (), 400_000)
    exact = {(x.series, x.eval_t, x["item"] if fn == "topk" else None): x.result for x in rules.evaluate(node, samples, grid).collect()}
    for width, hits in ((1_000_000, {1_400_000, 1_600_000, 1_800_000, 2_000_000}), (700_000, {1_800_000, 2_000_000}), (399_999, set())):
        registry = rules.Registry({("v", rules.FAMILIES[fn]): width})
        found = cache.evaluate_cached(node, lambda view: samples, store, registry, grid, cache.Sizes(k_eh=20, k_univ=20, pane=10)).collect()
        assert {x.eval_t for x in found if x.source == "cache"} == hits
        assert {(x.series, x.eval_t) for x in found} == {(s, e) for s, e, _ in exact}
        for x in found:
            if x.source == "exact":
                assert x.bound == 0 and x.result == pytest.approx(exact[x.series, x.eval_t, x["item"] if fn == "topk" else None])
            elif fn in ("quantile", "max", "avg", "distinct", "entropy"):
                assert x.result == pytest.approx(exact[x.series, x.eval_t, None], rel=0.1)


def test_windows_inside_a_bucket_are_exact(samples, store):
    """A window that lies in one bucket takes none: the samples answer, and a window without samples has no answer."""
    grid = Grid(1_010_000, 1_010_000, 1, 3_000)
    node = rules.OverTime("quantile", 0.5, "v", (("series", "=", "a"),), 3_000)
    registry = rules.Registry({("v", "kll"): 1_000_000})
    inside = [replace(grid, start=t, end=t) for t in (1_004_000, 1_006_000, 1_007_500)]
    for one in inside:
        found = cache.evaluate_cached(node, lambda view: samples, store, registry, one).collect()
        want = rules.evaluate(node, samples, one).collect()
        assert len(found) == len(want) == 1 and (found[0].source == "cache" or found[0].result == want[0].result)
    assert any(cache.evaluate_cached(node, lambda view: samples, store, registry, one).first().source == "exact" for one in inside)


def test_versions_sync_and_vacuum(spark, samples, store):
    store.commit("v", "kll", {"buckets": kll.build(samples, 4)}, 0, NOW)
    assert store.versions("v", "kll") == [1, 2] and store.read("v", "kll").low == 0
    assert store.vacuum("v", "kll") == 1 and store.versions("v", "kll") == [2]
    registry = rules.Registry({("v", "kll"): NOW, ("v", "univ"): NOW})
    assert cache.sync(store, registry, [rules.RuleSpec("q", "record", 1, "max_over_time(v[1d])")]) == [("v", "univ")]
    assert store.read("v", "univ") is None and store.read("v", "kll") is not None


def test_operations_on_cached_results(samples, store):
    grid = Grid(1_400_000, 2_000_000, 200_000, 1)
    registry = rules.Registry({("v", "kll"): 1_000_000})
    node = rules.Binary("-", rules.OverTime("max", None, "v", (), 400_000), rules.OverTime("last", None, "v", (), 400_000))
    found = cache.evaluate_cached(node, lambda view: samples, store, registry, grid).collect()
    assert found and all(x.source == "mixed" and abs(x.result) <= 200 for x in found)


def test_sketch_buckets_store_no_items(spark, samples):
    """Of a sketch, cells and at most the configured heavy items of a layer are stored; the map rows belong to maps."""
    config = univ.Config([64] * 4, 3, 5)
    stored = univ.build(samples, 20, 10, config, map_bytes=20 * univ.ENTRY_BYTES)
    forms = {(x.series, x.bucket): x.form for x in stored.spans.collect()}
    assert {"map", "sketch"} == set(forms.values())
    assert {(x.series, x.bucket) for x in stored.maps.collect()} == {k for k, form in forms.items() if form == "map"}
    assert {(x.series, x.bucket) for x in stored.cells.collect()} == {k for k, form in forms.items() if form == "sketch"}
    assert stored.heavy.groupBy("series", "bucket", "layer").count().agg(F.max("count")).first()[0] <= config.heavy
    assert stored.cells.groupBy("series", "bucket").count().agg(F.max("count")).first()[0] <= config.cells


def test_layout_joins_samples_with_nothing(spark):
    """With n given, the layout is arithmetic in one stage; without, it is a join by series only."""
    counted = spark.createDataFrame([("a", 1, 5), ("a", 2, 5)], "series string, seq long, n long")
    plan = eh.layout_count(counted, 4)._jdf.queryExecution().optimizedPlan().toString()
    assert "Join" not in plan and "Aggregate" not in plan


@pytest.mark.parametrize("k", [3, 20])
def test_advance_is_the_whole_layout(spark, k):
    """Batches of any size, of series that come and go, give the layout of all samples at once, less what has expired."""
    rows = [(s, t, float(t % 91), t) for s, step in (("a", 1), ("b", 3)) for t in range(step, 700, step)] + [("c", t, 1.0, t) for t in range(300, 310)]
    frame = spark.createDataFrame(rows, "series string, t long, value double, id long")
    held = None
    scratch = Scratch(spark, "test")
    for i, (low, high) in enumerate(((0, 10), (10, 11), (11, 400), (400, 699))):
        held = scratch.save(live.advance(held, frame.where((F.col("t") > low) & (F.col("t") <= high)), k, 64, high - 450), f"v{i}")
    got = {(x.series, x.bucket): (x.t_lo, x.t_hi, x.size) for x in held.collect()}
    want = {}
    for s in "abc":
        own = sorted(t for x, t, *_ in rows if x == s)
        at = 0
        for b, size in enumerate(eh.insert_counts(len(own), k)):
            part = own[at : at + size]
            at += size
            if part[-1] > 699 - 450:
                want[s, b + 1] = (part[0], part[-1], size)
    assert got == want

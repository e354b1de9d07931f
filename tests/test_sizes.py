"""Queries on more or other rows than the given tables have."""

from collections import Counter

import pytest
from pyspark.sql import functions as F

from subwin.operators import baselines, kll, relational, sampling, univ
from subwin.operators.eh import in_range
from subwin.storage import Scratch
from subwin.streaming import live


@pytest.mark.parametrize("fn, result", [("stddev", 1000.0), ("stdvar", 1000000.0)])
def test_squares_do_not_overflow(spark, fn, result):
    """Eight values whose squared hundredths sum up to more than a long holds."""
    kept = spark.range(8).selectExpr("'a' AS series", "id + 1 AS seq", "15000000.0D + IF(id % 2 = 0, 1000.0D, -1000.0D) AS value")
    ranges = spark.createDataFrame([("all", "a", 0, 8)], "query string, series string, low long, high long")
    assert sampling.query(kept, ranges, fn, 1.0).first()["estimate"] == result


EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def _events(spark, folder, rows):
    """rows of (event_id, microseconds from 2024 on, event_type, value)"""
    frame = spark.createDataFrame(rows, "event_id long, at long, event_type string, value double")
    ts = "cast(timestamp_micros(1704067200000000 + at) AS timestamp_ntz) AS ts"
    frame.selectExpr("event_id", ts, "event_id % 3 AS user_id", "event_type", "value", "'{\"k\": 1}' AS props").write.parquet(f"{folder}/events.parquet")
    return str(folder)


def test_late_reject_by_time_and_id(spark, tmp_path):
    """Equal times of different ids and ids out of the order of time: all are taken once, only repeats are rejected."""
    rows = [(i * 1000 + j, j // 2 * 7_000_000, "a", 1.0) for i in range(2) for j in range(400)]
    found = live.rejected(spark, _events(spark, tmp_path, rows)).first()
    assert (found["taken"], found["rejected"]) == (800, sum(e % 100 == 7 for e, *_ in rows))


def test_range_frame_at_its_edges(spark, tmp_path):
    """Frames reach back a day, both ends and equal times included, over panes and gaps, also before 1970; nulls are skipped."""
    day = 86_400_000_000
    at = [0, 0, 1, day - 1, day, day, day + 1, 2 * day + 1, 5 * day, -60 * 366 * day, -60 * 366 * day + day]
    rows = [(i, t, "a" if i % 4 else "b", None if i == 4 else float(i)) for i, t in enumerate(at)]
    folder = _events(spark, tmp_path, rows)
    plain = relational._run(relational.QUERY["win_range_frame"])(spark, folder)
    found = relational.QUERIES["win_range_frame"](spark, folder)
    assert found.schema == plain.schema or found.dtypes == plain.dtypes
    assert sorted(found.collect(), key=str) == sorted(plain.collect(), key=str)


def test_spacesaving_until_certain(spark):
    """More near-even items than counters: the best are still the true ones, and few counters do where they are clear."""
    items = [i * 7919 % 900 for i in range(3000)] + [880, 881, 882]
    samples = spark.createDataFrame([("a", i + 1, f"u{x:03}") for i, x in enumerate(items)], "series string, seq long, item string")
    found = baselines.fixed_window_topk(samples, {"all": 1.0}, 3, m=20, certain=True).collect()
    true = sorted(Counter(f"u{x:03}" for x in items).items(), key=lambda x: (-x[1], x[0]))[:3]
    assert [(r["item"], r["est"]) for r in found] == true
    few = baselines.SpaceSaving(3)
    for x in "abacabdaeabf":
        few.add(x)
    assert few.certain(1) and not few.certain(2)


def test_spacesaving_takes_over_the_least():
    """The counters are those of the plain definition: the least count goes, of equal ones the least item."""
    kept, plain = baselines.SpaceSaving(5), {}
    for i in range(2000):
        item = f"u{i * i * 31 % 97 % (3 + i % 17)}"
        kept.add(item)
        if item not in plain and len(plain) == 5:
            least = min(plain, key=lambda x: (plain[x], x))
            plain[item] = plain.pop(least)
        plain[item] = plain.get(item, 0) + 1
    assert kept.counts == plain


@pytest.mark.parametrize("near", [0.001, 0.0])
def test_judged_without_maps_of_values(spark, monkeypatch, near):
    """Exact quantiles come from the values near them, not from a map of all values; brackets that miss are opened."""
    monkeypatch.setattr(kll, "NEAR", near)
    value = "CASE WHEN id % 50 = 0 THEN NULL WHEN id % 3 = 0 THEN 7.5D ELSE (id * 7919 % 2003) / 8.0D END AS value"
    samples = spark.range(3000).selectExpr("concat('s', id % 2) AS series", "id div 2 + 1 AS seq", "id AS t", value)
    ranges = spark.createDataFrame([(q, s, a, b) for s in ("s0", "s1") for q, a, b in (("all", 0, 1500), ("part", 400, 901), ("one", 1, 2))], "query string, series string, low long, high long")
    asked = ranges.select("query", "series", F.explode(F.array(*map(F.lit, kll.POINTS))).alias("phi")).selectExpr("*", "100.0D * phi AS estimate", "0.0D AS bound")
    found = kll.judged(samples, asked, ranges)
    assert "percentile(value" not in found._jdf.queryExecution().toString()
    inside = in_range(samples, ranges).join(asked, ["query", "series"])
    plain = inside.groupBy("query", "series", "phi").agg(F.expr(f"percentile(value, array({', '.join(f'{p}D' for p in kll.POINTS)}))").alias("p"), F.count("*").alias("n"), F.expr("count_if(value < estimate)").alias("below"), F.expr("count_if(value <= estimate)").alias("upto"))
    true = {(r["query"], r["series"], r["phi"]): (r["n"], r["below"], r["upto"], r["p"] and round(r["p"][kll.POINTS.index(r["phi"])], 6)) for r in plain.collect()}
    assert {(r["query"], r["series"], r["phi"]): (r["n"], r["below"], r["upto"], r["exact"]) for r in found.collect()} == true


def test_judged_ranks_alone(spark):
    samples = spark.range(100).selectExpr("'a' AS series", "id + 1 AS seq", "id AS t", "cast(id AS double) AS value")
    ranges = spark.createDataFrame([("all", "a", 0, 100)], "query string, series string, low long, high long")
    asked = ranges.selectExpr("query", "series", "0.5D AS phi", "59.0D AS estimate", "0.0D AS bound")
    found = kll.judged(samples, asked, ranges, exact=False).first()
    assert (found["n"], found["below"], found["upto"], round(found["rank_error"], 9)) == (100, 59, 60, 0.09) and "exact" not in found


def test_distinct_of_many_more_items_than_are_heavy(spark):
    """Sketches keep 100 items of a layer; the distinct ones of 30,000 come from the layers that are whole in each bucket."""
    config = univ.Config([256] * 8 + [64] * 8, 3, 100)
    samples = spark.range(60_000).selectExpr("'a' AS series", "id + 1 AS seq", "id AS t", "concat('u', id * 7919 % 30011) AS item")
    ranges = spark.createDataFrame([("full", "a", 0, 60_000), ("late", "a", 40_000, 60_000)], "query string, series string, low long, high long")
    # with maps, the newer buckets are maps of more items than a sketch keeps
    for kind in (False, True):
        stored = univ.build(samples, 500, 10, config, hybrid=kind, map_bytes=1500 * univ.ENTRY_BYTES).saved(Scratch(spark, "test"))
        taken = {x.query: x.distinct for x in univ.exact_statistics(samples, _aligned(stored, ranges)).collect()}
        for x in univ.query(stored, ranges, config).collect():
            assert x.forms == ("sketch" if not kind else "mixed" if x.query == "full" else "map") and abs(x.distinct - taken[x.query]) <= 0.05 * taken[x.query], (kind, x, taken)


@pytest.mark.parametrize("entries", [700, 2200], ids=["smallest_are_maps", "most_are_maps"])
def test_distinct_of_maps_beside_sketches(spark, entries):
    """As in ehuniv_mixed_tokens and ehuniv_hybrid_tokens: a range of sketches that keep 100 items of a layer, and of exact maps."""
    config = univ.Config([256] * 8 + [64] * 8, 3, 100)
    samples = spark.range(60_000).selectExpr("'a' AS series", "id + 1 AS seq", "id AS t", "concat('u', id * 7919 % 30011) AS item")
    ranges = spark.createDataFrame([("full", "a", 0, 60_000)], "query string, series string, low long, high long")
    stored = univ.build(samples, 500, 10, config, map_bytes=entries * univ.ENTRY_BYTES).saved(Scratch(spark, "test"))
    found = univ.query(stored, ranges, config).first()
    assert (found.forms, found.n) == ("mixed", 60_000) and abs(found.distinct - 30_011) <= 0.05 * 30_011


def _aligned(stored, ranges):
    """The ranges of positions that the buckets of ``ranges`` cover."""
    return in_range(stored.spans, ranges, "seq_lo").groupBy("query", "series").agg((F.min("seq_lo") - 1).alias("low"), F.max("seq_hi").alias("high"))


def test_distinct_where_no_layer_is_whole(spark):
    """With all layers cut, the estimate of the sums over layers stays."""
    config = univ.Config([256] * 2, 3, 20)
    samples = spark.range(2000).selectExpr("'a' AS series", "id + 1 AS seq", "id AS t", "concat('u', id) AS item")
    ranges = spark.createDataFrame([("full", "a", 0, 2000)], "query string, series string, low long, high long")
    stored = univ.build(samples, 500, 10, config, hybrid=False).saved(Scratch(spark, "test"))
    found = univ.query(stored, ranges, config).first()
    _, _, summed, candidates = univ.merged(stored, ranges, config)
    sums = univ.gsum(univ.point_estimates(summed, candidates, config, "query", "series"), config, "query", "series").first()
    assert found.distinct == sums["distinct"]

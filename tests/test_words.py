import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from subwin.operators import eh, sampling, univ
from subwin.operators.eh import cut_runs, in_range
from subwin.sources.views import samples_of, series_view, written_words
from subwin.storage import Scratch

TEXTS = [(i * 7 % 40, " ".join(f"W{i * j % 23}" for j in range(1 + i * 5 % 17)), "en" if i % 3 else "de") for i in range(40)]


def _documents(spark, path, texts):
    spark.createDataFrame(texts, "doc_id long, text string, lang string").repartition(3).write.parquet(f"{path}/documents.parquet")
    return str(path)


def test_words_have_their_positions(spark, tmp_path):
    """Runs written in order hold the samples of the view, also of two texts of one id, an empty one and a null."""
    at = _documents(spark, tmp_path, [*TEXTS, (50, "", "en"), (51, None, "en"), (52, "x y z", None), (7, "w1 w2 w3 w4 w5 w6 w7 w8 w9", "en")])
    for name in ("doc_tokens", "doc_tokens_lang"):
        runs = written_words(spark, at, name)
        assert "Exchange hashpartitioning" not in runs._jdf.queryExecution().executedPlan().toString()
        found, true = (sorted(x.select("series", "t", "seq", "n", F.col("item") if name == "doc_tokens_lang" else "value").collect()) for x in (samples_of(runs), series_view(spark, at, name, counted=True)))
        # ties of id and position may stand either way
        assert [x[:4] for x in found] == [x[:4] for x in true] and sorted(x[4] for x in found) == sorted(x[4] for x in true)


def test_cut_runs_meet_each_sample_once(spark, tmp_path):
    runs = written_words(spark, _documents(spark, tmp_path, TEXTS))
    spans = spark.createDataFrame([("all", a, b, i) for i, (a, b) in enumerate([(0, 1), (1, 40), (40, 43), (43, 400), (10, 90)])], "series string, low long, high long, span int")
    got = cut_runs(runs, spans, 16).select("span", F.col("seq").alias("at"), F.posexplode("items").alias("nth", "item")).selectExpr("span", "at + nth AS seq", "item")
    true = in_range(samples_of(runs), spans.withColumn("query", F.col("span"))).select("span", "seq", "item")
    assert sorted(got.collect()) == sorted(true.collect())


def test_layout_and_sketches_without_moving_words(spark, tmp_path):
    """The fold over summaries made where the words are gives the buckets of a plain fold; cells and heavy items are those of the counts."""
    runs = written_words(spark, _documents(spark, tmp_path, TEXTS))
    items = [x.item for x in samples_of(runs).orderBy("seq").collect()]
    folded = eh.Fold(4, univ._median_square, np.add)
    for pane in range(0, len(items), 5):
        summary = np.zeros(3 * univ.PANE_CELLS)
        for x in items[pane : pane + 5]:
            h = univ._hashes(pa.array([x]))
            for r in range(3):
                summary[r * univ.PANE_CELLS + univ._places(h, r, univ.PANE_CELLS)] += univ._signs(h, r)
        folded.add(pane // 5, summary)
    layout = univ.bucket_layout(runs, 5, 4)
    assert [(x.pane_lo, x.pane_hi, x.weight) for x in layout.orderBy("bucket").collect()] == [(a, b, w) for a, b, _, w in folded.buckets]
    config = univ.Config([64] * 3 + [16] * 2, 3, 4)
    counts = univ.count(runs, 5, 4)
    stored = univ.formed(counts, config, hybrid=False).saved(Scratch(spark, "test"))
    keys = ["series", "bucket", "layer"]
    cells = univ.sketch_cells(counts.freq, config, "series", "bucket")
    assert sorted(map(tuple, stored.cells.collect())) == sorted(map(tuple, cells.select(stored.cells.columns).collect()))
    nth = F.row_number().over(univ.Window.partitionBy(*keys).orderBy(F.desc("f"), "item"))
    heavy = counts.freq.select("series", "bucket", "item", "f", univ._layers(config)).withColumn("nth", nth).where("nth <= 4").select(*keys, "item")
    assert sorted(stored.heavy.select(*keys, "item").collect()) == sorted(heavy.collect())


def test_overlapping_ranges_meet_samples_once(spark):
    """Means of overlapping ranges come from sums by the pieces of the ranges, each sample in one; a gap is in none."""
    rows = [("a", i + 1, float(i * 37 % 101) / 4) for i in range(3000)]
    samples = spark.createDataFrame(rows, "series string, seq long, value double")
    cuts = {"x": (0, 3000), "y": (100, 2000), "z": (1500, 2999), "none": (7, 7)}
    ranges = spark.createDataFrame([(q, "a", a, b) for q, (a, b) in cuts.items()], "query string, series string, low long, high long")
    pieces = eh.segments(ranges.where("query <> 'x'")).select("low", "high").distinct().collect()
    assert sorted(map(tuple, pieces)) == [(100, 1500), (1500, 2000), (2000, 2999)]
    kept = {x.seq for x in sampling.build(samples, 0.5).collect()}
    found = {x.query: x for x in sampling.sweep(samples, ranges, [0.5]).collect()}
    assert sorted(found) == ["x", "y", "z"]
    for q, x in found.items():
        inside = [(s, v) for _, s, v in rows if cuts[q][0] < s <= cuts[q][1]]
        drawn = [v for s, v in inside if s in kept]
        error = abs(sum(drawn) / len(drawn) / (sum(v for _, v in inside) / len(inside)) - 1)
        assert x.m == len(drawn) and abs(x.relative_error - error) < 2e-6

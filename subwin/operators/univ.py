"""Frequency statistics over sub-windows: an exponential histogram by squared L2 norm whose buckets hold
exact counts while few items are in them, and universal sketches beyond.

A universal sketch is a stack of Count Sketches; layer j counts the items whose depth hash ends in j zero
bits. Any sum of g(count) over the items is put together from the heavy items of the layers. All hashes are
modular, of the first 28 bits of an item's MD5, so that another engine makes the same cells.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass, field, fields

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from subwin.operators.eh import CUTS, cut_runs, fractions_of, fractions_sql, in_range, layout_weight, segments
from subwin.sources.views import VIEWS, WORDS, runs_of, series_view, written_words
from subwin.storage import Scratch

PRIME = 2_147_483_647
K_EH = 20
#: Bytes of an entry of an exact map (item and count) and of a cell, for the switch from map to sketch.
ENTRY_BYTES, CELL_BYTES = 24, 8
#: Factors and offsets of the row hashes: cell, then sign; and of the depth hash.
ROWS = [(48271, 11), (69621, 101), (16807, 1009), (39373, 10007), (40692, 100003)]
SIGNS = [(742938285, 31), (950706376, 313), (1226874159, 3137), (62089911, 31379), (1343714438, 313781)]
DEPTH = (630360016, 77)


@dataclass(frozen=True)
class Config:
    """Layers of a universal sketch: columns of each, rows of all, heavy items kept of each."""

    widths: list[int] = field(default_factory=lambda: [2048] * 8 + [512] * 8)
    rows: int = 3
    heavy: int = 200

    @property
    def cells(self) -> int:
        return self.rows * sum(self.widths)


LARGE = Config()
MIDDLE = Config([1024] * 8 + [128] * 8)
SMALL = Config([256] * 8 + [64] * 6)
#: For errors of at most five in a hundred, of distinct items too.
FINE = Config([4096] * 8 + [1024] * 8, 5, 1000)

ITEM_HASH = "cast(conv(substr(md5(item), 1, 7), 16, 10) AS bigint)"


def _hash(factor: int, offset: int) -> str:
    return f"((h * {factor} + {offset}) % {PRIME})"


def _depth(layers: int) -> str:
    """Number of low zero bits of the depth hash, at most layers - 1."""
    return "CASE " + " ".join(f"WHEN {_hash(*DEPTH)} % {1 << (j + 1)} <> 0 THEN {j}" for j in range(layers - 1)) + f" ELSE {layers - 1} END"


def frequencies(samples: DataFrame, *keys: str) -> DataFrame:
    """Counts f of items for each series and further keys; partial counts before the shuffle keep hot items cheap."""
    return samples.where("item is not null").groupBy("series", *keys, "item").agg(F.count("*").alias("f")).withColumn("h", F.expr(ITEM_HASH))


def sketch_cells(freq: DataFrame, config: Config, *keys: str, update: str = "all") -> DataFrame:
    """Non-zero cells (keys, layer, row, col, c) of the universal sketches of ``freq``.

    ``update``: "all" writes an item to each layer up to its depth, "deepest" to that of its depth only.
    """
    layers = len(config.widths)
    deep = freq.withColumn("depth", F.expr(_depth(layers)))
    layer = F.explode(F.sequence(F.lit(0), F.col("depth"))) if update == "all" else F.col("depth")
    width = "CASE layer " + " ".join(f"WHEN {j} THEN {w}" for j, w in enumerate(config.widths)) + " END"
    spread = deep.withColumn("layer", layer).withColumn("w", F.expr(width))
    cells = F.array(*[F.struct(F.lit(r).alias("row"), F.expr(f"{_hash(*ROWS[r])} % w").alias("col"), F.expr(f"CASE WHEN {_hash(*SIGNS[r])} % 2 = 0 THEN f ELSE -f END").alias("v")) for r in range(config.rows)])
    return spread.select(*keys, "layer", F.inline(cells)).groupBy(*keys, "layer", "row", "col").agg(F.sum("v").alias("c"))


def merge_cells(cells: DataFrame, *keys: str) -> DataFrame:
    """Sum of sketches: cells are linear."""
    return cells.groupBy(*keys, "layer", "row", "col").agg(F.sum("c").alias("c"))


def l2_of_cells(cells: DataFrame, *keys: str) -> DataFrame:
    """L2 norm from layer 0: the root of the median over rows of the sum of squares."""
    rows = cells.where("layer = 0").groupBy(*keys, "row").agg(F.sum(F.col("c") * F.col("c")).alias("s"))
    return rows.groupBy(*keys).agg(F.sqrt(F.expr("percentile(s, 0.5)")).alias("l2"))


def point_estimates(cells: DataFrame, items: DataFrame, config: Config, *keys: str) -> DataFrame:
    """keys, layer, item, h, est: the median over rows of an item's signed cells, for candidates (keys, layer, item, h)."""
    width = "CASE layer " + " ".join(f"WHEN {j} THEN {w}" for j, w in enumerate(config.widths)) + " END"
    looked = F.array(*[F.struct(F.lit(r).alias("row"), F.expr(f"{_hash(*ROWS[r])} % w").alias("col"), F.expr(f"CASE WHEN {_hash(*SIGNS[r])} % 2 = 0 THEN 1 ELSE -1 END").alias("sign")) for r in range(config.rows)])
    asked = items.withColumn("w", F.expr(width)).select(*keys, "layer", "item", "h", F.inline(looked))
    joined = asked.join(cells, [*keys, "layer", "row", "col"], "left").withColumn("e", F.col("sign") * F.coalesce("c", F.lit(0)))
    return joined.groupBy(*keys, "layer", "item", "h").agg(F.expr("percentile(e, 0.5)").alias("est"))


#: g of a count x, for sums over items.
G = {"distinct": "CASE WHEN x > 0 THEN 1.0D ELSE 0.0D END", "count": "x", "l2sq": "x * x", "flogf": "CASE WHEN x > 0 THEN x * ln(x) ELSE 0.0D END"}


def gsum(estimates: DataFrame, config: Config, *keys: str) -> DataFrame:
    """Sums of every g over the items, by one aggregate over the layers' heavy items.

    Working the recursion out, a heavy item of layer j counts 2 ** j times, less twice that if it lives on
    in layer j + 1, where it counts again; so an item that is heavy all the way down counts once.
    """
    layers = len(config.widths)
    order = Window.partitionBy(*keys, "layer").orderBy(F.desc("est"), "item")
    heavy = estimates.withColumn("nth", F.row_number().over(order)).where((F.col("nth") <= config.heavy) & (F.col("est") > 0.5))
    weight = F.expr(f"shiftleft(1L, layer) * CASE WHEN layer < {layers - 1} AND ({_depth(layers)}) > layer THEN -1 ELSE 1 END")
    x = heavy.withColumn("x", F.round("est")).withColumn("weight", weight)
    return x.groupBy(*keys).agg(*[F.sum(F.col("weight") * F.expr(g)).alias(name) for name, g in G.items()])


def finish(sums: DataFrame, n: Column) -> DataFrame:
    """distinct, entropy and l2 from the sums and the number of samples."""
    return sums.withColumn("entropy", F.log(n) - F.col("flogf") / n).withColumn("l2", F.sqrt(F.greatest(F.col("l2sq"), F.lit(0.0))))


def heavy_hitters(estimates: DataFrame, norms: DataFrame, eps: float, *keys: str) -> DataFrame:
    """Items of layer 0 whose estimate is at least ``eps`` of the L2 norm (keys, l2)."""
    return estimates.where("layer = 0").join(norms, list(keys)).where(F.col("est") >= eps * F.col("l2")).select(*keys, "item", "est")


def tractable(g, n: int = 4096) -> bool:
    """Whether g (a function of a count, g(0) = 0) may be estimated: it grows slower than the square, up to a
    slowly growing factor, falls no faster than slowly, and changes little between near counts."""
    slow = lambda x: 4 * (1 + np.log2(x)) ** 2
    counts = [2**i for i in range(1, int(np.log2(n)) + 1)]
    grows = all(g(y) <= slow(y) * (y / x) ** 2 * g(x) for x in counts for y in counts if y > x)
    falls = all(g(y) * slow(y) >= g(x) for x in counts for y in counts if y > x)
    near = all(g(x + max(1, int(x / slow(x)))) <= 4 * g(x) for x in counts)
    return bool(grows and falls and near)


# -- exponential histogram ---------------------------------------------------------------------------------------------

PANE_CELLS = 512


def _median_square(vector) -> float:
    return float(np.sort(np.square(np.asarray(vector, np.float64).reshape(3, PANE_CELLS)).sum(axis=1))[1])


def _packed(at: np.ndarray, v: np.ndarray) -> bytes:
    """Cells of a pane's sketch: all of them in a byte each, or places and values of those that aren't zero."""
    if 3 * len(at) < PANE_CELLS or abs(v).max() > 127:
        return b"s" + at.astype("<i2").tobytes() + v.astype("<i8").tobytes()
    out = np.zeros(3 * PANE_CELLS, np.int8)
    out[at] = v
    return b"d" + out.tobytes()


def _dense(packed: bytes) -> np.ndarray:
    if packed[:1] == b"d":
        return np.frombuffer(packed, np.int8, offset=1).astype(np.float64)
    n = (len(packed) - 1) // 10
    out = np.zeros(3 * PANE_CELLS)
    out[np.frombuffer(packed, "<i2", n, 1)] = np.frombuffer(packed, "<i8", n, 1 + 2 * n)
    return out


#: Samples of which a task makes summaries at a time.
CHUNK = 1 << 18


def _chunks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    held, rows = [], 0
    for batch in batches:
        held.append(batch)
        rows += len(batch["items"].flatten()) if "items" in batch.schema.names else batch.num_rows
        if rows >= CHUNK:
            yield pa.Table.from_batches(held)
            held, rows = [], 0
    if rows:
        yield pa.Table.from_batches(held)


def _hashes(items: pa.Array) -> np.ndarray:
    return np.fromiter((int(hashlib.md5(x.encode()).hexdigest()[:7], 16) for x in items.to_pylist()), np.int64, len(items))


def _places(h: np.ndarray, row: int, width) -> np.ndarray:
    return (h * ROWS[row][0] + ROWS[row][1]) % PRIME % width


def _signs(h: np.ndarray, row: int) -> np.ndarray:
    return 1 - 2 * ((h * SIGNS[row][0] + SIGNS[row][1]) % PRIME % 2)


def _depths(h: np.ndarray, layers: int) -> np.ndarray:
    x = (h * DEPTH[0] + DEPTH[1]) % PRIME
    x = np.where(x == 0, 1 << 40, x)
    return np.minimum(np.log2(x & -x).astype(np.int64), layers - 1)


def _summaries(size: int):
    """series, pane, summary of runs (series, seq, items): a summary of each pane in a batch, as a sketch is linear."""

    def summarise(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for chunk in _chunks(batches):
            series, items = chunk["series"].combine_chunks().dictionary_encode(), chunk["items"].combine_chunks()
            lens = np.diff(items.offsets.to_numpy())
            code = np.repeat(series.indices.to_numpy().astype(np.int64), lens)
            nth = np.arange(len(code)) - np.repeat(np.cumsum(lens) - lens, lens)
            pane = (np.repeat(chunk["seq"].to_numpy(), lens) + nth - 1) // size
            item = items.flatten().dictionary_encode()
            if item.null_count:
                known = item.is_valid().to_numpy(zero_copy_only=False)
                code, pane, item = code[known], pane[known], item.drop_null()
            if not len(code):
                continue
            order = slice(None)
            if ((np.diff(code) < 0) | ((np.diff(code) == 0) & (np.diff(pane) < 0))).any():
                order = np.lexsort((pane, code))
            starts = np.ones(len(code), bool)
            starts[1:] = (np.diff(code[order]) > 0) | (np.diff(pane[order]) != 0)
            code, pane, words = code[order][starts], pane[order][starts], item.indices.to_numpy()[order]
            group, h = np.cumsum(starts) - 1, _hashes(item.dictionary)
            flat = np.concatenate([group * (3 * PANE_CELLS) + (r * PANE_CELLS + _places(h, r, PANE_CELLS))[words] for r in range(3)])
            sign = np.concatenate([_signs(h, r)[words] for r in range(3)])
            if len(code) * 3 * PANE_CELLS <= 4 * len(flat):
                sums = np.bincount(flat, sign).astype(np.int64)
                cells = np.flatnonzero(sums)
                sums = sums[cells]
            else:
                cells, of = np.unique(flat, return_inverse=True)
                sums = np.bincount(of, sign).astype(np.int64)
            cuts = np.searchsorted(cells, np.arange(len(code) + 1) * (3 * PANE_CELLS))
            at = cells % (3 * PANE_CELLS)
            packed = [_packed(at[i:j], sums[i:j]) if i < j else b"s" for i, j in zip(cuts, cuts[1:])]
            yield pa.RecordBatch.from_arrays([series.dictionary.take(pa.array(code)), pa.array(pane), pa.array(packed, pa.binary())], names=["series", "pane", "summary"])

    return summarise


def bucket_layout(samples: DataFrame, size: int, k: float = K_EH) -> DataFrame:
    """series, bucket, pane_lo, pane_hi, weight: the fold of panes by squared L2.

    Of each pane the fold gets a Count Sketch of fixed size, three rows of PANE_CELLS cells, whose sums give
    the squared L2 of unions. Tasks sum up what they have of a pane; no sample is moved.
    """
    runs = runs_of(samples).select("series", "seq", "items")
    return layout_weight(runs.mapInArrow(_summaries(size), "series string, pane long, summary binary"), k, _median_square, np.add, read=_dense)


@dataclass(frozen=True)
class Buckets:
    """What a histogram stores: spans with form (map or sketch); of maps, item and count f; of sketches, cells, and the heavy items of each layer."""

    spans: DataFrame
    maps: DataFrame
    cells: DataFrame
    heavy: DataFrame

    def tables(self) -> dict[str, DataFrame]:
        return {f.name: getattr(self, f.name) for f in fields(self)}

    def saved(self, scratch: Scratch) -> "Buckets":
        return Buckets(**{name: scratch.save(df, name) for name, df in self.tables().items()})


@dataclass(frozen=True)
class Counts:
    """Buckets before they take a form: spans with size and items, and the counts f of items by bucket."""

    spans: DataFrame
    freq: DataFrame


def count(samples: DataFrame, size: int, k: float = K_EH) -> Counts:
    """Counts by bucket of panes of ``size`` positions, written. What meets the samples, or runs of them, is the small table of
    buckets."""
    scratch = Scratch(samples.sparkSession, "univ")
    layout = scratch.save(bucket_layout(samples, size, k).selectExpr("series", "bucket", f"pane_lo * {size} AS low", f"(pane_hi + 1) * {size} AS high"), "layout")
    placed = cut_runs(runs_of(samples), layout, 256 * size)
    freq = scratch.save(frequencies(placed.select("series", "bucket", F.explode("items").alias("item")), "bucket"), "frequencies")
    spans = placed.groupBy("series", "bucket").agg(F.min("seq").alias("seq_lo"), F.expr("max(seq + len - 1) AS seq_hi"), F.min("t").alias("t_lo"), F.expr("max(t + (len - 1) * step) AS t_hi"), F.sum("len").alias("size"))
    distinct = freq.groupBy("series", "bucket").agg(F.count("*").alias("items"))
    return Counts(scratch.save(spans.join(distinct, ["series", "bucket"]), "spans"), freq)


def _cells(config: Config):
    """Cells of the sketches of rows (series, bucket, h, f) that come bucket by bucket: one sketch is held at a time."""
    layers = len(config.widths)
    starts = np.cumsum([0] + [w * config.rows for w in config.widths])
    layer = np.repeat(np.arange(layers), np.diff(starts))
    row, col = np.divmod(np.arange(starts[-1]) - starts[layer], np.array(config.widths)[layer])

    def sketch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, sums = None, np.zeros(starts[-1], np.int64)

        def cells() -> pa.RecordBatch:
            at = np.flatnonzero(touched)
            return pa.RecordBatch.from_arrays([pa.array([now[0]], pa.string()).take(pa.array(np.zeros(len(at), np.int32))), pa.array(np.full(len(at), now[1], np.int32)), pa.array(layer[at], pa.int32()), pa.array(row[at], pa.int32()), pa.array(col[at]), pa.array(sums[at])], names=["series", "bucket", "layer", "row", "col", "c"])

        touched = np.zeros(starts[-1], bool)
        for chunk in _chunks(batches):
            for key, rows in _by_bucket(chunk):
                if key != now:
                    if now:
                        yield cells()
                    now = key
                    sums[:], touched[:] = 0, False
                h, f = rows["h"].to_numpy(), rows["f"].to_numpy()
                depth = _depths(h, layers)
                for j in range(layers):
                    deep = depth >= j
                    if not deep.any():
                        break
                    h, f, depth = h[deep], f[deep], depth[deep]
                    for r in range(config.rows):
                        at = starts[j] + r * config.widths[j] + _places(h, r, config.widths[j])
                        np.add.at(sums, at, _signs(h, r) * f)
                        touched[at] = True
        if now:
            yield cells()

    return sketch


def _by_bucket(chunk: pa.Table) -> Iterator[tuple[tuple, pa.Table]]:
    bucket, series = chunk["bucket"].to_numpy(), chunk["series"].combine_chunks().dictionary_encode()
    code = series.indices.to_numpy()
    cuts = [0, *(np.flatnonzero((np.diff(bucket) != 0) | (np.diff(code) != 0)) + 1), len(bucket)]
    for i, j in zip(cuts, cuts[1:]):
        yield (series.dictionary[code[i]].as_py(), int(bucket[i])), chunk.slice(i, j - i)


def _heavy(config: Config):
    """Of rows (series, bucket, item, h) that come bucket by bucket, the heaviest first, the first of each layer."""
    layers = len(config.widths)

    def first(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, had = None, None
        for chunk in _chunks(batches):
            for key, rows in _by_bucket(chunk):
                if key != now:
                    now, had = key, [0] * layers
                depth = _depths(rows["h"].to_numpy(), layers)
                for j in range(layers):
                    at = np.flatnonzero(depth >= j)[: config.heavy - had[j]]
                    had[j] += len(at)
                    if len(at):
                        yield rows.take(pa.array(at)).append_column("layer", pa.array(np.full(len(at), j, np.int32))).select(["series", "bucket", "layer", "item", "h"]).combine_chunks().to_batches()[0]

    return first


def build(samples: DataFrame, size: int, k: float = K_EH, config: Config = LARGE, hybrid: bool = True, map_bytes: int | None = None) -> Buckets:
    """Buckets of panes of ``size`` positions: see ``formed``."""
    return formed(count(samples, size, k), config, hybrid, map_bytes)


def formed(counts: Counts, config: Config = LARGE, hybrid: bool = True, map_bytes: int | None = None) -> Buckets:
    """Buckets as they are stored.

    A bucket stays a map while its entries take fewer bytes than a sketch's cells, or than ``map_bytes``; ``hybrid`` False sketches all. What a
    sketch stores depends on the configuration, not on the items: its cells, and for each layer ``config.heavy`` items at most. A bucket's
    items stream through one task, which holds one sketch; no cells are moved.
    """
    limit = (config.cells * CELL_BYTES if map_bytes is None else map_bytes) if hybrid else 0
    form = F.when(F.col("items") * ENTRY_BYTES < limit, F.lit("map")).otherwise(F.lit("sketch"))
    spans = counts.spans.withColumn("form", form)
    of_form = counts.freq.join(spans.select("series", "bucket", "form"), ["series", "bucket"])
    sketched = of_form.where("form = 'sketch'").select("series", "bucket", "item", "h", "f").repartition("series", "bucket")
    cells = sketched.drop("item").sortWithinPartitions("bucket", "series").mapInArrow(_cells(config), "series string, bucket int, layer int, row int, col long, c long")
    heavy = sketched.sortWithinPartitions("bucket", "series", F.desc("f"), "item").select("series", "bucket", "item", "h").mapInArrow(_heavy(config), "series string, bucket int, layer int, item string, h long")
    return Buckets(spans, of_form.where("form = 'map'").select("series", "bucket", "item", "f", "h"), cells, heavy)


def _layers(config: Config) -> Column:
    return F.explode(F.sequence(F.lit(0), F.expr(_depth(len(config.widths))))).alias("layer")


def merged(buckets: Buckets, ranges: DataFrame, config: Config = LARGE, by: str = "seq") -> tuple[DataFrame, DataFrame, DataFrame, DataFrame]:
    """Of each range (query, series): n and forms (map, sketch or mixed); counts of the items of maps; and, where a sketch takes part,
    summed cells and candidates (layer, item, h). Maps beside sketches are added to the cells, their items to the candidates."""
    taken = in_range(buckets.spans, ranges, f"{by}_lo").select("query", "series", "bucket", "size", "form")
    forms = taken.groupBy("query", "series").agg(F.sum("size").alias("n"), F.when(F.min("form") == F.max("form"), F.min("form")).otherwise(F.lit("mixed")).alias("forms"))
    of = taken.select("query", "series", "bucket")
    counts = buckets.maps.join(of, ["series", "bucket"]).groupBy("query", "series", "item", "h").agg(F.sum("f").alias("f"))
    loose = counts.join(forms.where("forms = 'mixed'").select("query", "series"), ["query", "series"])
    cells = buckets.cells.join(of, ["series", "bucket"]).select("query", "series", "layer", "row", "col", "c")
    summed = merge_cells(cells.unionByName(sketch_cells(loose, config, "query", "series")), "query", "series")
    candidates = buckets.heavy.join(of, ["series", "bucket"]).select("query", "series", "layer", "item", "h").unionByName(loose.select("query", "series", _layers(config), "item", "h")).distinct()
    return forms, counts, summed, candidates


def distinct_items(buckets: Buckets, ranges: DataFrame, candidates: DataFrame, config: Config, by: str = "seq") -> DataFrame:
    """query, series, known: distinct items of each range from its ``candidates`` (see ``merged``), which all are in it.

    A layer is whole if no bucket had more items in it than it keeps; from the first layer below which all are whole the
    number of candidates is that of the items. Going up, a layer has twice the items of the next one, corrected by its
    candidates, known to be in the next one or not: as in ``gsum``, but for all candidates instead of the heaviest, and
    without estimated counts. Null where the last layer isn't whole.
    """
    layers = len(config.widths)
    taken = in_range(buckets.spans, ranges, f"{by}_lo").where("form = 'sketch'").select("query", "series", "bucket")
    cut = buckets.heavy.groupBy("series", "bucket", "layer").agg(F.count("*").alias("kept")).where(F.col("kept") >= config.heavy).groupBy("series", "bucket").agg(F.max("layer").alias("cut"))
    base = taken.join(cut, ["series", "bucket"], "left").groupBy("query", "series").agg((F.coalesce(F.max("cut"), F.lit(-1)) + 1).alias("base"))
    by_layer = candidates.groupBy("query", "series", "layer").agg(F.count("*").alias("c"), F.count_if(F.expr(f"({_depth(layers)}) > layer")).alias("on"))
    part = F.expr("CASE WHEN layer = base THEN shiftleft(c, layer) WHEN layer < base THEN shiftleft(c - 2 * on, layer) ELSE 0 END")
    return by_layer.join(base, ["query", "series"]).groupBy("query", "series").agg(F.when(F.max("base") < layers, F.sum(part)).cast("double").alias("known"))


def query(buckets: Buckets, ranges: DataFrame, config: Config = LARGE, by: str = "seq") -> DataFrame:
    """query, series, n, forms (map, sketch or mixed), distinct, entropy, l2 of each range.

    Ranges that take only maps are answered from summed counts, exactly but for the alignment; others from summed cells,
    and their distinct items from the candidates.
    """
    forms, counts, summed, candidates = merged(buckets, ranges, config, by)
    exact = counts.join(forms.where("forms = 'map'").select("query", "series"), ["query", "series"]).withColumn("x", F.col("f").cast("double")).groupBy("query", "series").agg(*[F.sum(F.expr(g)).alias(name) for name, g in G.items()])
    sums = gsum(point_estimates(summed, candidates, config, "query", "series"), config, "query", "series")
    norms = l2_of_cells(summed, "query", "series").withColumnRenamed("l2", "row_l2")
    known = distinct_items(buckets, ranges, candidates, config, by)
    sketched_sums = sums.join(norms, ["query", "series"]).withColumn("l2sq", F.col("row_l2") * F.col("row_l2")).drop("row_l2")
    sketched_sums = sketched_sums.join(known, ["query", "series"], "left").withColumn("distinct", F.coalesce("known", "distinct")).drop("known")
    return finish(exact.unionByName(sketched_sums).join(forms, ["query", "series"]), F.col("n")).select("query", "series", "n", "forms", "distinct", "entropy", "l2")


def top_items(buckets: Buckets, ranges: DataFrame, k: int, config: Config = LARGE, by: str = "seq") -> DataFrame:
    """query, series, rank, item and est of the ``k`` most frequent items of each range, ties by item."""
    forms, counts, summed, candidates = merged(buckets, ranges, config, by)
    exact = counts.join(forms.where("forms = 'map'").select("query", "series"), ["query", "series"]).select("query", "series", "item", F.col("f").cast("double").alias("est"))
    sketched = point_estimates(summed, candidates.where("layer = 0"), config, "query", "series").select("query", "series", "item", "est")
    best = Window.partitionBy("query", "series").orderBy(F.desc("est"), "item")
    return exact.unionByName(sketched).withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("query", "series", "rank", "item", "est")


def exact_statistics(samples: DataFrame, ranges: DataFrame) -> DataFrame:
    """query, series, n, distinct, entropy, l2 of the samples of each range. Items are counted once by the pieces of the
    ranges, then summed up for each range where all pieces of an item are."""
    pieces = Scratch(samples.sparkSession, "exact").save(segments(ranges), "pieces")
    inside = cut_runs(runs_of(samples), pieces.select("series", "low", "high").distinct()).select("series", "low", "high", F.explode("items").alias("item"))
    by_piece = inside.groupBy("series", "low", "high", "item").agg(F.count("*").alias("f")).repartition("series", "item")
    counts = by_piece.join(pieces, ["series", "low", "high"]).groupBy("query", "series", "item").agg(F.sum("f").alias("f")).withColumn("x", F.col("f").cast("double"))
    sums = counts.groupBy("query", "series").agg(F.sum("f").alias("n"), *[F.sum(F.expr(g)).alias(name) for name, g in G.items()])
    return finish(sums, F.col("n")).select("query", "series", "n", "distinct", "entropy", "l2")


# -- queries -----------------------------------------------------------------------------------------------------------

_H = "cast('0x' || substr(md5(item), 1, 7) AS bigint)"


def _exact_sql(view: str, cuts) -> str:
    return f"""WITH v AS ({view}), {fractions_sql(cuts)},
c AS (SELECT query, v.series, item, count(*)::DOUBLE AS x FROM v JOIN ranges r ON v.series = r.series AND seq > low AND seq <= high GROUP BY ALL)"""


def gsum_exact(spark: SparkSession, sf_dir: str) -> DataFrame:
    samples = series_view(spark, sf_dir, "ev_type")
    found = exact_statistics(samples, fractions_of(samples, CUTS))
    return found.select("query", "series", "n", F.col("distinct").cast("long").alias("distinct"), F.round("entropy", 6).alias("entropy"), F.round("l2", 6).alias("l2"))


def cells_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sketch_cells(frequencies(series_view(spark, sf_dir, "doc_tokens_lang")), SMALL, "series")


def deepest_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sketch_cells(frequencies(series_view(spark, sf_dir, "ev_type")), SMALL, "series", update="deepest")


def l2_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return l2_of_cells(sketch_cells(frequencies(series_view(spark, sf_dir, "doc_tokens_lang")), SMALL, "series"), "series").withColumn("l2", F.round("l2", 6))


def point_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Estimates of the counts of every user, by event type."""
    freq = frequencies(series_view(spark, sf_dir, "ev_type"))
    found = point_estimates(sketch_cells(freq, SMALL, "series"), freq.select("series", F.lit(0).alias("layer"), "item", "h"), SMALL, "series")
    return found.select("series", "item", F.round("est").cast("long").alias("est"))


def _cells_sql(view: str, config: Config, update: str) -> str:
    width = "CASE layer " + " ".join(f"WHEN {j} THEN {w}" for j, w in enumerate(config.widths)) + " END"
    layers = "unnest(range(0, depth + 1))" if update == "all" else "depth"
    parts = " UNION ALL ".join(f"SELECT series, layer, {r} AS row, {_hash(*ROWS[r])} % ({width}) AS col, CASE WHEN {_hash(*SIGNS[r])} % 2 = 0 THEN f ELSE -f END AS v FROM s" for r in range(config.rows))
    return f"""WITH f AS (SELECT series, item, count(*) AS f, {_H} AS h FROM ({view}) GROUP BY series, item),
s AS (SELECT series, f, h, {layers} AS layer FROM (SELECT *, {_depth(len(config.widths))} AS depth FROM f)),
cells AS (SELECT series, layer::INT AS layer, row, col, sum(v)::BIGINT AS c FROM ({parts}) GROUP BY ALL)"""


def _bounded(size: int, cuts, tolerance: dict[str, float], view: str, hybrid: bool = True, config: Config = FINE, map_bytes: int | None = None):
    """Estimates beside the exact values, with whether each is within its tolerance of the suffix's statistic."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        scratch = Scratch(spark, "univ")
        samples = written_words(spark, sf_dir, view) if view in WORDS else scratch.save(series_view(spark, sf_dir, view, counted=True), "samples")
        # of each range and of the suffix that it begins
        both = scratch.save(fractions_of(samples, [(f"{x}{q}", a, b * (x == "e")) for q, a, b in cuts for x in "es"]), "ranges")
        ranges = both.where("query LIKE 'e%'").withColumn("query", F.expr("substr(query, 2)"))
        found = query(build(samples, size, K_EH, config, hybrid, map_bytes).saved(Scratch(spark, "univ")), ranges, config)
        exact = scratch.save(exact_statistics(samples, both), "exact")
        exact, suffix = (exact.where(F.col("query").startswith(x)).withColumn("query", F.expr("substr(query, 2)")) for x in "es")
        joined = found.alias("e").join(exact.alias("x"), ["query", "series"]).join(suffix.alias("s"), ["query", "series"])
        checks = [(F.abs(F.col(f"e.{m}") - F.col(f"x.{m}")) <= tol * F.col(f"s.{m}")).alias(f"{m}_within") for m, tol in tolerance.items()]
        return joined.select("query", "series", F.col("x.distinct").cast("long").alias("distinct"), F.round("x.entropy", 6).alias("entropy"), F.round("x.l2", 6).alias("l2"), *checks)

    return run


def _bounded_sql(view: str, cuts) -> str:
    return _exact_sql(view, cuts) + " SELECT query, series, count(*) AS \"distinct\", round(ln(sum(x)) - sum(x * ln(x)) / sum(x), 6) AS entropy, round(sqrt(sum(x * x)), 6) AS l2, true AS distinct_within, true AS entropy_within, true AS l2_within FROM c GROUP BY query, series"


WIDE = [("full", 1.0, 0.0), ("suffix", 0.4, 0.0), ("middle", 0.6, 0.3)]
#: Of the statistic of the suffix that the range begins.
_TOLERANCE = {"distinct": 0.05, "entropy": 0.05, "l2": 0.05}


def raw_statistics(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Estimates with the small sketches, for a look at the errors: no bound is claimed."""
    samples = series_view(spark, sf_dir, "doc_tokens")
    ranges = fractions_of(samples, WIDE)
    return query(build(samples, 5000, K_EH, SMALL), ranges, SMALL)


def topk_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recall of the ten most frequent tokens of a range, from the sketch's heavy items."""
    samples = series_view(spark, sf_dir, "doc_tokens")
    ranges = fractions_of(samples, WIDE)
    found = top_items(build(samples, 5000, K_EH, LARGE, hybrid=False), ranges, 10)
    inside = in_range(samples, ranges).groupBy("query", "series", "item").agg(F.count("*").alias("f"))
    true = inside.withColumn("nth", F.row_number().over(Window.partitionBy("query", "series").orderBy(F.desc("f"), "item"))).where("nth <= 10").select("query", "series", "item", "f")
    hit = true.join(found.withColumn("hit", F.lit(1)), ["query", "series", "item"], "left")
    return hit.groupBy("query", "series").agg(F.sum("f").alias("exact"), (F.sum(F.coalesce("hit", F.lit(0))) >= 9).alias("within_bound"))


QUERIES: dict = {
    "gsum_exact": gsum_exact, "univ_cells": cells_query, "univ_cells_deepest": deepest_cells, "cs_l2": l2_query, "cs_point": point_query,
    "ehuniv_hybrid_events": _bounded(20, CUTS[:4], _TOLERANCE, "ev_type"), "ehuniv_hybrid_tokens": _bounded(1000, WIDE, _TOLERANCE, "doc_tokens"),
    "ehuniv_plain_tokens": _bounded(1000, WIDE, _TOLERANCE, "doc_tokens", hybrid=False), "ehuniv_mixed_tokens": _bounded(1000, WIDE, _TOLERANCE, "doc_tokens", map_bytes=500 * ENTRY_BYTES), "ehuniv_raw_statistics": raw_statistics, "topk_recall": topk_query,
}
SQL: dict = {
    "gsum_exact": _exact_sql(VIEWS["ev_type"].sql, CUTS) + " SELECT query, series, sum(x)::BIGINT AS n, count(*) AS \"distinct\", round(ln(sum(x)) - sum(x * ln(x)) / sum(x), 6) AS entropy, round(sqrt(sum(x * x)), 6) AS l2 FROM c GROUP BY query, series",
    "univ_cells": _cells_sql(VIEWS["doc_tokens_lang"].sql, SMALL, "all") + " SELECT * FROM cells",
    "univ_cells_deepest": _cells_sql(VIEWS["ev_type"].sql, SMALL, "deepest") + " SELECT * FROM cells",
    "cs_l2": _cells_sql(VIEWS["doc_tokens_lang"].sql, SMALL, "all") + " SELECT series, round(sqrt(median(s)), 6) AS l2 FROM (SELECT series, row, sum(c * c)::DOUBLE AS s FROM cells WHERE layer = 0 GROUP BY ALL) GROUP BY series",
    "cs_point": _cells_sql(VIEWS["ev_type"].sql, SMALL, "all") + f", asked AS (SELECT series, item, f.h, unnest([0, 1, 2]) AS row FROM f), seen AS (SELECT a.series, a.item, coalesce(c, 0) * sign AS e FROM (SELECT series, item, row, CASE row WHEN 0 THEN {_hash(*ROWS[0])} WHEN 1 THEN {_hash(*ROWS[1])} ELSE {_hash(*ROWS[2])} END % {SMALL.widths[0]} AS col, CASE WHEN CASE row WHEN 0 THEN {_hash(*SIGNS[0])} WHEN 1 THEN {_hash(*SIGNS[1])} ELSE {_hash(*SIGNS[2])} END % 2 = 0 THEN 1 ELSE -1 END AS sign FROM asked) a LEFT JOIN (SELECT * FROM cells WHERE layer = 0) c ON a.series = c.series AND a.row = c.row AND a.col = c.col) SELECT series, item, round(median(e))::BIGINT AS est FROM seen GROUP BY series, item",
    "ehuniv_hybrid_events": _bounded_sql(VIEWS["ev_type"].sql, CUTS[:4]),
    "ehuniv_hybrid_tokens": _bounded_sql(VIEWS["doc_tokens"].sql, WIDE),
    "ehuniv_plain_tokens": _bounded_sql(VIEWS["doc_tokens"].sql, WIDE),
    "ehuniv_mixed_tokens": _bounded_sql(VIEWS["doc_tokens"].sql, WIDE),
    "topk_recall": f"WITH v AS ({VIEWS['doc_tokens'].sql}), {fractions_sql(WIDE)}, c AS (SELECT query, v.series, item, count(*) AS f FROM v JOIN ranges r ON v.series = r.series AND seq > low AND seq <= high GROUP BY ALL) SELECT query, series, sum(f)::BIGINT AS exact, true AS within_bound FROM (SELECT *, row_number() OVER (PARTITION BY query, series ORDER BY f DESC, item) AS nth FROM c) WHERE nth <= 10 GROUP BY query, series",
}

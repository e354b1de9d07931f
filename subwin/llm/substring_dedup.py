"""Substring dedup by super-k-mers: windows of words whose sequence starts anywhere else are removed.

The minimiser of a window is the least hash of the runs of M words in it; equal windows have equal ones.
Consecutive windows that share it are one super-k-mer, which can travel to the minimiser's bucket as one
packed string. First only minimisers are counted: a super-k-mer whose minimiser no other has, and that
can't repeat within itself, holds no repeated window and stays at home. The others are packed, equal
strings are counted before they are shuffled, and in each bucket a sort brings equal windows together, to
be counted exactly on their words. A bucket of more than MOST_WINDOWS windows is split: its windows are
dealt by their own digests and counted by an aggregate. Counts then go back to the occurrences.

Defined results: a null text has no words; a text of fewer words than a window keeps all; windows are
judged on the input, so all copies of a repeated window go; repeated rows repeat each other's windows. Rows
with a null or repeated doc_id each get a row. Other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from subwin.llm.common import join_same, map_batches, partitions, table, text_key, texts
from subwin.storage import Scratch

WINDOW, M = 35, 8
#: Most windows of one super-k-mer, and of one bucket that is sorted by a single task.
MOST_TOGETHER, MOST_WINDOWS = 4096, 16_384
SALTS = 16


def minimisers(words: list[bytes], window: int = WINDOW, m: int = M) -> np.ndarray:
    """The minimiser of each window, and whether it stands more than once in the window."""
    hashes = np.fromiter(map(xxhash.xxh3_64_intdigest, words), np.uint64, len(words))
    runs = np.zeros(len(words) - m + 1, np.uint64)
    for i in range(m):
        runs = runs * np.uint64(0x9E3779B97F4A7C15) + hashes[i : i + len(runs)]
    runs ^= runs >> np.uint64(29)
    runs *= np.uint64(0xBF58476D1CE4E5B9)
    runs ^= runs >> np.uint64(32)
    view = np.lib.stride_tricks.sliding_window_view(runs, window - m + 1)
    least = view.min(axis=1)
    return least, np.concatenate([(part == low[:, None]).sum(axis=1) > 1 for part, low in zip(np.array_split(view, len(view) // 65_536 + 1), np.array_split(least, len(view) // 65_536 + 1), strict=True)])


def super_kmers(words: list[bytes], window: int = WINDOW, m: int = M) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Of each super-k-mer: minimiser, first window, number of windows, whether a window may repeat within it."""
    if len(words) < window:
        return tuple(np.empty(0, np.int64) for _ in range(4))
    least, twice = minimisers(words, window, m)
    starts = np.append(0, np.flatnonzero(least[1:] != least[:-1]) + 1)
    lengths = np.diff(np.append(starts, len(least)))
    if lengths.max() > MOST_TOGETHER:
        parts = [np.arange(s, s + n, MOST_TOGETHER) for s, n in zip(starts, lengths, strict=True)]
        starts = np.concatenate(parts)
        lengths = np.diff(np.append(starts, len(least)))
    within = np.logical_or.reduceat(twice, starts) | (lengths > window - m + 1)
    return least[starts].view(np.int64), starts, lengths, within


def _occurrences(batch: pa.RecordBatch) -> pa.RecordBatch:
    rows: list[list] = [[], [], [], []]
    which = []
    for i, text in enumerate(texts(batch)):
        found = super_kmers(text.encode().split())
        if len(found[0]):
            for column, values in zip(rows, found, strict=True):
                column.append(values)
            which.append(np.full(len(found[0]), i))
    if not which:
        return None
    at = pa.array(np.concatenate(which))
    mini, start, n, within = map(np.concatenate, rows)
    return pa.RecordBatch.from_arrays([batch.column(0).take(at), batch.column(1).take(at), pa.array(mini), pa.array(start.astype(np.int32)), pa.array(n.astype(np.int32)), pa.array(within)], names=["doc_id", "text_key", "mini", "start", "n", "within"])


def _results(rows: list[tuple[int, list[bytes], list[bytes]]], with_text: bool) -> list[list]:
    """Columns place, n_words, n_removed, kept_sha256 and kept, of places, words and kept words."""
    joined = [b" ".join(left) for _, _, left in rows]
    return [[i for i, _, _ in rows], [len(words) for _, words, _ in rows], [len(words) - len(left) for _, words, left in rows], [hashlib.sha256(x).hexdigest() for x in joined], [x.decode() if with_text else None for x in joined]]


_RESULT = "n_words long, n_removed long, kept_sha256 string, kept string"
_RESULT_TYPES = (pa.int64(), pa.int64(), pa.string(), pa.string())
_STRING = ("mini", "hot", "start", "packed", "digest")
_STRING_TYPES = (pa.int64(), pa.bool_(), pa.int32(), pa.binary(), pa.binary())


def _pack(batch: pa.RecordBatch, with_text: bool) -> pa.RecordBatch:
    """Of documents that have a list of super-k-mers: one row with the text, and one of each packed string; of others, the result."""
    out: list[list] = [[] for _ in range(6)]
    whole, done = [], []
    for i, (text, found) in enumerate(zip(texts(batch), batch.column(3).to_pylist(), strict=True)):
        words = text.encode().split()
        if found is None:
            done.append((i, words, words))
            continue
        whole.append(i)
        for x in found:
            packed = b" ".join(words[x["start"] : x["start"] + x["n"] + WINDOW - 1])
            for column, value in zip(out, (i, x["mini"], x["hot"], x["start"], packed, hashlib.blake2b(packed, digest_size=16).digest()), strict=True):
                column.append(value)
    at, *results = _results(done, with_text)
    nulls = lambda n, kinds: [pa.nulls(n, t) for t in kinds]
    parts = [
        [pa.array(out[0], pa.int64()), *map(pa.array, out[1:], _STRING_TYPES), *nulls(len(out[0]), _RESULT_TYPES), pa.nulls(len(out[0]), pa.string())],
        [pa.array(at, pa.int64()), *nulls(len(at), _STRING_TYPES), *map(pa.array, results, _RESULT_TYPES), pa.nulls(len(at), pa.string())],
        [pa.array(whole, pa.int64()), *nulls(len(whole), _STRING_TYPES), *nulls(len(whole), _RESULT_TYPES), batch.column(2).take(pa.array(whole, pa.int64())).cast(pa.string())],
    ]
    place, *columns = (pa.concat_arrays(x) for x in zip(*parts, strict=True))
    return pa.RecordBatch.from_arrays([batch.column(0).take(place), batch.column(1).take(place), *columns], names=["doc_id", "text_key", *_STRING, "n_words", "n_removed", "kept_sha256", "kept", "text"])


def windows_of(packed: bytes) -> list[bytes]:
    """The windows of a packed string, each as its words joined by spaces."""
    spaces = np.flatnonzero(np.frombuffer(packed, np.uint8) == 32)
    starts = np.append(0, spaces + 1)
    ends = np.append(spaces, len(packed))
    return [packed[a:b] for a, b in zip(starts[: len(starts) - WINDOW + 1].tolist(), ends[WINDOW - 1 :].tolist(), strict=True)]


def runs_of(offsets: np.ndarray) -> list[dict]:
    """Sorted numbers of windows as runs: first, and how many."""
    if not len(offsets):
        return []
    starts = np.append(0, np.flatnonzero(np.diff(offsets) > 1) + 1)
    return [{"first": int(offsets[s]), "count": int(n)} for s, n in zip(starts, np.diff(np.append(starts, len(offsets))), strict=True)]


_RUNS = pa.list_(pa.struct([("first", pa.int32()), ("count", pa.int32())]))


def _count_bucket(rows: list[tuple[bytes, bytes, int]]) -> list[tuple[bytes, list[dict]]]:
    """digest and runs of repeated windows, of a bucket's distinct strings (digest, string, how often)."""
    entries = [(w, i, k) for i, (_, packed, _) in enumerate(rows) for k, w in enumerate(windows_of(packed))]
    entries.sort()
    repeated: list[list[int]] = [[] for _ in rows]
    at = 0
    while at < len(entries):
        end = at + 1
        while end < len(entries) and entries[end][0] == entries[at][0]:
            end += 1
        if end - at > 1 or rows[entries[at][1]][2] > 1:
            for _, i, k in entries[at:end]:
                repeated[i].append(k)
        at = end
    return [(digest, runs_of(np.array(sorted(k)))) for (digest, _, _), k in zip(rows, repeated, strict=True) if k]


def _sweep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of rows sorted by minimiser (mini, digest, packed, n): digest and runs of repeated windows."""
    bucket, held = None, []

    def close() -> list:
        if len(held) == 1 and held[0][2] > 1:
            return [(held[0][0], [{"first": 0, "count": held[0][1].count(b" ") + 2 - WINDOW}])]
        return _count_bucket(held)

    def emit(rows):
        digest, runs = zip(*rows, strict=True)
        return pa.RecordBatch.from_arrays([pa.array(digest, pa.binary()), pa.array(runs, _RUNS)], names=["digest", "runs"])

    for batch in batches:
        out = []
        for mini, digest, packed, n in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
            if mini != bucket:
                out += close()
                bucket, held = mini, []
            held.append((digest, packed, n))
        if out:
            yield emit(out)
    if out := close():
        yield emit(out)


def _window_digests(batch: pa.RecordBatch) -> pa.RecordBatch:
    out: list[list] = [[], [], [], []]
    for digest, packed, n in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True):
        for k, w in enumerate(windows_of(packed)):
            for column, value in zip(out, (hashlib.blake2b(w, digest_size=16).digest(), digest, k, n), strict=True):
                column.append(value)
    return pa.RecordBatch.from_arrays([pa.array(out[0], pa.binary()), pa.array(out[1], pa.binary()), pa.array(out[2], pa.int32()), pa.array(out[3], pa.int64())], names=["window", "digest", "k", "n"])


def repeated_runs(docs: DataFrame, scratch: Scratch, most: int = MOST_WINDOWS, with_text: bool = False) -> tuple[DataFrame, DataFrame]:
    """Of ``docs`` (doc_id, text_key, text), in two frames: results of the documents that no other shares a minimiser
    with; and the others, with runs of their windows that repeat, as first and count.

    Texts travel to their super-k-mers; once packed, only the texts that may hold a repeat travel again, to their runs.
    """
    id_type = docs.schema["doc_id"].dataType.simpleString()
    keys = f"doc_id {id_type}, text_key long"
    found = scratch.save(map_batches(docs.select("doc_id", "text_key", "text"), _occurrences, f"{keys}, mini long, start int, n int, within boolean"), "super_kmers")
    shared = found.groupBy("mini").agg(F.sum(F.when(F.col("within"), 2).otherwise(1)).alias("times"), (F.sum("n") > most).alias("hot")).where("times > 1").select("mini", "hot")
    travel = found.join(shared, "mini").groupBy("doc_id", "text_key").agg(F.collect_set(F.struct("start", "n", "mini", "hot")).alias("list"))
    with_list = join_same(docs, travel, ["doc_id", "text_key"], "left").select("doc_id", "text_key", "text", "list")
    met = scratch.save(map_batches(with_list, lambda batch: _pack(batch, with_text), f"{keys}, mini long, hot boolean, start int, packed binary, digest binary, {_RESULT}, text string"), "packed")
    scratch.drop("super_kmers")
    packed = met.where("packed is not null").select("doc_id", "text_key", *_STRING)
    cold = packed.where("not hot").groupBy("mini", "digest", "packed").agg(F.count("*").alias("n"))
    dealt = cold.repartition(partitions(docs.sparkSession), "mini").sortWithinPartitions("mini").select("mini", "digest", "packed", "n")
    counted = scratch.save(dealt.mapInArrow(_sweep, "digest binary, runs array<struct<first:int,count:int>>"), "counted")
    hot = packed.where("hot").groupBy("digest", "packed").agg(F.count("*").alias("n")).select("digest", "packed", "n")
    large = scratch.save(map_batches(hot, _window_digests, "window binary, digest binary, k int, n long"), "large")
    # a window may be in any number of strings: its strings are dealt to SALTS tasks
    often = large.groupBy("window").agg(F.sum("n").alias("times")).where("times > 1").select("window", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("salt"))
    salted = large.withColumn("salt", F.pmod(F.xxhash64("digest"), F.lit(SALTS)).cast("int"))
    single = salted.join(often, ["window", "salt"]).groupBy("digest").agg(F.transform(F.collect_set("k"), lambda k: F.struct(k.alias("first"), F.lit(1).alias("count"))).alias("runs"))
    flags = counted.unionByName(single)
    hits = packed.select("doc_id", "text_key", "start", "digest").join(flags, "digest").select("doc_id", "text_key", "start", F.inline("runs"))
    runs = hits.groupBy("doc_id", "text_key").agg(F.collect_set(F.struct((F.col("start") + F.col("first")).alias("first"), "count")).alias("runs"))
    runs = scratch.save(runs, "runs")
    for name in ("counted", "large"):
        scratch.drop(name)
    waiting = met.where("packed is null and kept_sha256 is null").select("doc_id", "text_key", "text")
    done = met.where("kept_sha256 is not null").select("doc_id", "n_words", "n_removed", "kept_sha256", "kept")
    return done, join_same(waiting, runs, ["doc_id", "text_key"], "left").select("doc_id", "text", "runs")


def kept_words(words: list[bytes], runs: list[dict]) -> list[bytes]:
    if not runs:
        return words
    covered = np.zeros(len(words) + 1, np.int64)
    for run in runs:
        covered[run["first"]] += 1
        covered[min(len(words), run["first"] + run["count"] + WINDOW - 1)] -= 1
    return [w for w, c in zip(words, np.cumsum(covered).tolist(), strict=False) if not c]


def drop_repeats(docs: DataFrame, with_text: bool = False, most: int = MOST_WINDOWS) -> DataFrame:
    """doc_id, n_words, n_removed and kept_sha256 of each document (doc_id, text); ``with_text`` adds kept, its kept
    words joined by spaces; a minimiser of more than ``most`` windows is split by the windows' digests."""
    scratch = Scratch(docs.sparkSession, "substrings")
    rows = docs.select("doc_id", text_key(F.col("text")).alias("text_key"), "text")
    done, waiting = repeated_runs(rows, scratch, most, with_text)

    def cut(batch: pa.RecordBatch) -> pa.RecordBatch:
        split = [text.encode().split() for text in texts(batch)]
        _, *results = _results([(i, words, kept_words(words, own.as_py())) for i, (words, own) in enumerate(zip(split, batch.column(2), strict=True))], with_text)
        return pa.RecordBatch.from_arrays([batch.column(0), *map(pa.array, results, _RESULT_TYPES)], names=["doc_id", "n_words", "n_removed", "kept_sha256", "kept"])

    id_type = docs.schema["doc_id"].dataType.simpleString()
    found = done.unionByName(map_batches(waiting, cut, f"doc_id {id_type}, {_RESULT}"))
    return found if with_text else found.drop("kept")


def op6_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return drop_repeats(table(spark, sf_dir, "documents"))


OP6_SQL = r"""
WITH d AS (SELECT doc_id, row_number() OVER () AS id, list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS words FROM documents),
w AS (SELECT id, pos, array_to_string(words[pos : pos + 34], ' ') AS win FROM (SELECT id, words, unnest(range(1, len(words) - 33)) AS pos FROM d)),
rep AS (SELECT win FROM w GROUP BY win HAVING count(*) > 1),
hit AS (SELECT w.id, w.pos FROM w JOIN rep USING (win)),
gone AS (SELECT DISTINCT id, unnest(range(pos, pos + 35)) AS spot, true AS is_gone FROM hit),
word AS (SELECT id, unnest(words) AS word, generate_subscripts(words, 1) AS spot FROM d),
kept AS (SELECT id, string_agg(word, ' ' ORDER BY spot) AS kept FROM word LEFT JOIN gone USING (id, spot) WHERE is_gone IS NULL GROUP BY id),
n AS (SELECT id, count(*) AS n_removed FROM gone GROUP BY id)
SELECT doc_id, len(words)::BIGINT AS n_words, coalesce(n_removed, 0)::BIGINT AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256
FROM d LEFT JOIN kept USING (id) LEFT JOIN n USING (id)
"""

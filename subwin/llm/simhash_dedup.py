"""SimHash near-dedup by deletion-variant signatures.

Fingerprints of 64 bits link at two or fewer differing bits. Cut into two segments, at least one segment
of a linked pair differs by one bit at most, so its two values are equal once that bit is left out. Each
distinct fingerprint is indexed under the 64 values that leave one bit of one segment out; equal values
meet by an equality join (one shuffle, sorted, swept in order), and pairs are verified by the bits in
which they differ. A value that more than MOST_IN_BUCKET distinct fingerprints share isn't paired out:
its members are indexed under the values that leave out any two of the bits that may still differ, and
members of one such value are all linked with each other, so linking each with the first is exact. Linked
fingerprints are joined to components by contracting stars, a checkpoint each round.

Defined results: a text without words, or null, has fingerprint zero and links like any other; copies
have one fingerprint and so one component. The component is named by its smallest doc_id; null ids are
greater than any, and named null only among themselves. Repeated rows each get a row. Other columns are
ignored, or kept where rows are returned whole.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from subwin.llm.common import map_batches, partitions, table, text_key, texts
from subwin.storage import Scratch

SEED, WIDTH, NEAR = 42, 3, 2
#: Most distinct fingerprints under one value that are compared pair by pair.
MOST_IN_BUCKET = 512
ASCII_LOWER = bytes.maketrans(b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"abcdefghijklmnopqrstuvwxyz")


def shingles(text: str, width: int = WIDTH) -> np.ndarray:
    """A hash of each run of ``width`` words; of all words where there are no more; none of no words."""
    words = text.encode().translate(ASCII_LOWER).split()
    if not words:
        return np.empty(0, np.uint64)
    joined = b" ".join(words)
    if len(words) <= width:
        return np.array([xxhash.xxh64_intdigest(joined, SEED)], np.uint64)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)
    starts = [0, *(ends[: -width]).tolist()]
    digest = xxhash.xxh64_intdigest
    return np.array([digest(joined[a:b], SEED) for a, b in zip(starts, (ends[width - 1 :] - 1).tolist(), strict=True)], np.uint64)


def simhash(text: str, width: int = WIDTH) -> int:
    """The fingerprint of one text, unsigned."""
    hashes = shingles(text, width)
    return _majority(hashes) if len(hashes) else 0


def _majority(hashes: np.ndarray) -> int:
    """Bit i is set if it is in over half the hashes."""
    ones = np.zeros(64, np.int64)
    for part in np.array_split(hashes, max(1, len(hashes) // 65_536)):
        ones += np.unpackbits(part.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(hashes), bitorder="little").view("<u8")[0])


def _signed(values: list[int]) -> pa.Array:
    return pa.array(np.array(values, np.uint64).view(np.int64))


def fingerprints(docs: DataFrame, key: bool = False) -> DataFrame:
    """doc_id and fp (the fingerprint as a signed long) of each document; with ``key`` also its text_key."""

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        values = _signed([simhash(x) for x in texts(batch)])
        rest = batch.schema.names[:-1]
        return pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(len(rest))), values], names=[*rest, "fp"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    keys = [text_key(F.col("text")).alias("text_key")] if key else []
    return map_batches(docs.select("doc_id", *keys, "text"), run, f"doc_id {kind}" + ", text_key long" * key + ", fp long")


def _sweep(batches: Iterator[pa.RecordBatch], most: int) -> Iterator[pa.RecordBatch]:
    """Of rows sorted by (slot, value): linked pairs a, b, slot null; members a of crowded values with their slot, b null."""
    held: list[np.ndarray] = []  # fingerprints of the value that the last batch ended in
    last: tuple | None = None
    crowded = False

    def close() -> tuple[list, list, list]:
        nonlocal held
        fps = np.concatenate(held) if held else np.empty(0, np.int64)
        held = []
        if crowded or len(fps) > most:
            return fps.tolist(), [None] * len(fps), [last[0]] * len(fps)
        i, j = np.triu_indices(len(fps), 1)
        near = np.bitwise_count((fps[i] ^ fps[j]).view(np.uint64)) <= NEAR
        return fps[i][near].tolist(), fps[j][near].tolist(), [None] * int(near.sum())

    for batch in batches:
        slot, value, fp = (batch.column(i).to_numpy(zero_copy_only=False) for i in range(3))
        cuts = np.flatnonzero((slot[1:] != slot[:-1]) | (value[1:] != value[:-1])) + 1
        starts, ends = np.append(0, cuts), np.append(cuts, len(slot))
        found: tuple[list, list, list] = ([], [], [])

        def add(rows, found=found):
            for whole, part in zip(found, rows, strict=True):
                whole.extend(part)

        # single members in the middle of a batch have no partner
        many = np.flatnonzero((ends - starts > 1) | (np.arange(len(starts)) == 0) | (np.arange(len(starts)) == len(starts) - 1))
        for g in many:
            key = (int(slot[starts[g]]), int(value[starts[g]]))
            if key != last:
                if last is not None:
                    add(close())
                last, crowded = key, False
            held.append(fp[starts[g] : ends[g]])
            if crowded or sum(map(len, held)) > most:
                crowded = True
                add(close())
        if found[0]:
            yield pa.RecordBatch.from_arrays([pa.array(found[0], pa.int64()), pa.array(found[1], pa.int64()), pa.array(found[2], pa.int32())], names=["a", "b", "slot"])
    if last is not None and held:
        rows = close()
        if rows[0]:
            yield pa.RecordBatch.from_arrays([pa.array(rows[0], pa.int64()), pa.array(rows[1], pa.int64()), pa.array(rows[2], pa.int32())], names=["a", "b", "slot"])


def _variants(batch: pa.RecordBatch) -> pa.RecordBatch:
    """Slot (segment and bit that is left out), value and fingerprint, for each of the 64 slots."""
    fp = batch.column(0).to_numpy(zero_copy_only=False)
    segment = np.array([0xFFFFFFFF, 0xFFFFFFFF << 32], np.uint64).view(np.int64)
    bits = np.left_shift(np.uint64(1), np.arange(64, dtype=np.uint64)).view(np.int64)
    masks = segment[np.arange(64) // 32] & ~bits
    return pa.RecordBatch.from_arrays([pa.array(np.tile(np.arange(64, dtype=np.int32), len(fp))), pa.array((fp[:, None] & masks[None, :]).ravel()), pa.array(np.repeat(fp, 64))], names=["slot", "value", "fp"])


def _pair_masks(slot: int) -> np.ndarray:
    """Masks that leave out two of the bits in which members of one value of ``slot`` may differ."""
    free = [slot, *range(32, 64)] if slot < 32 else [slot, *range(32)]
    return np.array([~((1 << a) | (1 << b)) & (2**64 - 1) for a, b in combinations(free, NEAR)], np.uint64).view(np.int64)


def _crowd(batch: pa.RecordBatch) -> pa.RecordBatch:
    fp, slot = (batch.column(i).to_numpy(zero_copy_only=False) for i in range(2))
    masks = np.stack([_pair_masks(int(s)) for s in slot])
    n = masks.shape[1]
    return pa.RecordBatch.from_arrays([pa.array(masks.ravel()), pa.array((fp[:, None] & masks).ravel()), pa.array(np.repeat(fp, n))], names=["mask", "value", "fp"])


def links(fps: DataFrame, scratch: Scratch, most: int = MOST_IN_BUCKET) -> DataFrame:
    """Pairs a, b of distinct fingerprints (column fp, distinct) that connect all that link; ``most`` under one value are paired out."""
    n = partitions(fps.sparkSession)
    variants = map_batches(fps.select("fp"), _variants, "slot int, value long, fp long")
    swept = scratch.save(variants.repartition(n, "slot", "value").sortWithinPartitions("slot", "value").mapInArrow(lambda batches: _sweep(batches, most), "a long, b long, slot int").distinct(), "swept")
    crowds = map_batches(swept.where("slot is not null").select(F.col("a").alias("fp"), "slot"), _crowd, "mask long, value long, fp long")
    firsts = crowds.groupBy("mask", "value").agg(F.min("fp").alias("first"), F.max("fp").alias("last"))
    stars = crowds.join(firsts.where("first < last"), ["mask", "value"]).where("fp <> first").select(F.col("first").alias("a"), F.col("fp").alias("b"))
    return swept.where("slot is null").select("a", "b").unionByName(stars).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def components(edges: DataFrame, scratch: Scratch) -> DataFrame:
    """node, root for each node of ``edges`` (a, b): root is the smallest node that it reaches.

    Large stars hang each node's greater neighbours on its smallest neighbour, small stars the smaller
    ones; the rounds, each a checkpoint, end when no edge changes. Hot nodes are only aggregated and joined.
    """
    pairs = scratch.save(edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), "edges0")

    def stamp(frame: DataFrame) -> tuple:
        return tuple(frame.agg(F.count("*"), F.coalesce(F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")), F.lit(0))).first())

    before, turn = stamp(pairs), 0
    while before[0]:
        both = pairs.unionByName(pairs.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = large.distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u")
        small = small.where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(least.select("u", F.col("m").alias("v")))
        pairs = scratch.save(small.where("u <> v").distinct(), f"edges{turn + 1}")
        after, turn = stamp(pairs), turn + 1
        scratch.drop(f"edges{turn - 1}")
        if after == before:
            break
        before = after
    return pairs.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(pairs.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())


def classes(printed: DataFrame, scratch: Scratch, most: int = MOST_IN_BUCKET) -> DataFrame:
    """fp and component_id for each distinct fingerprint of ``printed`` (doc_id, fp)."""
    nodes = scratch.save(printed.groupBy("fp").agg(F.min("doc_id").alias("least")), "nodes")
    roots = components(links(nodes, scratch, most), scratch)
    rooted = nodes.join(roots, nodes["fp"] == roots["node"], "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    named = rooted.groupBy("root").agg(F.min("least").alias("component_id"))
    return scratch.save(rooted.join(named, "root").select("fp", "component_id"), "classes")


def near_duplicates(docs: DataFrame) -> DataFrame:
    """doc_id, fp and component_id of each document (doc_id, text)."""
    scratch = Scratch(docs.sparkSession, "simhash")
    printed = scratch.save(fingerprints(docs), "printed")
    return printed.join(classes(printed, scratch), "fp").select("doc_id", "fp", "component_id")


def drop_near_copies(docs: DataFrame) -> DataFrame:
    """``docs`` (doc_id, text, ...) with the row of the smallest doc_id of each component; all columns stay.

    Rows alike in doc_id and text are one; where rows of one id differ in text, the one of the least text hash stays.
    """
    scratch = Scratch(docs.sparkSession, "simhash")
    printed = scratch.save(fingerprints(docs, key=True), "printed")
    placed = printed.join(classes(printed, scratch), "fp")
    first = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "text_key")).alias("first")
    # a component without any id is one group by its fingerprints' common null name, told apart by fp
    kept = placed.groupBy("component_id", F.when(F.col("component_id").isNull(), F.col("fp")).alias("of")).agg(first)
    kept = kept.select(F.col("first.doc_id").alias("_subwin_id"), F.col("first.text_key").alias("_subwin_key")).distinct()
    keyed = docs.withColumn("_subwin_text", text_key(docs["text"]))
    found = keyed.join(kept, (keyed["_subwin_text"] == kept["_subwin_key"]) & keyed["doc_id"].eqNullSafe(kept["_subwin_id"]), "left_semi")
    return found.dropDuplicates(["_subwin_text", "doc_id"]).select(*[F.col(f"`{c}`") for c in docs.columns])


def op10_simhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents")).select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")

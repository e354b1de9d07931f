"""LM scoring by cross-entropy difference of two matched n-gram models.

A target model is counted on the documents labelled good, a background model on all documents. Both are
word-pair models that back off to words, with the same weights over the same vocabulary, that of all
documents. A document is held out when it is scored: its own counts are taken off each model that holds
it, so that no model is asked about text it was counted on. Its score is the mean over its words of target
loss less background loss; the lower, the more it reads like the target.

The probability of a word w after v, of counts without the document: MIX[0] * pair(v, w) / before(v) where v
has been seen before any word, else nothing; MIX[2] / words of the vocabulary; and the rest of the weight
by w's share of all words. It sums to one over the vocabulary. A model without any word is uniform.

Words are known by 64-bit digests and pairs by 64-bit digests of both, so the models grow with the corpus;
n distinct pairs share a digest n ** 2 / 2 ** 65 times. Documents are dealt to chunks of about CHUNK bytes. A
chunk sends its distinct digests with its counts, sorted, cut by the digests' first bits into one packed string
for each bucket; a bucket sums what all chunks sent and returns each chunk the sums of what it had sent, in
the same order. No model is ever in one place: a task holds one chunk of text, or a bucket, which gets
about what BUCKET bytes of text send and at most one entry of each digest from each chunk.

Defined results: a document without words, or null, has losses and score null; a document counts once for
each row, and is target if any label of its doc_id is good; repeats are documents of their own. Rows
with a null or repeated doc_id each get a row; those of one doc_id are in one chunk. Other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from subwin.llm.common import table, texts
from subwin.storage import Scratch

#: Weights of pair, word and uniform model; bytes of text in a chunk and for a bucket.
MIX = (0.55, 0.4, 0.05)
CHUNK, BUCKET = 8 << 20, 16 << 20
START = 0x51ED270B
WORDS, PAIRS, TOTALS, LABELS = range(4)


def pack(values: np.ndarray) -> bytes:
    """Whole numbers as the compressed planes of their bytes."""
    return zstandard.compress(np.ascontiguousarray(values.astype("<u8").view(np.uint8).reshape(-1, 8).T).tobytes(), 1)


def unpack(packed: bytes) -> np.ndarray:
    planes = np.frombuffer(zstandard.decompress(packed), np.uint8).reshape(8, -1)
    return np.ascontiguousarray(planes.T).view("<u8").ravel()


class Grams:
    """Words and pairs of a chunk: sorted distinct digests, and the number of each occurrence's word, word before and pair."""

    def __init__(self, docs: pa.Table):
        found, lengths = [np.empty(0, np.uint64)], []
        for batch in docs.to_batches():
            for text in texts(batch):
                words = text.encode().split()
                lengths.append(len(words))
                found.append(np.fromiter(map(xxhash.xxh3_64_intdigest, words), np.uint64, len(words)))
        self.lengths = np.array(lengths, np.int64)
        self.of = np.repeat(np.arange(len(lengths)), self.lengths)
        digests = np.append(np.concatenate(found), np.uint64(START))
        self.words, number = np.unique(digests, return_inverse=True)
        self.word = number[:-1]
        self.before = np.append(number[-1], number[:-2])[: len(self.word)]
        self.before[(np.cumsum(self.lengths) - self.lengths)[self.lengths > 0]] = number[-1]
        pair = self.words[self.before] * np.uint64(0x9E3779B97F4A7C15) + self.words[self.word]
        pair ^= pair >> np.uint64(31)
        pair *= np.uint64(0xBF58476D1CE4E5B9)
        self.pairs, self.pair = np.unique(pair, return_inverse=True)

    def own(self, number: np.ndarray) -> np.ndarray:
        """How often the number of each occurrence stands in its document."""
        _, which, times = np.unique(self.of * (int(number.max(initial=0)) + 1) + number, return_inverse=True, return_counts=True)
        return times[which]


def good_rows(docs: pa.Table, good: pa.ChunkedArray) -> np.ndarray:
    return pc.is_in(docs["doc_id"], value_set=good.combine_chunks().drop_null()).to_numpy(zero_copy_only=False).astype(bool)


def count(rows: DataFrame, good: DataFrame, bits: int) -> DataFrame:
    """chunk, kind, bucket, keys, counts: what the chunks send. Of words, counts as a word and as the one before, in all and in target documents; of pairs, in all and in target documents."""

    def run(docs: pa.Table, good: pa.Table) -> pa.Table:
        chunk = (docs if docs.num_rows else good)["chunk"][0].as_py()
        grams = Grams(docs.select(["text"]))
        mine = good_rows(docs, good["doc_id"])[grams.of]
        out: list[list] = [[] for _ in range(5)]
        for kind, keys, numbers in ((WORDS, grams.words, (grams.word, grams.before)), (PAIRS, grams.pairs, (grams.pair,))):
            counts = np.stack([np.bincount(x, minlength=len(keys)) for number in numbers for x in (number, number[mine])]) if len(keys) else np.empty((2 * len(numbers), 0))
            bucket = (keys >> np.uint64(64 - bits)).astype(np.int64) if bits else np.zeros(len(keys), np.int64)
            starts = np.flatnonzero(np.diff(bucket, prepend=-1))
            for a, b in zip(starts, [*starts[1:], len(keys)], strict=True):
                for column, value in zip(out, (chunk, kind, int(bucket[a]), pack(np.diff(keys[a:b], prepend=np.uint64(0))), pack(counts[:, a:b].ravel())), strict=True):
                    column.append(value)
        return pa.table([pa.array(x, t) for x, t in zip(out, (pa.int32(), pa.int32(), pa.int32(), pa.binary(), pa.binary()), strict=True)], names=["chunk", "kind", "bucket", "keys", "counts"])

    return rows.groupBy("chunk").cogroup(good.groupBy("chunk")).applyInArrow(run, "chunk int, kind int, bucket int, keys binary, counts binary")


def add_up(sent: DataFrame) -> DataFrame:
    """chunk, kind, bucket, sums: to each chunk the sums of what it has sent; and of each bucket of words, without a chunk, words of the vocabulary, occurrences, and occurrences in target documents."""

    def run(rows: pa.Table) -> pa.Table:
        kind, bucket = rows["kind"][0].as_py(), rows["bucket"][0].as_py()
        keys = [np.cumsum(unpack(x)) for x in rows["keys"].to_pylist()]
        known, where = np.unique(np.concatenate(keys), return_inverse=True)
        counts = np.concatenate([unpack(x).reshape(-1, len(k)) for x, k in zip(rows["counts"].to_pylist(), keys, strict=True)], axis=1)
        sums = np.stack([np.bincount(where, c, len(known)) for c in counts]).astype(np.uint64)
        ends = np.cumsum([len(k) for k in keys])
        out = [pack(sums[:, where[b - len(k) : b]].ravel()) for k, b in zip(keys, ends, strict=True)]
        chunks, kinds = rows["chunk"].to_pylist(), [kind] * len(keys)
        if kind == WORDS:
            out, chunks, kinds = [*out, pack(np.array([np.count_nonzero(sums[0]), sums[0].sum(), sums[1].sum()]))], [*chunks, None], [*kinds, TOTALS]
        return pa.table([pa.array(chunks, pa.int32()), pa.array(kinds, pa.int32()), pa.array([bucket] * len(out), pa.int32()), pa.array(out, pa.binary())], names=["chunk", "kind", "bucket", "sums"])

    return sent.groupBy("bucket", "kind").applyInArrow(run, "chunk int, kind int, bucket int, sums binary")


def probabilities(pair, before, word, total, size: int, mix=MIX):
    """Of counts of the pair, of the word before and of the word, of all words, and of the vocabulary."""
    paired = np.where(before > 0, mix[0], 0.0)
    flat = np.where(total > 0, mix[2], 1.0)
    return paired * pair / np.maximum(before, 1) + (1 - flat - np.where(total > 0, paired, 0.0)) * word / np.maximum(total, 1) + flat / max(size, 1)


def score(docs: DataFrame, labels: DataFrame, mix=MIX, chunk: int = CHUNK, bucket: int = BUCKET) -> DataFrame:
    """doc_id, n_words, target_loss, background_loss and score of each document (doc_id, text), given labels (doc_id, quality)."""
    id_type = docs.schema["doc_id"].dataType.simpleString()
    size = int(docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0)
    dealt = lambda key: F.pmod(key, F.lit(size // chunk + 1)).cast("int").alias("chunk")
    by_id = F.xxhash64(F.col("doc_id"))
    rows = docs.select(dealt(F.when(F.col("doc_id").isNull(), F.xxhash64("text")).otherwise(by_id)), "doc_id", "text")
    good = labels.where("quality = 1 and doc_id is not null").select(F.col("doc_id").cast(id_type).alias("doc_id")).distinct().select(dealt(by_id), "doc_id")
    summed = Scratch(docs.sparkSession, "lm").save(add_up(count(rows, good, (size // bucket).bit_length())), "summed")
    totals = [unpack(bytes(x.sums)) for x in summed.where(f"kind = {TOTALS}").select("sums").collect()]
    known, *totals = map(int, sum(totals)) if totals else (0, 0, 0)

    def run(docs: pa.Table, sums: pa.Table) -> pa.Table:
        grams = Grams(docs.select(["text"]))
        good = good_rows(docs, sums.filter(pc.equal(sums["kind"], LABELS))["doc_id"])
        sums = sums.filter(pc.less(sums["kind"], TOTALS)).sort_by([("kind", "ascending"), ("bucket", "ascending")])
        parts: list[list] = [[np.empty((4, 0))], [np.empty((2, 0))]]
        for kind, packed in zip(sums["kind"].to_pylist(), sums["sums"].to_pylist(), strict=True):
            parts[kind].append(unpack(packed).reshape(4 if kind == WORDS else 2, -1))
        words, pairs = (np.concatenate(x, axis=1) for x in parts)
        own = [grams.own(x) for x in (grams.pair, grams.before, grams.word)]
        found = []
        for model, total in enumerate(totals):
            held = np.ones(len(good)) if model == 0 else good.astype(float)
            counts = (pairs[model, grams.pair], words[2 + model, grams.before], words[model, grams.word])
            p = probabilities(*(c - o * held[grams.of] for c, o in zip(counts, own, strict=True)), (total - grams.lengths * held)[grams.of], known, mix)
            found.append(np.bincount(grams.of, -np.log(p), len(good)) / np.maximum(grams.lengths, 1))
        none = grams.lengths == 0
        return pa.table([docs["doc_id"], pa.array(grams.lengths), pa.array(found[1], mask=none), pa.array(found[0], mask=none)], names=["doc_id", "n_words", "target_loss", "background_loss"])

    back = summed.where(f"kind < {TOTALS}").withColumn("doc_id", F.lit(None).cast(id_type))
    back = back.unionByName(good.select("chunk", F.lit(LABELS).alias("kind"), F.lit(0).alias("bucket"), F.lit(None).cast("binary").alias("sums"), "doc_id"))
    scored = rows.groupBy("chunk").cogroup(back.groupBy("chunk")).applyInArrow(run, f"doc_id {id_type}, n_words long, target_loss double, background_loss double")
    return scored.withColumn("score", F.col("target_loss") - F.col("background_loss"))


def op4_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))

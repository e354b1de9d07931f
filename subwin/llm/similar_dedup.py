"""Near-dedup by the similarity of shingles: texts link if the Jaccard similarity of their sets of shingles is at least LEAST.

Candidates come from min-hashes: BANDS bands of ROWS minima each. Texts that share a band are candidates if at
least ENOUGH of all their minima agree, which takes a byte of each, and candidates are compared by their whole
sets of shingles. A pair of similarity 0.8 shares no band with chance (1 - 0.8 ** ROWS) ** BANDS, 3e-6, and fewer
than ENOUGH minima with chance 6e-7; nothing is linked that isn't similar enough.

A band that many texts share isn't paired out. In each of TURNS turns a member drawn for every band is compared
with the members of other components. What then still is outside the band's largest component meets
all members in blocks of about BLOCK such outsiders, or fewer where they are long, and only links leave a block.
So a group of copies costs about its size; the blocks alone cost the outsiders times the group, in comparisons of
160 bytes, and of whole sets for what agrees.

Fingerprints as in ``simhash_dedup`` don't serve here: at a similarity of 0.8 two of them differ in about
ten bits of 64, more than segments can index.

Defined results: shingles are hashes of WIDTH words in a row, ASCII letters lowered; texts of equal words are
one node; texts without words, or null, are one node and link with no other. Rows and names of components
are as in ``simhash_dedup``.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from subwin.llm.common import map_batches, partitions, text_key, texts
from subwin.llm.simhash_dedup import ASCII_LOWER, components, shingles
from subwin.storage import Scratch

WIDTH, LEAST = 5, 0.8
BANDS, ROWS = 32, 5
#: Least number of agreeing minima, of BANDS * ROWS, for a comparison by shingles.
ENOUGH = 102
TURNS, BLOCK = 1, 1024
_RANDOM = np.random.default_rng(20).integers(0, 2**64, (2, BANDS * ROWS), np.uint64)
_XOR, _ODD = _RANDOM[0], _RANDOM[1] | np.uint64(1)


def _minima(hashes: np.ndarray) -> np.ndarray:
    """The least of each of the BANDS * ROWS rehashes of ``hashes``; the greatest number for none."""
    least = np.full(BANDS * ROWS, 2**64 - 1, np.uint64)
    for part in np.array_split(hashes, len(hashes) // 1024 + 1):
        mixed = (part[:, None] ^ _XOR) * _ODD
        mixed ^= mixed >> np.uint64(32)
        mixed *= np.uint64(0x9E3779B97F4A7C15)
        np.minimum(least, mixed.min(axis=0, initial=2**64 - 1), out=least)
    return least


def bands(least: np.ndarray) -> list[int]:
    """A digest of each band's number and minima."""
    packed, size = least.tobytes(), ROWS * 8
    return [xxhash.xxh64_intdigest(packed[i * size : (i + 1) * size], i) for i in range(BANDS)]


def signature(least: np.ndarray, digests: list[int]) -> bytes:
    """A byte of each of the minima, then four of each band's digest (zeros for no bands)."""
    return least.astype(np.uint8).tobytes() + np.array(digests or [0] * BANDS, np.uint64).astype(np.uint32).tobytes()


def similarity(a: np.ndarray, b: np.ndarray) -> float:
    """Jaccard similarity of two sets, sorted and each without repeats."""
    both = len(np.intersect1d(a, b, assume_unique=True))
    return both / max(1, len(a) + len(b) - both)


def _signed(values: list[int]) -> np.ndarray:
    return np.array(values, np.uint64).view(np.int64)


def sketched(docs: DataFrame, width: int = WIDTH) -> DataFrame:
    """doc_id, text_key, node (a digest of the words), n (shingles), bands and sig (see ``signature``) of each document; no bands for no words."""

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        nodes, sizes, found, sigs = [], [], [], []
        for text in texts(batch):
            nodes.append(xxhash.xxh64_intdigest(b" ".join(text.encode().translate(ASCII_LOWER).split())))
            hashes = np.unique(shingles(text, width))
            least = _minima(hashes)
            sizes.append(len(hashes))
            digests = bands(least) if len(hashes) else []
            found.append(_signed(digests))
            sigs.append(signature(least, digests))
        return pa.RecordBatch.from_arrays(
            [batch.column(0), batch.column(1), pa.array(_signed(nodes)), pa.array(sizes, pa.int64()), pa.array(found, pa.list_(pa.int64())), pa.array(sigs, pa.binary())], names=["doc_id", "text_key", "node", "n", "bands", "sig"]
        )

    kind = docs.schema["doc_id"].dataType.simpleString()
    return map_batches(docs.select("doc_id", text_key(F.col("text")).alias("text_key"), "text"), run, f"doc_id {kind}, text_key long, node long, n long, bands array<long>, sig binary")


def _sketch(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The signatures of a column: rows of bytes of the minima, rows of digests."""
    whole = np.frombuffer(b"".join(column.to_pylist()), np.uint8).reshape(len(column), BANDS * (ROWS + 4))
    return whole[:, : BANDS * ROWS], np.ascontiguousarray(whole[:, BANDS * ROWS :]).view(np.uint32)


def _pairs(a: np.ndarray, b: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(np.minimum(a, b)), pa.array(np.maximum(a, b))], names=["a", "b"])


def _agreeing(batch: pa.RecordBatch) -> pa.RecordBatch:
    """Of rows (a, b, sa, sb) the pairs whose signatures agree enough."""
    near = (_sketch(batch.column(2))[0] == _sketch(batch.column(3))[0]).sum(axis=1) >= ENOUGH
    return _pairs(*(batch.column(i).to_numpy()[near] for i in range(2)))


def _overlaps(own: np.ndarray, others: list[np.ndarray]) -> np.ndarray:
    """How many members of each of ``others`` are in ``own``; all sorted, without repeats, not empty."""
    joined = np.concatenate(others)
    hit = own[np.minimum(np.searchsorted(own, joined), len(own) - 1)] == joined
    return np.add.reduceat(hit.astype(np.int64), np.cumsum([0, *map(len, others[:-1])]))


def _block(batches: Iterator[pa.RecordBatch], least: float) -> Iterator[pa.RecordBatch]:
    """Of rows (band, block, asks, slot, node, root, n, sig, hashes), sorted by band, block and those that ask first: links between roots.

    ``slot`` is the number of the band; a pair that shares more bands is compared in the first of them.
    """
    last, held = None, []
    for batch in batches:
        band, block, asks, slot, node, root, n = (batch.column(i).to_numpy(zero_copy_only=False) for i in range(7))
        (sigs, digests), sets = _sketch(batch.column(7)), [np.frombuffer(x, np.uint64) for x in batch.column(8).to_pylist()]
        cuts = np.flatnonzero((band[1:] != band[:-1]) | (block[1:] != block[:-1])) + 1
        found: list[tuple[np.ndarray, np.ndarray]] = []
        for start, end in zip([0, *cuts.tolist()], [*cuts.tolist(), len(band)], strict=True):
            if (band[start], block[start]) != last:
                last, held = (band[start], block[start]), []
            for i in range(start, start + int(asks[start:end].sum())):
                held.append((node[i], root[i], sigs[i].copy(), digests[i].copy(), sets[i].copy()))
            for x, of, sig, digest, own in held:
                may = ((sigs[start:end] == sig).sum(axis=1) >= ENOUGH) & (root[start:end] != of) & (np.minimum(n[start:end], len(own)) / np.maximum(n[start:end], len(own)) >= least)
                at = np.flatnonzero(may) + start
                at = at[(digests[at] == digest).argmax(axis=1) == slot[start]]
                if len(at):
                    both = _overlaps(own, [sets[i] for i in at])
                    at = at[both / (len(own) + n[at] - both) >= least]
                    found.append((np.full(len(at), x), node[at]))
        if found:
            yield _pairs(*(np.concatenate(x) for x in zip(*found, strict=True)))


def turn_pairs(placed: DataFrame, turn: int, least: float = LEAST) -> DataFrame:
    """Agreeing pairs of one member of each band of ``placed`` (band, node, root, n, sig), drawn by ``turn``, with those of other roots."""
    drawn = F.struct(F.xxhash64("node", "band", F.lit(turn)).alias("order"), "node", "root", "n", "sig")
    hubs = placed.groupBy("band").agg(F.min(drawn).alias("hub"), F.min("root").alias("r"), F.max("root").alias("s")).where("r < s")
    hubs = hubs.select("band", F.col("hub.node").alias("a"), F.col("hub.root").alias("of"), F.col("hub.n").alias("size"), F.col("hub.sig").alias("sa"))
    sized = F.least("n", "size") / F.greatest("n", "size") >= least
    met = placed.join(hubs, "band").where((F.col("root") != F.col("of")) & sized).select("a", F.col("node").alias("b"), "sa", F.col("sig").alias("sb"))
    return map_batches(met, _agreeing, "a long, b long").distinct()


def rest_links(placed: DataFrame, bodies: DataFrame, width: int = WIDTH, least: float = LEAST, block: int = BLOCK) -> DataFrame:
    """Links of each member outside the largest component of its band (``placed`` as in ``turn_pairs``, with slot) with members of other roots."""

    def hashed(batch: pa.RecordBatch) -> pa.RecordBatch:
        sets = [np.unique(shingles(x, width)).tobytes() for x in texts(batch)]
        return pa.RecordBatch.from_arrays([batch.column(0), pa.array(sets, pa.binary())], names=["node", "hashes"])

    sizes = placed.groupBy("band", "root").agg(F.count("*").alias("size"), F.sum("n").alias("n"))
    split = sizes.groupBy("band").agg(F.max(F.struct("size", "root", "n")).alias("most"), F.sum("size").alias("size"), F.sum("n").alias("n")).where("size > most.size")
    blocks = F.ceil(F.greatest((F.col("size") - F.col("most.size")) / block, (F.col("n") - F.col("most.n")) / (block * 2048)))
    split = split.select("band", F.col("most.root").alias("main"), blocks.cast("int").alias("blocks"))
    own = F.when(F.col("root") != F.col("main"), F.pmod(F.xxhash64("node"), F.col("blocks")))
    open_ = placed.join(split, "band")
    sets = map_batches(bodies.join(open_.select("node").distinct(), "node", "left_semi").select("node", "text"), hashed, "node long, hashes binary")
    dealt = open_.join(sets, "node").withColumn("own", own).withColumn("block", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    rows = dealt.select("band", "block", F.coalesce(F.col("own") == F.col("block"), F.lit(False)).alias("asks"), "slot", "node", "root", "n", "sig", "hashes")
    dealt = rows.repartition(partitions(placed.sparkSession), "band", "block").sortWithinPartitions("band", "block", F.desc("asks"))
    return dealt.mapInArrow(lambda batches: _block(batches, least), "a long, b long").distinct()


def alike(pairs: DataFrame, bodies: DataFrame, width: int = WIDTH, least: float = LEAST) -> DataFrame:
    """Those of ``pairs`` (a, b) whose texts, in ``bodies`` (node, text), are similar enough."""

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        last: tuple = (None, None)
        keep = []
        for a, left, right in zip(batch.column(0).to_pylist(), texts(batch, "left"), texts(batch, "right"), strict=True):
            if a != last[0]:
                last = (a, np.unique(shingles(left, width)))
            keep.append(similarity(last[1], np.unique(shingles(right, width))) >= least)
        return pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], names=["a", "b"]).filter(pa.array(keep, pa.bool_()))

    left, right = bodies.select(F.col("node").alias("a"), F.col("text").alias("left")), bodies.select(F.col("node").alias("b"), F.col("text").alias("right"))
    return map_batches(pairs.join(left, "a").join(right, "b").select("a", "b", "left", "right"), run, "a long, b long")


def classes(printed: DataFrame, docs: DataFrame, scratch: Scratch, width: int = WIDTH, least: float = LEAST, block: int = BLOCK) -> DataFrame:
    """node and component_id of each node of ``printed`` (see ``sketched``), whose texts are in ``docs``."""
    nodes = scratch.save(printed.groupBy("node").agg(F.min("doc_id").alias("least"), F.min("text_key").alias("text_key"), F.first("n").alias("n"), F.first("sig").alias("sig")), "nodes")
    banded = printed.select("node", F.posexplode("bands").alias("slot", "band")).distinct()
    common = banded.groupBy("band").agg(F.min("node").alias("r"), F.max("node").alias("s")).where("r < s").select("band")
    shared = scratch.save(banded.join(common, "band"), "shared")
    # the texts that may be compared, one for each node that shares a band
    known = nodes.join(shared.select("node").distinct(), "node").select("node", F.col("text_key").alias("key"))
    keyed = docs.select(text_key(F.col("text")).alias("key"), "text")
    bodies = scratch.save(keyed.join(known, "key").groupBy("node").agg(F.first("text").alias("text")), "bodies")
    members = shared.join(nodes.select("node", "n", "sig"), "node")
    placed, edges = members.withColumn("root", F.col("node")), None
    for turn in range(TURNS + 1):
        if turn < TURNS:
            linked = alike(scratch.save(turn_pairs(placed, turn, least), f"pairs{turn}"), bodies, width, least)
        else:
            linked = rest_links(placed, bodies, width, least, block)
        linked = scratch.save(linked, f"linked{turn}")
        if turn and linked.isEmpty():
            continue
        edges = edges.unionByName(linked) if turn else linked
        roots = components(edges, Scratch(docs.sparkSession, "similar")).withColumnRenamed("node", "of")
        if turn < TURNS:
            placed = scratch.save(members.join(roots, F.col("node") == F.col("of"), "left").select("band", "slot", "node", F.coalesce("root", "node").alias("root"), "n", "sig"), f"placed{turn}")
    rooted = nodes.join(roots, F.col("node") == F.col("of"), "left").select("node", "least", F.coalesce("root", "node").alias("root"))
    named = rooted.groupBy("root").agg(F.min("least").alias("component_id"))
    found = scratch.save(rooted.join(named, "root").select("node", "root", "component_id"), "classes")
    for name in ("nodes", "shared", "bodies", *(f"{x}{turn}" for x in ("pairs", "placed", "linked") for turn in range(TURNS + 1))):
        scratch.drop(name)
    return found


def drop_similar(docs: DataFrame, width: int = WIDTH, least: float = LEAST) -> DataFrame:
    """``docs`` (doc_id, text, ...) with the row of the smallest doc_id of each component; all columns stay.

    Rows alike in doc_id and text are one; where rows of one id differ in text, the one of the least text hash stays.
    """
    scratch = Scratch(docs.sparkSession, "similar")
    printed = scratch.save(sketched(docs, width), "printed")
    placed = printed.drop("bands", "n", "sig").join(classes(printed, docs, scratch, width, least), "node")
    kept = placed.groupBy("root").agg(F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "text_key")).alias("first"))
    kept = kept.select(F.col("first.doc_id").alias("_subwin_id"), F.col("first.text_key").alias("_subwin_key")).distinct()
    keyed = docs.withColumn("_subwin_text", text_key(docs["text"]))
    found = keyed.join(kept, (keyed["_subwin_text"] == kept["_subwin_key"]) & keyed["doc_id"].eqNullSafe(kept["_subwin_id"]), "left_semi")
    return found.dropDuplicates(["_subwin_text", "doc_id"]).select(*[F.col(f"`{c}`") for c in docs.columns])

"""Exact dedup by a persistent digest index, bucketed and sorted by digest.

Texts are equal when they are the same after each run of ASCII white space is replaced by one space.
The index is a table of one row for each distinct text: digest, keep_id. A batch is first reduced to
its distinct digests by a partial and a final aggregate, so a text that a third of all rows share is
one row before any join; a sort-merge anti-join against the index, whose buckets need no shuffle, then
finds the digests that are new, and these are appended.

Defined results: a null text is an empty one; of equal texts the smallest doc_id stays, a null one only
if all are null; of repeated rows of that id, one. Other columns are ignored, or kept where rows are
returned whole. All of it is built-in functions.
"""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from subwin.llm.common import WHITE_RE, partitions, table
from subwin.storage import Scratch


def digest(text: Column) -> Column:
    """SHA-256 of the normalised text, 32 bytes."""
    return F.unhex(F.sha2(F.regexp_replace(F.coalesce(text, F.lit("")), f"{WHITE_RE}+", " "), 256))


class DigestIndex:
    """The persistent index: Parquet at ``path``, in the catalogue as ``name``, in ``buckets`` sorted buckets."""

    def __init__(self, spark: SparkSession, path: str, buckets: int, name: str | None = None, id_type: str = "bigint"):
        self.spark, self.name = spark, name or f"digests_{uuid.uuid4().hex}"
        self.path, self.buckets = path, buckets
        spark.sql(f"CREATE TABLE IF NOT EXISTS {self.name} (digest BINARY, keep_id {id_type}) USING parquet CLUSTERED BY (digest) SORTED BY (digest) INTO {buckets} BUCKETS LOCATION '{path}'")

    def close(self) -> None:
        """Take the index out of the catalogue. Its files stay: a table of the same name over the same path has it again."""
        self.spark.sql(f"DROP TABLE IF EXISTS {self.name}")

    def compact(self, path: str) -> None:
        """Write the index anew at ``path``, one sorted file for each bucket, which appends have made several of; then use that."""
        schema = self.rows().schema
        fresh = DigestIndex(self.spark, path, self.buckets, f"{self.name}_{uuid.uuid4().hex[:8]}", schema["keep_id"].dataType.simpleString())
        # as plain files: of the bucketed table the shuffle would be left out, and then the buckets be scanned as plain files all the same
        fresh._write(self.spark.read.schema(schema).parquet(self.path))
        self.close()
        self.spark.sql(f"ALTER TABLE {fresh.name} RENAME TO {self.name}")
        self.path = path

    def _write(self, rows: DataFrame) -> None:
        rows.select("digest", "keep_id").repartition(self.buckets, "digest").sortWithinPartitions("digest").write.mode("append").format("parquet").bucketBy(self.buckets, "digest").sortBy("digest").option("path", self.path).saveAsTable(self.name)

    def rows(self) -> DataFrame:
        return self.spark.table(self.name)

    def append(self, keepers: DataFrame) -> None:
        """Append the digests (digest, keep_id) that the index lacks."""
        known = self.rows()
        self._write(keepers.join(known.select("digest").hint("merge"), "digest", "left_anti"))

    def ingest(self, docs: DataFrame) -> DataFrame:
        """Index a batch (doc_id, text); a row for each of its documents: doc_id, digest, keep_id, group_size (in the batch), kept.

        A text that the index had before is kept by no row of the batch.
        """
        scratch = Scratch(self.spark, "dedup")
        rows = docs.select("doc_id", digest(F.col("text")).alias("digest"))
        # repeats of an id with one text are one row from here
        units = scratch.save(rows.groupBy("digest", "doc_id").agg(F.count("*").alias("n")), "units")
        groups = units.groupBy("digest").agg(F.min("doc_id").alias("batch_id"), F.sum("n").alias("group_size"))
        before = self.rows().select("digest", F.col("keep_id").alias("old_id"), F.lit(True).alias("old"))
        groups = scratch.save(groups.join(before.hint("merge"), "digest", "left").select("digest", F.coalesce("old_id", "batch_id").alias("keep_id"), "group_size", F.col("old").isNull().alias("new")), "groups")
        self.append(groups.where("new").select("digest", "keep_id"))
        judged = units.join(groups, "digest").select("doc_id", "digest", "keep_id", "group_size", (F.col("new") & F.col("doc_id").eqNullSafe(F.col("keep_id"))).alias("keeper"), F.explode(F.sequence(F.lit(1).cast("long"), F.col("n"))).alias("nth"))
        return judged.select("doc_id", "digest", "keep_id", "group_size", (F.col("keeper") & (F.col("nth") == 1)).alias("kept"))


def fresh_index(docs: DataFrame) -> DigestIndex:
    spark = docs.sparkSession
    return DigestIndex(spark, Scratch(spark, "digests").root + "/index", partitions(spark), id_type=docs.schema["doc_id"].dataType.simpleString())


def ingest_once(docs: DataFrame) -> DataFrame:
    """``ingest`` into a fresh index that is given up again: what it returns reads no index."""
    index = fresh_index(docs)
    found = index.ingest(docs)
    index.close()
    return found


def drop_copies(docs: DataFrame, index: DigestIndex | None = None) -> DataFrame:
    """``docs`` (doc_id, text, ...) with one row of each group of equal texts, and none of a group that ``index`` had; all columns stay."""
    kept = (index.ingest(docs) if index else ingest_once(docs)).where("kept").select(F.col("doc_id").alias("_subwin_id"), F.col("digest").alias("_subwin_digest"))
    keyed = docs.withColumn("_subwin_text", digest(F.col("text")))
    found = keyed.join(kept, keyed["_subwin_text"].eqNullSafe(kept["_subwin_digest"]) & keyed["doc_id"].eqNullSafe(kept["_subwin_id"]), "left_semi")
    return found.dropDuplicates(["_subwin_text", "doc_id"]).select(*[F.col(f"`{c}`") for c in docs.columns])


def op7_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return ingest_once(docs).select("doc_id", "keep_id", "group_size", "kept", F.lower(F.hex("digest")).alias("text_sha256"))


OP7_SQL = r"""
WITH d AS (SELECT doc_id, sha256(regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g')) AS text_sha256 FROM documents)
SELECT doc_id, min(doc_id) OVER g AS keep_id, count(*) OVER g AS group_size,
    row_number() OVER (PARTITION BY text_sha256 ORDER BY doc_id NULLS LAST) = 1 AS kept, text_sha256
FROM d WINDOW g AS (PARTITION BY text_sha256)
"""

"""What the operators share: words, row keys, batches."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: ASCII white space: the bytes that bytes.split() splits on, and the class for Java's regular expressions.
WHITE = b" \t\n\x0b\x0c\r"
WHITE_RE = r"[\x20\x09-\x0D]"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def text_key(text: Column) -> Column:
    """Second half of a row's key (doc_id, hash of the text): rows alike in both are repeats of one document."""
    return F.xxhash64(F.coalesce(text, F.lit("")))


def join_same(left: DataFrame, right: DataFrame, names: list[str], how: str = "inner") -> DataFrame:
    """Join on columns of equal names, null being equal to null; the left's columns, then the right's others."""
    renamed = right.withColumnsRenamed({n: f"_subwin_{n}" for n in names})
    on = F.lit(True)
    for n in names:
        on = on & left[n].eqNullSafe(renamed[f"_subwin_{n}"])
    return left.join(renamed, on, how).drop(*[f"_subwin_{n}" for n in names])


def map_batches(df: DataFrame, fn: Callable[[pa.RecordBatch], pa.RecordBatch | None], schema: str) -> DataFrame:
    """mapInArrow with a function of one batch."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows and (out := fn(batch)) is not None and out.num_rows:
                yield out

    return df.mapInArrow(run, schema)


def texts(batch: pa.RecordBatch, name: str = "text") -> Iterator[str]:
    """The texts of a batch one at a time, null as empty."""
    for x in batch.column(batch.schema.get_field_index(name)):
        yield x.as_py() or ""

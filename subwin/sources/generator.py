"""Generated samples as a data source, and table functions for SQL."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.functions import udtf

from subwin.operators.eh import layout_sql
from subwin.sources.views import EPOCH, PRIME, STEP, TOP, synthetic


class UniformSource(DataSource):
    """``spark.read.format("subwin_uniform")`` with options series and samples: the uniform law, row by row."""

    @classmethod
    def name(cls) -> str:
        return "subwin_uniform"

    def schema(self) -> str:
        return "series string, t long, seq long, value double, item string"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(int(self.options.get("series", 1)), int(self.options.get("samples", 1000)))


class _Reader(DataSourceReader):
    def __init__(self, series: int, samples: int):
        self.series, self.samples = series, samples

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(s) for s in range(self.series)]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        for seq in range(1, self.samples + 1):
            at = partition.value * self.samples + seq - 1
            u = ((at % 1000003 + 1) * 48271 + at // 1000003 * 7919 + 17) % PRIME * 69621 % PRIME / PRIME
            value = float(int(u * TOP))
            yield str(partition.value), EPOCH + seq * STEP, seq, value, str(int(value))


class EhLayout:
    """Table function eh_layout(n, k): bucket (1 the oldest) and size of a count layout."""

    def eval(self, n: int, k: int):
        counts, at, cap = [], n, k
        while at > 0:
            moved = max(0, (at - cap) // 2)
            counts.append(at - 2 * moved)
            at, cap = moved, -(-k // 2)
        bucket = 0
        for level in range(len(counts) - 1, -1, -1):
            for _ in range(counts[level]):
                bucket += 1
                yield bucket, 1 << level


def register(spark: SparkSession) -> None:
    """Make the source and the table function known to SQL."""
    spark.dataSource.register(UniformSource)
    spark.udtf.register("eh_layout", udtf(EhLayout, returnType="bucket bigint, size bigint"))


def layout_function(spark: SparkSession, sf_dir: str) -> DataFrame:
    register(spark)
    return spark.sql("SELECT * FROM eh_layout(10000, 20)")


def generated(law: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return synthetic(spark, law, 3, 2000)

    return run


def source(spark: SparkSession, sf_dir: str) -> DataFrame:
    register(spark)
    return spark.read.format("subwin_uniform").option("series", 3).option("samples", 2000).load()


_UNIFORM = f"SELECT (id // 2000)::VARCHAR AS series, {EPOCH} + (id % 2000 + 1) * {STEP} AS t, id % 2000 + 1 AS seq, value, value::BIGINT::VARCHAR AS item FROM (SELECT id, floor(((((id % 1000003 + 1) * 48271 + (id // 1000003) * 7919 + 17) % {PRIME}) * 69621 % {PRIME}) / {PRIME}::DOUBLE * {TOP}) AS value FROM range(6000) r(id))"
QUERIES: dict = {"source_generator_uniform": generated("uniform"), "source_generator_zipf": generated("zipf"), "source_generator_dynamic": generated("dynamic"), "source_python": source, "udtf_layout": layout_function}
SQL: dict = {
    "source_generator_uniform": _UNIFORM, "source_python": _UNIFORM,
    "udtf_layout": layout_sql("SELECT 'x' AS series, i AS seq, 0 AS t, 0.0 AS value, '' AS item FROM range(1, 10001) r(i)", 20) + "SELECT bucket, count(*) AS size FROM placed GROUP BY bucket",
}

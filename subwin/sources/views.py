"""Series views: samples (series, t, seq, value, item) of the given tables.

``t`` is epoch microseconds, ``seq`` the 1-based position inside the series in a total order. Each view
also has its SQL, for comparison.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from subwin.storage import Scratch

DAY = 86_400_000_000
#: Synthetic timestamps start here and step by this much.
EPOCH, STEP = 1_704_067_200_000_000, 100_000
#: Panes of a block in the two-level prefix sums of position().
PANES = 1024


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def micros(column: str) -> str:
    """A timestamp without time zone as epoch microseconds, whatever the session's zone."""
    return f"timestampdiff(MICROSECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', {column})"


def position(base: DataFrame, order: list[str], counted: bool = False) -> DataFrame:
    """Adds seq to ``base`` (series, pane, ...): panes are counted, their counts summed up in blocks, and
    rows numbered within panes only, so that one series of any length is spread over tasks. ``counted`` adds n,
    the number of rows of the series, from the same counts."""
    panes = base.groupBy("series", "pane").agg(F.count("*").alias("n")).withColumn("block", F.floor(F.col("pane") / PANES))
    blocks = panes.groupBy("series", "block").agg(F.sum("n").alias("n"))
    before = Window.partitionBy("series").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.partitionBy("series")
    blocks = blocks.select("series", "block", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("past"), *[F.sum("n").over(whole).alias("total")] * counted)
    within = Window.partitionBy("series", "block").orderBy("pane").rowsBetween(Window.unboundedPreceding, -1)
    starts = panes.select("series", "block", "pane", F.coalesce(F.sum("n").over(within), F.lit(0)).alias("before")).join(blocks, ["series", "block"]).select("series", "pane", (F.col("past") + F.col("before")).alias("past"), *[F.col("total").alias("n")] * counted)
    # numbered first: the join finds its order in that of the numbers
    number = F.row_number().over(Window.partitionBy("series", "pane").orderBy(*order))
    return base.withColumn("nth", number).join(starts, ["series", "pane"]).withColumn("seq", F.col("past") + F.col("nth")).drop("nth", "past")


@dataclass(frozen=True)
class View:
    """How a view comes about: a select over tables in each dialect, its panes and order."""

    build: Callable[[SparkSession, str], DataFrame]
    order: list[str]
    sql: str
    timed: bool = True


#: The name of an only series, as an expression of a column: a constant would be folded out of join keys, and leave products.
_ONE = "substr(concat('all', coalesce({}, '')), 1, 3)"
_LINE = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus"]


def _events(series: str, value: str, item: str):
    return lambda spark, d: table(spark, d, "events").selectExpr(f"{series} AS series", f"{micros('ts')} AS t", f"{value} AS value", f"{item} AS item", "event_id").withColumn("pane", F.expr(f"t div {DAY}"))


def _lines(series: str):
    return lambda spark, d: table(spark, d, "lineitem").selectExpr(f"{series} AS series", f"{micros('l_shipdate')} AS t", "l_extendedprice AS value", "cast(l_partkey AS string) AS item", *_LINE).withColumn("pane", F.expr(f"t div {DAY}"))


def _orders(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "orders").selectExpr("o_orderpriority AS series", f"{micros('o_orderdate')} AS t", "o_totalprice AS value", "cast(o_custkey AS string) AS item", "o_orderkey").withColumn("pane", F.expr(f"t div {DAY}"))


def _nations(spark: SparkSession, d: str) -> DataFrame:
    orders, customer, nation = (table(spark, d, x) for x in ("orders", "customer", "nation"))
    joined = orders.join(customer, orders.o_custkey == customer.c_custkey).join(nation, customer.c_nationkey == nation.n_nationkey)
    return joined.selectExpr("n_name AS series", f"{micros('o_orderdate')} AS t", "o_totalprice AS value", "c_mktsegment AS item", "o_orderkey").withColumn("pane", F.expr(f"t div {DAY}"))


def _tokens(series: str):
    return lambda spark, d: table(spark, d, "documents").selectExpr(f"{series} AS series", "doc_id", "doc_id AS pane", "posexplode(split(lower(text), ' ')) AS (pos, item)").withColumn("value", F.length("item").cast("double"))


def _pages(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "pages").selectExpr(_ONE.format("url") + " AS series", "page_id", "page_id div 1000 AS pane", "cast(length(html) AS double) AS value", "regexp_extract(url, '://([^/?#]*)', 1) AS item")


def _turns(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "conversations").selectExpr("role AS series", "conv_id", "turn", "conv_id div 100 AS pane", "cast(length(text) AS double) AS value", "split(text, ' ')[0] AS item")


def _dimensions(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "embeddings").selectExpr("vec_id", "vec_id div 100 AS pane", "cast(label AS string) AS item", "posexplode(embedding) AS (dim, x)").selectExpr("cast(dim AS string) AS series", "vec_id", "pane", "cast(x AS double) AS value", "item")


#: Series of the views of words.
WORDS = {"doc_tokens": _ONE.format("lang"), "doc_tokens_lang": "lang"}

_EV = "SELECT {} AS series, epoch_us(ts) AS t, {} AS value, {} AS item, row_number() OVER (PARTITION BY {} ORDER BY event_id) AS seq FROM events"
_LI = "SELECT {0} AS series, epoch_us(l_shipdate) AS t, l_extendedprice AS value, cast(l_partkey AS varchar) AS item, row_number() OVER (PARTITION BY {0} ORDER BY l_shipdate, " + ", ".join(_LINE) + ") AS seq FROM lineitem"
_TOK = "SELECT series, {0} + seq * {1} AS t, cast(length(item) AS double) AS value, item, seq FROM (SELECT series, item, row_number() OVER (PARTITION BY series ORDER BY doc_id, pos) AS seq FROM (SELECT {2} AS series, doc_id, unnest(string_split(lower(text), ' ')) AS item, generate_subscripts(string_split(lower(text), ' '), 1) AS pos FROM documents))"
_K = "cast(json_extract_string(props, '$.k') AS bigint)"

VIEWS: dict[str, View] = {
    "ev_type": View(_events("event_type", "value", "cast(user_id AS string)"), ["event_id"], _EV.format("event_type", "value", "cast(user_id AS varchar)", "event_type")),
    "ev_user": View(_events("cast(user_id AS string)", "value", "event_type"), ["event_id"], _EV.format("cast(user_id AS varchar)", "value", "event_type", "user_id")),
    "ev_type_k": View(_events("event_type", "cast(get_json_object(props, '$.k') AS double)", "get_json_object(props, '$.k')"), ["event_id"], _EV.format("event_type", f"cast({_K} AS double)", f"cast({_K} AS varchar)", "event_type")),
    "li_flag": View(_lines("concat(l_returnflag, l_linestatus)"), _LINE, _LI.format("l_returnflag || l_linestatus")),
    "li_all": View(_lines(_ONE.format("l_returnflag")), _LINE, _LI.format("'all'")),
    "doc_tokens": View(_tokens(WORDS["doc_tokens"]), ["pos"], _TOK.format(EPOCH, STEP, "'all'"), False),
    "doc_tokens_lang": View(_tokens(WORDS["doc_tokens_lang"]), ["pos"], _TOK.format(EPOCH, STEP, "lang"), False),
    "ord_prio": View(_orders, ["t", "o_orderkey"], "SELECT o_orderpriority AS series, epoch_us(o_orderdate) AS t, o_totalprice AS value, cast(o_custkey AS varchar) AS item, row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_orderdate, o_orderkey) AS seq FROM orders"),
    "ord_nation": View(_nations, ["t", "o_orderkey"], "SELECT n_name AS series, epoch_us(o_orderdate) AS t, o_totalprice AS value, c_mktsegment AS item, row_number() OVER (PARTITION BY n_name ORDER BY o_orderdate, o_orderkey) AS seq FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey"),
    "page_host": View(_pages, ["page_id"], f"SELECT 'all' AS series, {EPOCH} + seq * {STEP} AS t, value, item, seq FROM (SELECT cast(length(html) AS double) AS value, regexp_extract(url, '://([^/?#]*)', 1) AS item, row_number() OVER (ORDER BY page_id) AS seq FROM pages)", False),
    "conv_role": View(_turns, ["conv_id", "turn"], f"SELECT series, {EPOCH} + seq * {STEP} AS t, value, item, seq FROM (SELECT role AS series, cast(length(text) AS double) AS value, string_split(text, ' ')[1] AS item, row_number() OVER (PARTITION BY role ORDER BY conv_id, turn) AS seq FROM conversations)", False),
    "emb_dim": View(_dimensions, ["vec_id"], f"SELECT series, {EPOCH} + seq * {STEP} AS t, value, item, seq FROM (SELECT cast(dim - 1 AS varchar) AS series, cast(x AS double) AS value, item, row_number() OVER (PARTITION BY dim ORDER BY vec_id) AS seq FROM (SELECT vec_id, cast(label AS varchar) AS item, unnest(embedding) AS x, generate_subscripts(embedding, 1) AS dim FROM embeddings))", False),
}


def series_view(spark: SparkSession, sf_dir: str, name: str, counted: bool = False, window: tuple[int, int] | None = None) -> DataFrame:
    """Samples of a view: series, t, seq, value, item; ``counted`` adds n, the number of samples of the series.

    Of a ``window`` (low, high], for views with times of their own, only its samples are read, and positions start with it.
    """
    view = VIEWS[name]
    base = view.build(spark, sf_dir)
    if window:
        if not view.timed:
            raise ValueError(f"{name} has no times of its own")
        base = base.where((F.col("t") > window[0]) & (F.col("t") <= window[1]))
    placed = position(base, view.order, counted)
    t = F.col("t") if view.timed else F.lit(EPOCH) + F.col("seq") * STEP
    return placed.select("series", t.alias("t"), "seq", "value", "item", *["n"] * counted)


def _numbered(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """series, part, nth (words of the series before, in this part), len and words of texts in order."""
    part, past = TaskContext.get().partitionId(), {}
    for batch in batches:
        series, words = batch.column(0).dictionary_encode(), batch.column(1)
        lens, codes = pc.list_value_length(words).to_numpy().astype(np.int64), series.indices.to_numpy()
        nth = np.zeros(len(lens), np.int64)
        for code, name in enumerate(series.dictionary.to_pylist()):
            at = np.flatnonzero(codes == code)
            total = past.get(name, 0) + np.cumsum(lens[at])
            nth[at], past[name] = total - lens[at], int(total[-1])
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.full(len(lens), part, np.int32)), pa.array(nth), pa.array(lens), words], names=["series", "part", "nth", "len", "words"])


def written_words(spark: SparkSession, sf_dir: str, name: str = "doc_tokens") -> DataFrame:
    """The samples of a view of words in runs, written in the order of their positions: series, n, seq and t of a run's first
    sample, step from each t to the next, len, items.

    Whole texts move, once, into ranges of ids; what precedes a part is known from the counts of the parts, so that no word
    is moved and a task that reads the table meets positions in a row.
    """
    scratch = Scratch(spark, "words")
    texts = table(spark, sf_dir, "documents").selectExpr(f"{WORDS[name]} AS series", "doc_id", "text").where("series IS NOT NULL AND doc_id IS NOT NULL AND text IS NOT NULL")
    split = F.expr("split(lower(text), ' ')")
    if not texts.groupBy("series", "doc_id").agg(F.count("*").alias("texts")).where("texts > 1").isEmpty():
        # the words of texts of one id alternate
        texts = texts.groupBy("series", "doc_id").agg(F.collect_list(split).alias("all"))
        split = F.expr("flatten(transform(sequence(0, array_max(transform(all, w -> size(w))) - 1), i -> filter(transform(all, w -> get(w, i)), x -> x IS NOT NULL)))")
    ordered = texts.repartitionByRange("series", "doc_id").sortWithinPartitions("series", "doc_id").select("series", split.alias("words"))
    stored = scratch.save(ordered.mapInArrow(_numbered, "series string, part int, nth long, len long, words array<string>"), "words")
    parts = stored.groupBy("series", "part").agg(F.sum("len").alias("words"))
    before = Window.partitionBy("series").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    starts = parts.select("series", "part", F.coalesce(F.sum("words").over(before), F.lit(0)).alias("past"), F.sum("words").over(Window.partitionBy("series")).alias("n"))
    placed = stored.join(scratch.save(starts, "starts"), ["series", "part"]).withColumn("seq", F.col("past") + F.col("nth") + 1)
    return placed.select("series", "n", "seq", (F.lit(EPOCH) + F.col("seq") * STEP).alias("t"), F.lit(STEP).cast("long").alias("step"), "len", F.col("words").alias("items"))


def runs_of(samples: DataFrame) -> DataFrame:
    """Samples as runs of one (see ``written_words``), unless they are runs."""
    if "items" in samples.columns:
        return samples
    return samples.select("series", "seq", "t", F.lit(0).cast("long").alias("step"), F.lit(1).cast("long").alias("len"), F.array("item").alias("items"))


def samples_of(runs: DataFrame) -> DataFrame:
    """The single samples of runs of words: series, t, seq, value, item, n."""
    each = runs.select("series", "n", F.col("seq").alias("at"), "t", "step", F.posexplode("items").alias("nth", "item"))
    return each.select("series", F.expr("t + nth * step").alias("t"), F.expr("at + nth").alias("seq"), F.length("item").cast("double").alias("value"), "item", "n")


def drifting(spark: SparkSession, sf_dir: str) -> DataFrame:
    """View li_drift: li_all with 0.3 for each position from the newest added to its values."""
    base = series_view(spark, sf_dir, "li_all", counted=True)
    return base.withColumn("value", F.col("value") + 0.3 * (F.col("n") - F.col("seq")))


DRIFT_SQL = f"SELECT series, t, seq, value + 0.3 * (count(*) OVER () - seq) AS value, item FROM ({VIEWS['li_all'].sql})"

#: Generated values lie in 0 to TOP; the modulus and factors of the generator's hashes.
TOP, PRIME = 100_000, 2_147_483_647
_U = f"((({{0}} * 48271 + {{1}}) % {PRIME}) * 69621 % {PRIME}) / {PRIME}.0D"


def synthetic(spark: SparkSession, law: str, series: int, samples: int, exponent: float = 1.01) -> DataFrame:
    """Generated samples: law zipf, uniform or dynamic (zipf, uniform, normal, a third of the samples each).

    Without random state, so that any engine can make the same rows: uniform numbers come from modular
    hashes of the position; Zipf by inverting the continuous law; normal as a sum of twelve uniforms.
    """
    rows = spark.range(series * samples).selectExpr(f"id div {samples} AS s", f"id % {samples} + 1 AS seq", "id")
    u = _U.format("(id % 1000003 + 1)", "(id div 1000003) * 7919 + 17")
    zipf = f"floor(pow(1 - {u} * (1 - pow({TOP}.0D, {1 - exponent}D)), {1 / (1 - exponent)}D))"
    uniform = f"floor({u} * {TOP})"
    normal = "(" + " + ".join(_U.format(f"(id % 1000003 + {31 * i + 1})", f"(id div 1000003) * 104729 + {977 * i}") for i in range(12)) + f") * 10000 - 10000"
    third = samples // 3
    value = {"zipf": zipf, "uniform": uniform, "dynamic": f"CASE WHEN seq <= {third} THEN {zipf} WHEN seq <= {2 * third} THEN {uniform} ELSE {normal} END"}[law]
    return rows.selectExpr("cast(s AS string) AS series", f"{EPOCH} + seq * {STEP} AS t", "seq", f"cast({value} AS double) AS value").withColumn("item", F.floor("value").cast("string"))

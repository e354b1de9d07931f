"""Live maintenance by Structured Streaming: windows, dedup, rejection of late samples, histogram state, ingest.

Runs end when the input at their start is worked off; results are tables that foreachBatch writes into the
shared folder, one part for each micro-batch, so that a batch that runs twice overwrites itself.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from subwin.operators import kll, sampling
from subwin.operators.eh import in_range, layout_count, layout_sql
from subwin.plans.cache import CacheStore
from subwin.sources.views import DAY, VIEWS, micros, position, series_view, table
from subwin.storage import Scratch

COLUMNS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def stream_of(spark: SparkSession, path: str, schema: str = COLUMNS, files: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(path)


def stamped(events: DataFrame) -> DataFrame:
    """With ``at``, a timestamp that watermarks accept, and its epoch microseconds ``t``."""
    return events.withColumn("t", F.expr(micros("ts"))).withColumn("at", F.timestamp_micros("t"))


def run_to_table(stream: DataFrame, scratch: Scratch, name: str, mode: str) -> DataFrame:
    """Work off the stream; its output with ``batch``, the number of the micro-batch."""
    path = f"{scratch.root}/{name}"

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")

    stream.writeStream.foreachBatch(write).outputMode(mode).option("checkpointLocation", f"{scratch.root}/{name}-state").trigger(availableNow=True).start().awaitTermination()
    return stream.sparkSession.read.schema(T.StructType([*stream.schema.fields, T.StructField("batch", T.IntegerType())])).parquet(path)


def latest(found: DataFrame, keys: list[str]) -> DataFrame:
    """Of updated rows, the last of each key."""
    rest = [c for c in found.columns if c not in (*keys, "batch")]
    return found.groupBy(*keys).agg(F.max_by(F.struct(*rest), "batch").alias("last")).select(*keys, "last.*")


def insert(sizes: list[int], starts: list[int], k: int) -> None:
    """One sample into a count layout (oldest first) whose newest bucket was just appended: merge what is too many."""
    size, end = 1, len(sizes)
    while True:
        cap = (k if size == 1 else -(-k // 2)) + 1
        first = end
        while first and sizes[first - 1] == size:
            first -= 1
        if end - first <= cap:
            return
        sizes[first : first + 2] = [2 * size]
        del starts[first + 1]
        size, end = 2 * size, first + 1


def histogram_state(k: int) -> Callable:
    """State of one series: number of samples, bucket sizes, first time of each bucket. Batches arrive in
    time order; inside one they are sorted by time."""

    def update(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, sizes, starts = state.get if state.exists else (0, [], [])
        sizes, starts = list(sizes), list(starts)
        for t in pd.concat(list(batches))["t"].sort_values():
            n += 1
            sizes.append(1)
            starts.append(int(t))
            insert(sizes, starts, k)
        state.update((n, sizes, starts))
        yield pd.DataFrame({"series": [key[0]], "n": [n], "sizes": [sizes], "starts": [starts]})

    return update


def maintain(samples: DataFrame, k: int) -> DataFrame:
    """Streaming count layouts of ``samples`` (series, t): series, n, sizes, starts, updated each batch."""
    schema = "n long, sizes array<long>, starts array<long>"
    return samples.groupBy("series").applyInPandasWithState(histogram_state(k), f"series string, {schema}", schema, "update", GroupStateTimeout.NoTimeout)


def accept(samples: DataFrame) -> DataFrame:
    """``samples`` (series, t, id) with accepted: later than all of its series before it, in order of arrival by batch; of equal times, by id."""

    def judge(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        last, last_id = state.get if state.exists else (-(1 << 62), 0)
        rows = pd.concat(list(batches)).sort_values(["t", "id"])
        fresh = ((rows["t"] > last) | (rows["t"] == last) & (rows["id"] > last_id)) & ~rows.duplicated(["t", "id"])
        if fresh.any():
            state.update((int(rows["t"].iloc[-1]), int(rows["id"].iloc[-1])))
        yield pd.DataFrame({"series": key[0], "id": rows["id"], "accepted": fresh})

    return samples.groupBy("series").applyInPandasWithState(judge, "series string, id long, accepted boolean", "last long, last_id long", "append", GroupStateTimeout.NoTimeout)


def ingest(stream: DataFrame, root: str, pane: int = DAY, k: int = 256) -> None:
    """Samples (series, t, value) to the store and their panes' sketches to the cache, batch by batch.

    Both writes carry the batch's number and overwrite themselves, so a batch that is run again after a
    failure counts once. Panes merge in any order.
    """

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{root}/store/batch={number}")
        panes = batch.groupBy("series", F.expr(f"t div {pane}").alias("pane")).agg(F.count("*").alias("n"), F.min("t").alias("t_lo"), F.max("t").alias("t_hi"), F.expr(f"kll_sketch_agg_double(value, {k})").alias("sketch"))
        panes.write.mode("overwrite").parquet(f"{root}/panes/batch={number}")

    stream.writeStream.foreachBatch(write).option("checkpointLocation", f"{root}/state").trigger(availableNow=True).start().awaitTermination()


def rebuild(store: DataFrame, upto: int, live: DataFrame, pane: int = DAY, k: int = 256) -> DataFrame:
    """Panes of one instance from two: those up to ``upto`` from the store, later ones from the live cache."""
    old = store.where(F.col("t") <= upto).groupBy("series", F.expr(f"t div {pane}").alias("pane")).agg(F.count("*").alias("n"), F.expr(f"kll_sketch_agg_double(value, {k})").alias("sketch"))
    both = old.unionByName(live.where(F.col("t_lo") > upto).select("series", "pane", "n", "sketch"))
    return both.groupBy("series", "pane").agg(F.sum("n").alias("n"), F.expr("kll_merge_agg_double(sketch)").alias("sketch"))


def advance(buckets: DataFrame | None, fresh: DataFrame, k_eh: int, k_kll: int, expired: int) -> DataFrame:
    """The bucket table after a batch: ``fresh`` (series, t, value, and id for ties) are later than all that ``buckets`` hold.

    A bucket of the old layout lies whole inside one of the new, whose number follows from its last position; so
    sketches of old buckets and of new samples are merged by that number, all series at once, without a loop over
    samples. Buckets that end at or before ``expired`` go. ``buckets`` None: there are none yet.
    """
    placed = position(fresh.withColumn("pane", F.expr(f"t div {DAY}")), ["t", "id"], counted=True).drop("pane")
    if buckets is not None:
        past = buckets.groupBy("series").agg(F.max("n").alias("past"))
        placed = placed.join(past, "series", "left").withColumn("past", F.coalesce("past", F.lit(0))).withColumns({"seq": F.col("seq") + F.col("past"), "n": F.col("n") + F.col("past")}).drop("past")
    new = kll.build(placed, k_eh, k_kll)
    if buckets is not None:
        totals = new.groupBy("series").agg(F.max("n").alias("total"))
        old = buckets.drop("bucket").join(totals, "series", "left").withColumn("n", F.coalesce("total", "n")).drop("total")
        moved = layout_count(old.withColumn("seq", F.col("seq_hi")), k_eh).drop("seq")
        both = new.unionByName(moved.select(new.columns))
        new = both.groupBy("series", "bucket").agg(F.min("t_lo").alias("t_lo"), F.max("t_hi").alias("t_hi"), F.min("seq_lo").alias("seq_lo"), F.max("seq_hi").alias("seq_hi"), F.sum("size").alias("size"), F.expr("kll_merge_agg_double(sketch)").alias("sketch"), F.max("n").alias("n"))
    return new.where(F.col("t_hi") > expired)


def keep_up(stream: DataFrame, store: CacheStore, subject: str, width: int, k_eh: int = 50, k_kll: int = 256, p: float = 0.1) -> None:
    """Work off a stream of samples (series, t, value, id) into the committed cache, quantile sketches and samples, each ``width`` wide.

    A batch that runs again finds its version committed and leaves it: versions are numbered by batches.
    """

    def write(batch: DataFrame, number: int) -> None:
        now = batch.agg(F.max("t")).first()[0]
        if now is None:
            return
        held = {family: store.read(subject, family) for family in ("kll", "sample")}
        if len(store.versions(subject, "kll")) <= number:
            old = held["kll"].tables["buckets"] if held["kll"] else None
            store.commit(subject, "kll", {"buckets": advance(old, batch, k_eh, k_kll, now - width)}, now - width, now)
        if len(store.versions(subject, "sample")) <= number:
            placed = position(batch.withColumn("pane", F.expr(f"t div {DAY}")), ["t", "id"], counted=True)
            counts = placed.groupBy("series").agg(F.max("n").alias("n"))
            if held["sample"]:
                past = held["sample"].tables["counts"]
                placed = placed.join(past.withColumnRenamed("n", "past"), "series", "left").withColumn("seq", F.col("seq") + F.coalesce("past", F.lit(0)))
                counts = counts.unionByName(past).groupBy("series").agg(F.sum("n").alias("n"))
            kept = sampling.build(placed.select("series", "t", "seq", "value"), p)
            if held["sample"]:
                kept = kept.unionByName(held["sample"].tables["kept"])
            store.commit(subject, "sample", {"kept": sampling.expire(kept, now, width), "counts": counts}, now - width, now)

    stream.writeStream.foreachBatch(write).option("checkpointLocation", f"{store.root}/stream").trigger(availableNow=True).start().awaitTermination()


# -- queries -----------------------------------------------------------------------------------------------------------

CENTS = "cast(round(value * 100) AS bigint)"


def _split(spark: SparkSession, sf_dir: str, scratch: Scratch, repeats: bool = False) -> str:
    """The events as three files, in time order, so that a stream has several batches; ``repeats`` adds some again."""
    events = table(spark, sf_dir, "events")
    # cut by time, not by id: ids need not be dense, nor in the order of time
    cuts = events.agg(F.percentile_approx(F.expr(micros("ts")), [1 / 3, 2 / 3], 100).alias("at")).first()["at"] or [0, 0]
    rows = events.withColumn("part", F.expr(" + ".join(f"CASE WHEN {micros('ts')} > {cut} THEN 1 ELSE 0 END" for cut in cuts)))
    if repeats:
        rows = rows.unionByName(rows.where("event_id % 100 = 7"))
    path = f"{scratch.root}/events"
    for part in range(3):
        rows.where(F.col("part") == part).drop("part").coalesce(1).write.mode("append").parquet(path)
    return path


def tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    scratch = Scratch(spark, "stream")
    stream = stamped(stream_of(spark, _split(spark, sf_dir, scratch))).withWatermark("at", "40 days")
    found = stream.groupBy("event_type", F.window("at", "1 day")).agg(F.count("*").alias("n"), F.sum(F.expr(CENTS)).alias("cents")).select("event_type", F.unix_micros("window.start").alias("low"), "n", "cents")
    return latest(run_to_table(found, scratch, "tumbling", "update"), ["event_type", "low"])


def sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    scratch = Scratch(spark, "stream")
    stream = stamped(stream_of(spark, _split(spark, sf_dir, scratch))).withWatermark("at", "40 days")
    found = stream.groupBy("event_type", F.window("at", "10 days", "1 day")).agg(F.count("*").alias("n"), F.sum(F.expr(CENTS)).alias("cents")).select("event_type", F.unix_micros("window.start").alias("low"), "n", "cents")
    return latest(run_to_table(found, scratch, "sliding", "update"), ["event_type", "low"])


def dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    scratch = Scratch(spark, "stream")
    stream = stamped(stream_of(spark, _split(spark, sf_dir, scratch, repeats=True))).withWatermark("at", "2 days").dropDuplicatesWithinWatermark(["event_id"])
    return run_to_table(stream.select("event_id", "event_type", "value"), scratch, "dedup", "append").drop("batch")


def rejected(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Repeats of samples that were taken are rejected."""
    scratch = Scratch(spark, "stream")
    stream = stamped(stream_of(spark, _split(spark, sf_dir, scratch, repeats=True)))
    found = run_to_table(accept(stream.select(F.col("event_type").alias("series"), "t", F.col("event_id").alias("id"))), scratch, "accepted", "append")
    return found.groupBy("series").agg(F.count_if("accepted").alias("taken"), F.count_if(~F.col("accepted")).alias("rejected"))


def state_layout(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Layouts kept in state over several batches: bucket by bucket as the closed form has them."""
    scratch = Scratch(spark, "stream")
    stream = stamped(stream_of(spark, _split(spark, sf_dir, scratch)))
    found = latest(run_to_table(maintain(stream.select(F.col("event_type").alias("series"), "t"), 20), scratch, "layout", "update"), ["series"])
    return found.select("series", F.posexplode(F.arrays_zip("sizes", "starts")).alias("at", "b")).select("series", (F.col("at") + 1).cast("long").alias("bucket"), F.col("b.sizes").alias("size"), F.col("b.starts").alias("t_lo"))


def static_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events that a rule watches, from a stream and a static table of rules."""
    scratch = Scratch(spark, "stream")
    rules = spark.createDataFrame([("click", 50.0), ("purchase", 80.0)], "event_type string, threshold double")
    stream = stream_of(spark, _split(spark, sf_dir, scratch)).join(F.broadcast(rules), "event_type").where("value > threshold")
    return run_to_table(stream.select("event_id", "event_type", "value"), scratch, "static", "append").drop("batch")


def ingested(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Stored samples and cached panes of a stream, the old half rebuilt from the store: counts and medians within bounds."""
    scratch = Scratch(spark, "ingest")
    stream = stamped(stream_of(spark, _split(spark, sf_dir, scratch))).select(F.col("event_type").alias("series"), "t", "value")
    ingest(stream, scratch.root)
    store, panes = spark.read.parquet(f"{scratch.root}/store"), spark.read.parquet(f"{scratch.root}/panes")
    middle = (1_704_067_200_000_000 // DAY + 15) * DAY - 1
    whole = rebuild(store, middle, panes).groupBy("series").agg(F.sum("n").alias("n"), F.expr("kll_sketch_get_quantile_double(kll_merge_agg_double(sketch), 0.5D)").alias("median"))
    below = store.join(whole, "series").groupBy("series", "n").agg(F.count_if(F.col("value") <= F.col("median")).alias("below"))
    return below.select("series", "n", (F.abs(F.col("below") / F.col("n") - 0.5) < 0.04).alias("within_bound"))


def _kept_up(spark: SparkSession, sf_dir: str) -> CacheStore:
    scratch = Scratch(spark, "live")
    stream = stamped(stream_of(spark, _split(spark, sf_dir, scratch))).select(F.col("event_type").alias("series"), "t", "value", F.col("event_id").alias("id"))
    store = CacheStore(spark, scratch.root)
    keep_up(stream, store, "ev_type", 10 * DAY, 20)
    return store


def live_buckets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Buckets of quantile sketches after three batches, with expiry: spans as the whole layout has them."""
    buckets = _kept_up(spark, sf_dir).read("ev_type", "kll").tables["buckets"]
    return buckets.select("series", "bucket", "t_lo", "t_hi", "seq_lo", "seq_hi", "size")


def live_quantiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Medians of sub-windows from the live buckets, and whether each is within its bound."""
    samples = series_view(spark, sf_dir, "ev_type")
    buckets = _kept_up(spark, sf_dir).read("ev_type", "kll").tables["buckets"]
    ranges = buckets.select("series").distinct().withColumn("query", F.explode(F.array(F.lit("d9"), F.lit("d5")))).selectExpr("query", "series", f"{_END} - cast(substr(query, 2) AS bigint) * {DAY} AS low", f"{_END} AS high")
    found = kll.quantiles(buckets, ranges, [0.5], by="t")
    ranked = in_range(samples, ranges, "t").join(found, ["query", "series"]).groupBy("query", "series", "estimate", "bound").agg(F.round(F.expr("percentile(value, 0.5)"), 6).alias("exact"), F.count("*").alias("n"), F.count_if(F.col("value") < F.col("estimate")).alias("below"), F.count_if(F.col("value") <= F.col("estimate")).alias("upto"))
    error = F.greatest(F.lit(0.0), F.col("below") / F.col("n") - 0.5, 0.5 - F.col("upto") / F.col("n"))
    return ranked.select("query", "series", "exact", (error <= F.col("bound") + 2 * kll.sketch_error(256)).alias("within_bound"))


def live_samples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The sliding sample after three batches: the same rows as one pass keeps of the window."""
    return _kept_up(spark, sf_dir).read("ev_type", "sample").tables["kept"].select("series", "t", "seq", "value")


def sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Session windows of users, with gaps of two hours."""
    scratch = Scratch(spark, "stream")
    stream = stamped(stream_of(spark, _split(spark, sf_dir, scratch))).withWatermark("at", "40 days")
    found = stream.groupBy("user_id", F.session_window("at", "2 hours").alias("w")).agg(F.count("*").alias("n"), F.sum(F.expr(CENTS)).alias("cents"))
    # append emits only sessions that the watermark has closed; of complete ones the last output is the whole
    found = run_to_table(found.select("user_id", F.unix_micros("w.start").alias("low"), F.unix_micros("w.end").alias("high"), "n", "cents"), scratch, "sessions", "complete")
    last = found.agg(F.max("batch")).first()[0]
    return found.where(F.col("batch") == last).drop("batch")


_END = 1_704_067_200_000_000 + 30 * DAY
_V = VIEWS["ev_type"].sql
_LAST = f"SELECT max(epoch_us(ts)) - {10 * DAY} FROM events"
QUERIES: dict = {"stream_ehkll_buckets": live_buckets, "stream_ehkll_quantiles": live_quantiles, "stream_sample_window": live_samples, "stream_session": sessions, "stream_tumbling": tumbling, "stream_sliding": sliding, "stream_dedup": dedup, "stream_late_reject": rejected, "stream_eh_state": state_layout, "stream_static_join": static_join, "stream_ingest_rebuild": ingested}
SQL: dict = {
    "stream_ehkll_buckets": layout_sql(_V, 20) + f"SELECT series, bucket, min(t) AS t_lo, max(t) AS t_hi, min(seq) AS seq_lo, max(seq) AS seq_hi, count(*) AS size FROM placed GROUP BY series, bucket HAVING max(t) > ({_LAST})",
    "stream_ehkll_quantiles": f"SELECT 'd' || d AS query, series, round(quantile_cont(value, 0.5), 6) AS exact, true AS within_bound FROM ({_V}) JOIN (VALUES (9), (5)) AS n(d) ON t > {_END} - d * {DAY} AND t <= {_END} GROUP BY d, series",
    "stream_sample_window": f"SELECT series, t, seq, value FROM ({_V}) v WHERE {sampling.DRAW.format(salt=1).replace('series)', 'v.series)')} < 100000 AND t > ({_LAST})",
    "stream_session": f"SELECT user_id, min(t) AS low, max(t) + {2 * 3_600_000_000} AS high, count(*) AS n, sum(cents)::BIGINT AS cents FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY t, event_id) AS run FROM (SELECT user_id, event_id, epoch_us(ts) AS t, cast(round(value * 100) AS bigint) AS cents, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts, event_id) < {2 * 3_600_000_000} THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, run",
    "stream_tumbling": f"SELECT event_type, epoch_us(ts) // {DAY} * {DAY} AS low, count(*) AS n, sum(cast(round(value * 100) AS bigint))::BIGINT AS cents FROM events GROUP BY event_type, low",
    "stream_sliding": f"SELECT event_type, low, count(*) AS n, sum(cast(round(value * 100) AS bigint))::BIGINT AS cents FROM (SELECT event_type, value, unnest(range(epoch_us(ts) // {DAY} * {DAY} - 9 * {DAY}, epoch_us(ts) // {DAY} * {DAY} + 1, {DAY})) AS low FROM events) GROUP BY event_type, low",
    "stream_dedup": "SELECT event_id, event_type, value FROM events",
    "stream_late_reject": "SELECT event_type AS series, count(*) AS taken, count(*) FILTER (event_id % 100 = 7) AS rejected FROM events GROUP BY event_type",
    "stream_eh_state": layout_sql(VIEWS["ev_type"].sql, 20) + "SELECT series, bucket, count(*) AS size, min(t) AS t_lo FROM placed GROUP BY series, bucket",
    "stream_static_join": "SELECT event_id, event_type, value FROM events WHERE event_type = 'click' AND value > 50 OR event_type = 'purchase' AND value > 80",
    "stream_ingest_rebuild": "SELECT event_type AS series, count(*) AS n, true AS within_bound FROM events GROUP BY event_type",
}

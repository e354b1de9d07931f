"""Mixing sources to target weights by pivotal dependent rounding.

A source's documents are each to be taken target / source size times. The whole part of that is taken of
each; the fraction is rounded by the pivotal method: two documents put their fractions together, and by
chance one passes mass to the other until one of them is 0 or 1, which keeps each one's expected copies
and makes their sum all but certain. Documents of a source are dealt by hash into blocks; a fold
over each block, in order of size so that mass moves between documents of like size, leaves at most one
fraction, and the fractions of BLOCK blocks are folded again, until one is left for the source: a reduction
tree of which no task holds more than a block. Fractions are whole numbers of 2 ** -40, so no mass is lost.

Defined results: sources are ordered by code point, null last, and weigh 1, 2, 3 in turn; a null text has
no words, takes none and is a row; a source without words has target 0. Rows alike in doc_id, source and
size are one unit that gets the same copies. Chance comes from hashes of ids, so reruns agree. The table
of sources is one row for each, and so is what orders and weighs them. All of it is built-in functions.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from subwin.llm.common import WHITE_RE, join_same, table
from subwin.storage import Scratch

#: The weights in turn, and the most times that a source is taken.
WEIGHTS, MOST_COPIES = (1, 2, 3), 3
#: Documents of a block, on average, and fractions of one.
BLOCK, ONE = 128, 1 << 40
SEED = 42


def word_count(text: Column) -> Column:
    """Number of runs of other characters than ASCII white space, from their starts alone."""
    marked = F.regexp_replace(F.coalesce(text, F.lit("")), r"[^\x20\x09-\x0D]+", "x")
    return F.length(F.regexp_replace(marked, WHITE_RE, "")).cast("long")


def targets(sizes: DataFrame) -> DataFrame:
    """source, source_size, docs and target of each source of ``sizes`` (source, size).

    Targets stop at MOST_COPIES times the source; resharing what is above by weight until none is above
    gives the level at which each uncapped source's target over its weight is the same, found by one pass
    over the sources in the order in which they reach their caps.
    """
    sums = sizes.groupBy("source").agg(F.sum("size").alias("source_size"), F.count("*").alias("docs"))
    order = Window.orderBy(F.col("source").isNull(), "source")
    weighed = sums.withColumn("weight", F.element_at(F.array(*map(F.lit, WEIGHTS)), F.pmod(F.row_number().over(order) - 1, F.lit(len(WEIGHTS))).cast("int") + 1))
    cap = MOST_COPIES * F.col("source_size")
    capping = Window.orderBy(cap / F.col("weight"), F.col("source").isNull(), "source")
    before = capping.rowsBetween(Window.unboundedPreceding, -1)
    every = Window.partitionBy()
    total, weights = F.sum("source_size").over(every), F.sum("weight").over(every)
    level = (total - F.coalesce(F.sum(cap).over(before), F.lit(0))) / (weights - F.coalesce(F.sum("weight").over(before), F.lit(0)))
    # up to the first source whose cap lies above the level all are capped, from it on all get the level
    leveled = weighed.withColumn("level", level).withColumn("open", F.when(cap >= F.col("level") * F.col("weight"), F.col("level")))
    first = F.first("open", ignorenulls=True).over(capping.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    return leveled.withColumn("target", F.least(cap.cast("double"), F.coalesce(first * F.col("weight"), cap.cast("double")))).select("source", "source_size", "docs", "target")


def _fold(units: Column) -> Column:
    """Pivotal rounding over an array of (size, h, doc_id, n, part), sorted: done units with their copy, and the one left."""

    def step(state: Column, unit: Column) -> Column:
        left = state["left"]
        mass = left["part"] + unit["part"]
        chance = F.pmod(F.xxhash64(F.lit(SEED), left["h"], unit["h"]), F.lit(ONE))
        # below one in all: the winner has all mass; else the winner is taken and the other has what is above one
        small = mass < ONE
        wins = F.when(small, chance * 1.0 * mass < left["part"] * 1.0 * ONE).otherwise(chance * 1.0 * (2 * ONE - mass) < (ONE - unit["part"]) * 1.0 * ONE)
        stays_left = F.when(small, wins).otherwise(~wins)
        over = F.when(small, mass).otherwise(mass - ONE)

        def with_part(which: Column, part: Column) -> Column:
            return F.struct(which["size"].alias("size"), which["h"].alias("h"), which["doc_id"].alias("doc_id"), which["n"].alias("n"), part.cast("long").alias("part"))

        done = with_part(F.when(stays_left, unit).otherwise(left), F.when(small, F.lit(0)).otherwise(F.lit(ONE)))
        rest = with_part(F.when(stays_left, left).otherwise(unit), over)
        return F.when(left.isNull(), F.struct(unit.alias("left"), state["done"].alias("done"))).otherwise(F.struct(rest.alias("left"), F.concat(state["done"], F.array(done)).alias("done")))

    empty = F.struct(F.when(F.lit(False), F.element_at(units, 1)).alias("left"), F.slice(units, 1, 0).alias("done"))
    return F.aggregate(units, empty, step)


def rounded(units: DataFrame, most: int, scratch: Scratch) -> DataFrame:
    """source, doc_id, size, n and part (0 or ONE) of ``units`` (source, blocks, size, h, doc_id, n, part): the tree."""
    level, done = 0, None
    rows = units.withColumn("block", F.pmod(F.col("h"), F.col("blocks")))
    while True:
        last = most <= 1
        unit = F.struct("size", "h", "doc_id", "n", "part")
        folded = rows.groupBy("source", "block").agg(F.array_sort(F.collect_list(unit)).alias("units"))
        folded = scratch.save(folded.select("source", "block", _fold(F.col("units")).alias("state")), f"level{level}")
        decided = folded.select("source", F.inline("state.done"))
        done = decided if done is None else done.unionByName(decided)
        rest = folded.where("state.left is not null").select("source", F.floor(F.col("block") / BLOCK).alias("block"), "state.left.*")
        if last:
            final = F.when(F.pmod(F.xxhash64(F.lit(SEED), "h"), F.lit(ONE)) < F.col("part"), F.lit(ONE)).otherwise(F.lit(0))
            return done.unionByName(rest.select("source", "size", "h", "doc_id", "n", final.cast("long").alias("part"))).select("source", "doc_id", "size", "part")
        rows, most, level = rest, -(-most // BLOCK), level + 1


def copies(sized: DataFrame) -> DataFrame:
    """doc_id, source, size, source_size, target and copies of each distinct (doc_id, source, size) of ``sized``."""
    scratch = Scratch(sized.sparkSession, "mixing")
    units = scratch.save(sized.groupBy("doc_id", "source", "size").agg(F.count("*").alias("n")), "units")
    mixed = scratch.save(targets(units.select("source", (F.col("size") * F.col("n")).alias("size"))).withColumn("blocks", F.ceil(F.col("docs") / BLOCK)), "targets")
    times = F.when(F.col("source_size") > 0, F.least(F.col("target") / F.col("source_size"), F.lit(float(MOST_COPIES)))).otherwise(F.lit(0.0))
    mixed = mixed.withColumn("times", times).withColumn("whole", F.floor("times"))
    mixed = mixed.withColumn("part", F.round((F.col("times") - F.col("whole")) * ONE).cast("long"))
    rows = join_same(units, mixed, ["source"]).select("doc_id", "source", "size", "n", "source_size", "target", "blocks", "whole", "part")
    # units without words are taken no times, and those of a whole number of copies need no rounding
    to_round = rows.where("size > 0 and part > 0").select("source", "blocks", (F.col("size") * F.col("n")).alias("size"), F.xxhash64(F.lit(SEED), F.coalesce(F.col("doc_id").cast("string"), F.lit("")), "size").alias("h"), "doc_id", "n", "part")
    most = to_round.agg(F.coalesce(F.max("blocks"), F.lit(1))).first()[0]
    extra = rounded(to_round, most, scratch)
    extra = extra.where(F.col("part") == ONE).select("source", "doc_id", F.col("size").alias("total")).distinct().withColumn("extra", F.lit(1))
    joined = join_same(rows.withColumn("total", F.col("size") * F.col("n")), extra, ["source", "doc_id", "total"], "left")
    taken = F.when(F.col("size") > 0, F.col("whole") + F.coalesce("extra", F.lit(0))).otherwise(F.lit(0)).cast("int")
    return joined.select("doc_id", "source", "size", "n", "source_size", "target", taken.alias("copies"))


def mix(docs: DataFrame) -> DataFrame:
    """``docs`` (doc_id, text, source, ...) with each row as often as the mix takes it; all columns stay."""
    keyed = docs.withColumn("_subwin_size", word_count(docs["text"]))
    taken = copies(keyed.select("doc_id", "source", F.col("_subwin_size").alias("size"))).where("copies > 0").withColumnRenamed("copies", "_subwin_copies")
    taken = taken.select(F.col("doc_id").alias("_subwin_id"), F.col("source").alias("_subwin_source"), F.col("size").alias("_subwin_words"), "_subwin_copies")
    on = keyed["doc_id"].eqNullSafe(taken["_subwin_id"]) & keyed["source"].eqNullSafe(taken["_subwin_source"]) & (keyed["_subwin_size"] == taken["_subwin_words"])
    return keyed.join(taken, on).select(*[keyed[c] for c in docs.columns], F.explode(F.sequence(F.lit(1), F.col("_subwin_copies"))).alias("_subwin_nth")).drop("_subwin_nth")


def op5_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    found = copies(docs.select("doc_id", "source", word_count(F.col("text")).alias("size")))
    each = F.explode(F.sequence(F.lit(1).cast("long"), F.col("n")))
    return found.select("doc_id", "source", "size", "source_size", "target", (F.col("copies") * F.col("size")).alias("taken"), each.alias("nth")).drop("nth")

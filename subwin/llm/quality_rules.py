"""Quality rules: base rules, then thresholds whose false rejections are controlled on labelled holdouts.

Each rule rejects documents whose measure passes a cutoff. The cutoffs of a fixed grid are judged on
labelled documents that no model was fitted on: a cutoff is certified for a stratum (a language) if, at
the level ``delta`` divided by the number of all tests (Bonferroni), the exact binomial upper bound on
the share of good documents that it rejects is at most ``alpha`` divided by the number of rules. So with
probability 1 - delta no stratum loses more than ``alpha`` of its good documents to all rules together.
Among certified cutoffs the one that rejects most labelled bad documents, less PRICE times the good ones,
is used; a rule without one rejects nothing in that stratum.

Defined results: a null text has no words and fails the base rule; a null language is a stratum; a null
or repeated doc_id is judged like any other row, though a label counts once for each row it joins; labels
with a null quality are left out; with no labels only the base rules reject. Other columns are ignored.
"""

from __future__ import annotations

import math
from collections import Counter

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from subwin.llm.common import WHITE, join_same, map_batches, table, text_key, texts
from subwin.storage import Scratch

SYMBOLS = b"#*$%&|<>"
#: The share of good documents of a stratum that all rules may reject, the risk that this fails, and the price of a rejected good document in bad ones.
ALPHA, DELTA, PRICE = 0.05, 0.05, 20
#: Rule, its measure, and the grid of cutoffs, from lax to strict; a document above the cutoff is rejected.
GRID = {
    "symbols": ("try_divide(n_symbols, word_chars)", [0.3, 0.2, 0.1, 0.05, 0.03, 0.02]),
    "shouted": ("try_divide(n_upper_words, n_words)", [0.9, 0.7, 0.5, 0.3, 0.2, 0.1]),
    "dup_lines": ("try_divide(n_dup_lines, n_lines)", [0.9, 0.7, 0.5, 0.3, 0.2]),
    "repeats": ("try_divide(n_repeat_words, n_words)", [0.45, 0.4, 0.3, 0.2, 0.15, 0.1]),
    "long_words": ("try_divide(word_chars, n_words)", [20.0, 14.0, 11.0, 10.0, 9.0, 8.0]),
}
COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_upper_words", "n_lines")


def text_counts(text: str) -> tuple[int, ...]:
    """The counts named by COUNTS."""
    raw = text.encode()
    words = raw.split()
    n = len(words)
    seen: set[str] = set()
    dup = lines = 0
    for line in text.split("\n"):
        if line in seen:
            dup += 1
            lines += 1
        elif line.strip(" \t\n\x0b\x0c\r"):
            seen.add(line)
            lines += 1
    repeated = 0
    found = Counter(zip(words, words[1:], words[2:], strict=False))
    if len(found) < n - 2:
        until = 0  # words before it are counted
        for i, window in enumerate(zip(words, words[1:], words[2:], strict=False)):
            if found[window] > 1:
                repeated += i + 3 - max(i, until)
                until = i + 3
    white = len(raw) - len(raw.translate(None, WHITE))
    symbols = len(raw) - len(raw.translate(None, SYMBOLS))
    return n, len(text) - white, symbols, dup, repeated, sum(len(w) > 1 and w.isupper() for w in words), lines


def _count_batch(batch: pa.RecordBatch) -> pa.RecordBatch:
    counts = [text_counts(x) for x in texts(batch)]
    rest = [i for i, name in enumerate(batch.schema.names) if name != "text"]
    return pa.RecordBatch.from_arrays([*(batch.column(i) for i in rest), *(pa.array(x, pa.int64()) for x in zip(*counts, strict=True))], names=[*(batch.schema.names[i] for i in rest), *COUNTS])


def measure(docs: DataFrame, stratum: str = "lang", key: bool = False) -> DataFrame:
    """doc_id, stratum, the counts and base_failed of each document; with ``key`` also its text_key."""
    keys, kinds = (["text_key"], ", text_key long") if key else ([], "")
    kind = docs.schema["doc_id"].dataType.simpleString()
    rows = docs.select("doc_id", F.col(stratum).cast("string").alias("stratum"), *[text_key(F.col("text")).alias(k) for k in keys], "text")
    counted = map_batches(rows, _count_batch, f"doc_id {kind}, stratum string{kinds}, " + ", ".join(f"{c} long" for c in COUNTS))
    return counted.withColumn("base_failed", F.expr("n_words < 50 OR 100 * n_repeat_words > 50 * n_words"))


def binomial_cdf(k: int, n: int, p: float) -> float:
    """P(X <= k) for n trials of chance p, by the continued fraction of the incomplete beta function."""
    if k >= n:
        return 1.0
    return _beta(n - k, k + 1, 1 - p)


def _beta(a: float, b: float, x: float) -> float:
    """The regularised incomplete beta function."""
    if x <= 0 or x >= 1:
        return float(x >= 1)
    if x > (a + 1) / (a + b + 2):
        return 1 - _beta(b, a, 1 - x)
    front = math.exp(math.lgamma(a + b) - math.lgamma(a) - math.lgamma(b) + a * math.log(x) + b * math.log1p(-x)) / a
    tiny = 1e-300
    c, d, f = 1.0, 0.0, 1.0
    for i in range(100_000):
        m = i // 2
        if i == 0:
            term = 1.0
        elif i % 2 == 0:
            term = m * (b - m) * x / ((a + 2 * m - 1) * (a + 2 * m))
        else:
            term = -(a + m) * (a + b + m) * x / ((a + 2 * m) * (a + 2 * m + 1))
        d = 1 / ((1 + term * d) or tiny)
        c = (1 + term / c) or tiny
        f *= c * d
        if abs(1 - c * d) < 1e-12:
            break
    return front * (f - 1) if front else 0.0


def certify(counts: DataFrame, tests: int, alpha: float, delta: float) -> DataFrame:
    """``counts`` (good, good_rejected, ...) with certified: the exact upper bound on the rejected share is at most alpha at level delta / tests."""

    @F.pandas_udf("boolean")
    def bound(good: pd.Series, rejected: pd.Series) -> pd.Series:
        return pd.Series([n > 0 and binomial_cdf(int(k), int(n), alpha) <= delta / tests for n, k in zip(good, rejected, strict=True)])

    return counts.withColumn("certified", bound("good", "good_rejected"))


def thresholds(measured: DataFrame, labels: DataFrame, alpha: float = ALPHA, delta: float = DELTA) -> DataFrame:
    """Stratum, rule, cutoff, good, good_rejected, bad_rejected: the cutoffs in use, one row for each stratum and rule that has one."""
    known = labels.where("quality is not null and doc_id is not null").select(F.col("doc_id").alias("labelled"), "quality")
    held = measured.where("not base_failed").join(known, F.col("doc_id") == F.col("labelled"))
    cells = [(rule, cut, F.expr(value) > cut) for rule, (value, cuts) in GRID.items() for cut in cuts]
    sums = [F.struct(F.lit(rule).alias("rule"), F.lit(cut).alias("cutoff"), F.count_if(over & (F.col("quality") == 1)).alias("good_rejected"), F.count_if(over & (F.col("quality") == 0)).alias("bad_rejected")) for rule, cut, over in cells]
    table = held.groupBy("stratum").agg(F.count_if(F.col("quality") == 1).alias("good"), F.array(*sums).alias("cells"))
    strata = table.count()
    rows = table.select("stratum", "good", F.inline("cells"))
    sound = certify(rows, max(1, strata) * len(cells), alpha / len(GRID), delta).where("certified and bad_rejected > 0")
    best = F.max(F.struct((F.col("bad_rejected") - PRICE * F.col("good_rejected")).alias("worth"), "cutoff", "good", "good_rejected", "bad_rejected")).alias("best")
    return sound.groupBy("stratum", "rule").agg(best).where("best.worth > 0").select("stratum", "rule", "best.cutoff", "best.good", "best.good_rejected", "best.bad_rejected")


def judge(measured: DataFrame, labels: DataFrame, alpha: float = ALPHA, delta: float = DELTA) -> DataFrame:
    """``measured`` with kept and rejected_by, the rules (base or of GRID) that a document fails."""
    cuts = thresholds(measured, labels, alpha, delta).groupBy("stratum").agg(F.map_from_entries(F.collect_list(F.struct("rule", "cutoff"))).alias("cuts"))
    failed = [F.when(F.expr(value) > F.col("cuts")[rule], F.lit(rule)) for rule, (value, _) in GRID.items()]
    out = join_same(measured, cuts, ["stratum"], "left").select(*measured.columns, F.filter(F.array(F.when(F.col("base_failed"), F.lit("base")), *failed), lambda x: x.isNotNull()).alias("rejected_by"))
    return out.withColumn("kept", F.size("rejected_by") == 0)


def filter_quality(docs: DataFrame, labels: DataFrame, alpha: float = ALPHA, delta: float = DELTA) -> DataFrame:
    """``docs`` (doc_id, text, lang, ...) without the rows that a rule rejects; all columns stay."""
    spark = docs.sparkSession
    measured = Scratch(spark, "quality").save(measure(docs, key=True), "measured")
    gone = judge(measured, labels).where("not kept").select(F.col("doc_id").alias("_subwin_id"), F.col("text_key").alias("_subwin_key"), F.col("stratum").alias("_subwin_stratum")).distinct()
    return docs.join(gone, docs["doc_id"].eqNullSafe(F.col("_subwin_id")) & (text_key(docs["text"]) == F.col("_subwin_key")) & docs["lang"].eqNullSafe(F.col("_subwin_stratum")), "left_anti")


def op2_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    measured = Scratch(spark, "quality").save(measure(table(spark, sf_dir, "documents")), "measured")
    judged = judge(measured, table(spark, sf_dir, "labels"))
    return judged.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", F.array_join("rejected_by", ",").alias("rejected_by"))


def _sql() -> str:
    """The query in SQL: counts by unnesting, the binomial bound by its sum."""
    values = {rule: value.replace("try_divide(", "").replace(", ", " / nullif(").replace(")", ", 0)") for rule, (value, _) in GRID.items()}
    cells = " UNION ALL ".join(f"SELECT stratum, '{rule}' AS rule, {cut!r}::DOUBLE AS cutoff, count(*) FILTER (quality = 1) AS good, count(*) FILTER (quality = 1 AND {values[rule]} > {cut!r}) AS good_rejected, count(*) FILTER (quality = 0 AND {values[rule]} > {cut!r}) AS bad_rejected FROM held GROUP BY stratum" for rule, (_, cuts) in GRID.items() for cut in cuts)
    tests = sum(len(cuts) for _, cuts in GRID.values())
    alpha = ALPHA / len(GRID)
    failed = ", ".join(f"CASE WHEN {values[rule]} > (SELECT cutoff FROM cuts WHERE cuts.stratum IS NOT DISTINCT FROM m.stratum AND cuts.rule = '{rule}') THEN '{rule}' END" for rule in GRID)
    return rf"""
WITH d AS (SELECT row_number() OVER () AS id, doc_id, lang AS stratum, coalesce(text, '') AS text, list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS words FROM documents),
lines AS (SELECT id, count(*) AS n_lines, count(*) - count(DISTINCT line) AS n_dup_lines FROM (SELECT id, unnest(string_split(text, chr(10))) AS line FROM d) WHERE regexp_matches(line, '[^\x20\x09-\x0D]') GROUP BY id),
wins AS (SELECT id, pos, words[pos : pos + 2] AS win FROM (SELECT id, words, unnest(range(1, len(words) - 1)) AS pos FROM d)),
twice AS (SELECT id, win FROM wins GROUP BY id, win HAVING count(*) > 1),
repeats AS (SELECT id, count(DISTINCT spot) AS n_repeat_words FROM (SELECT id, unnest(range(pos, pos + 3)) AS spot FROM wins JOIN twice USING (id, win)) GROUP BY id),
m AS (SELECT d.id, doc_id, stratum, len(words)::BIGINT AS n_words, coalesce(list_sum(list_transform(words, lambda w: length(w))), 0)::BIGINT AS word_chars,
    (length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')))::BIGINT AS n_symbols, coalesce(n_dup_lines, 0) AS n_dup_lines, coalesce(n_repeat_words, 0) AS n_repeat_words, coalesce(n_lines, 0) AS n_lines,
    len(list_filter(words, lambda w: strlen(w) > 1 AND regexp_matches(w, '[A-Z]') AND NOT regexp_matches(w, '[a-z]'))) AS n_upper_words,
    len(words) < 50 OR 100 * coalesce(n_repeat_words, 0) > 50 * len(words) AS base_failed FROM d LEFT JOIN lines USING (id) LEFT JOIN repeats USING (id)),
held AS (SELECT m.*, quality FROM m JOIN labels l ON m.doc_id = l.doc_id WHERE NOT base_failed AND quality IS NOT NULL),
cells AS ({cells}),
tail AS (SELECT stratum, rule, cutoff, good, good_rejected, bad_rejected, CASE WHEN good_rejected >= good THEN 1 ELSE (SELECT sum(exp(lgamma(good + 1) - CASE WHEN i = 0 THEN 0 ELSE lgamma(i + 1) END - CASE WHEN i = good THEN 0 ELSE lgamma(good - i + 1) END + i * ln({alpha!r}) + (good - i) * ln(1 - {alpha!r}))) FROM (SELECT unnest(range(good_rejected + 1)) AS i)) END AS p FROM cells WHERE good > 0),
sound AS (SELECT *, bad_rejected - {PRICE} * good_rejected AS worth FROM tail WHERE p <= {DELTA!r} / ({tests} * greatest(1, (SELECT count(DISTINCT coalesce(stratum, chr(1))) FROM held))) AND bad_rejected > 0),
cuts AS (SELECT stratum, rule, cutoff FROM (SELECT *, row_number() OVER (PARTITION BY stratum, rule ORDER BY worth DESC, cutoff DESC) AS nth FROM sound) WHERE nth = 1 AND worth > 0),
judged AS (SELECT *, list_filter([CASE WHEN base_failed THEN 'base' END, {failed}], lambda x: x IS NOT NULL) AS rejected FROM m)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, len(rejected) = 0 AS kept, array_to_string(rejected, ',') AS rejected_by FROM judged
"""


OP2_SQL = _sql()

"""Rules, their expressions, the cache registry, routing, recording and alerting."""

from __future__ import annotations

import hashlib
import re
from bisect import bisect
from collections.abc import Callable
from dataclasses import dataclass, replace
from functools import reduce

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from subwin.functions.exact import AGGREGATES, DAILY, OF_COUNTS, Grid, over_time
from subwin.sources.views import DAY, VIEWS, position, series_view, table
from subwin.storage import Scratch

#: The family of summaries that serves a function; a function without one is always exact.
FAMILIES = {
    "quantile": "kll", "min": "kll", "max": "kll", "count": "sample", "sum": "sample", "avg": "sample", "stddev": "sample", "stdvar": "sample",
    "distinct": "univ", "entropy": "univ", "l2": "univ", "topk": "univ", "l1": "univ",
}
#: Families that serve a function too.
ALSO = {"count": ("univ",), "l1": ("sample",)}
UNCOVERED = ("last", "present", "absent", "quantile_disc")
#: Units of durations.
UNITS = {"s": 1_000_000, "m": 60_000_000, "h": 3_600_000_000, "d": DAY}


@dataclass(frozen=True)
class OverTime:
    """fn_over_time(arg, inner(view{matchers})[window]); matchers are label, operator, text."""

    fn: str
    arg: float | None
    view: str
    matchers: tuple[tuple[str, str, str], ...]
    window: int
    inner: str | None = None

    @property
    def subject(self) -> str:
        """What a cache instance is of: the view, or the series derived from it."""
        chosen = ",".join(f'{label}{op}"{text}"' for label, op, text in self.matchers)
        return f"{self.inner}({self.view}{{{chosen}}})" if self.inner else self.view

    @property
    def by_series(self) -> bool:
        """Whether whole series, or one derived from them, are asked: what buckets can answer."""
        return bool(self.inner) or all(label == "series" for label, _, _ in self.matchers)


@dataclass(frozen=True)
class Call:
    """A function of an expression's result."""

    fn: str
    child: "Node"


@dataclass(frozen=True)
class Binary:
    """Arithmetic or a comparison of two expressions. Of two series expressions, results of one series and time meet;
    a comparison keeps what it holds for, with the left side's result."""

    op: str
    left: "Node"
    right: "Node"


Node = OverTime | Call | Binary | float


@dataclass(frozen=True)
class RuleSpec:
    """A rule: kind record or alert, evaluated every ``every`` microseconds."""

    name: str
    kind: str
    every: int
    expression: str


_TOKEN = re.compile(r"\s*(?:(\d+(?:\.\d+)?)([smhd])?(?![a-z_0-9])|([a-z_0-9]+)|(\"[^\"]*\")|(=~|!=|!~|==|>=|<=|[-+*/<>=(){}\[\],]))")


class Parser:
    """Recursive descent over rule expressions such as ``max_over_time(ev_type{series="click"}[10d]) * 2 > 5``."""

    def __init__(self, text: str):
        self.tokens: list[tuple[str, str]] = []
        at = 0
        while at < len(text.rstrip()):
            m = _TOKEN.match(text, at)
            if not m:
                raise ValueError(f"unexpected text at {at}: {text[at:]!r}")
            number, unit, name, string, sign = m.groups()
            self.tokens.append(("duration", number + unit) if unit else ("number", number) if number else ("name", name) if name else ("string", string[1:-1]) if string else ("sign", sign))
            at = m.end()
        self.at = 0

    def peek(self) -> tuple[str, str]:
        return self.tokens[self.at] if self.at < len(self.tokens) else ("end", "")

    def take(self, kind: str, text: str | None = None) -> str:
        found = self.peek()
        if found[0] != kind or text is not None and found[1] != text:
            raise ValueError(f"expected {text or kind}, found {found[1] or 'the end'}")
        self.at += 1
        return found[1]

    #: From the loosest to the tightest; all of one level from left to right.
    LEVELS = (("==", "!=", ">", "<", ">=", "<="), ("+", "-"), ("*", "/"))

    def parse(self) -> Node:
        node = self.level(0)
        if self.peek()[0] != "end":
            raise ValueError(f"unexpected {self.peek()[1]}")
        return node

    def level(self, depth: int) -> Node:
        if depth == len(self.LEVELS):
            return self.operand()
        node = self.level(depth + 1)
        while self.peek()[0] == "sign" and self.peek()[1] in self.LEVELS[depth]:
            op = self.take("sign")
            other = self.level(depth + 1)
            node = ARITHMETIC[op](node, other) if isinstance(node, float) and isinstance(other, float) and op in ARITHMETIC else Binary(op, node, other)
        return node

    def operand(self) -> Node:
        if self.peek() == ("sign", "-"):
            self.take("sign")
            child = self.operand()
            return -child if isinstance(child, float) else Binary("*", -1.0, child)
        if self.peek() == ("sign", "("):
            self.take("sign")
            node = self.level(0)
            self.take("sign", ")")
            return node
        if self.peek()[0] == "number":
            return float(self.take("number"))
        name = self.take("name")
        self.take("sign", "(")
        if not name.endswith("_over_time"):
            node = Call(name, self.level(0))
            self.take("sign", ")")
            return node
        arg = None
        if self.peek()[0] == "number":
            arg = float(self.take("number"))
            self.take("sign", ",")
        inner, view = None, self.take("name")
        if self.peek() == ("sign", "("):
            inner = view
            self.take("sign", "(")
            view = self.take("name")
        matchers = self.matchers()
        if inner:
            self.take("sign", ")")
        self.take("sign", "[")
        duration = self.take("duration")
        self.take("sign", "]")
        self.take("sign", ")")
        return OverTime(name.removesuffix("_over_time"), arg, view, matchers, int(float(duration[:-1]) * UNITS[duration[-1]]), inner)

    def matchers(self) -> tuple[tuple[str, str, str], ...]:
        out = []
        if self.peek() == ("sign", "{"):
            self.take("sign", "{")
            while self.peek() != ("sign", "}"):
                out.append((self.take("name"), self.take("sign"), self.take("string")))
                if out[-1][1] not in MATCH:
                    raise ValueError(f"expected an operator of labels, found {out[-1][1]}")
                if self.peek() == ("sign", ","):
                    self.take("sign")
            self.take("sign", "}")
        return tuple(out)


ARITHMETIC = {"+": lambda a, b: a + b, "-": lambda a, b: a - b, "*": lambda a, b: a * b, "/": lambda a, b: a / b}
MATCH = {"=": lambda c, v: c == v, "!=": lambda c, v: c != v, "=~": lambda c, v: c.rlike(f"^(?:{v})$"), "!~": lambda c, v: ~c.rlike(f"^(?:{v})$")}


def parse(text: str) -> Node:
    return Parser(text).parse()


def leaves(node: Node) -> list[OverTime]:
    if isinstance(node, OverTime):
        return [node]
    return [x for child in ((node.child,) if isinstance(node, Call) else (node.left, node.right) if isinstance(node, Binary) else ()) for x in leaves(child)]


def leaf(node: Node) -> OverTime:
    """The only function over time of an expression."""
    (only,) = leaves(node)
    return only


def matching(samples: DataFrame, matchers) -> DataFrame:
    """Samples of the series that all matchers accept; equality is pushed to the scan. The label series is the series'
    name; other labels are columns of ``samples``, and one that they lack is empty."""
    for label, op, text in matchers:
        samples = samples.where(MATCH[op](F.col(label) if label in samples.columns else F.lit(""), text))
    return samples


def inner_aggregate(samples: DataFrame, how: str) -> DataFrame:
    """A derived series: the label dimension aggregated at each time, before the time dimension."""
    derived = samples.groupBy("t").agg(F.expr(f"{how}(value)").alias("value"), F.min("item").alias("item")).select(F.lit(how).alias("series"), "t", "value", "item", F.expr(f"t div {DAY}").alias("pane"))
    return position(derived, ["t"]).select("series", "t", "seq", "value", "item")


def join_series(left: DataFrame, right: DataFrame, how: str) -> DataFrame:
    """A derived series from two series of one time axis: the values at equal times, put together by an operator."""
    other = right.select("t", F.col("value").alias("other"))
    joined = left.join(other, "t").withColumn("value", F.expr(f"value {how} other")).withColumn("pane", F.expr(f"t div {DAY}"))
    return position(joined.drop("seq"), ["t"]).select("series", "t", "seq", "value", "item")


def subject_samples(node: OverTime, samples: DataFrame) -> DataFrame:
    """The samples that a function over time looks at, of those of its view."""
    held = matching(samples, node.matchers)
    return inner_aggregate(held, node.inner) if node.inner else held


def exact_leaf(node: OverTime, samples: DataFrame, grid: Grid) -> DataFrame:
    return over_time(subject_samples(node, samples), node.fn, replace(grid, window=node.window), node.arg)


def evaluate(node: Node, samples: DataFrame | Callable[[str], DataFrame], grid: Grid, over: Callable = exact_leaf) -> DataFrame:
    """series, eval_t, result, and what else the leaves carry: functions over time at each point of the grid, by ``over``, then the
    operations on their results. ``samples`` are those of the only view, or a function of a view's name."""
    if isinstance(node, OverTime):
        return over(node, samples(node.view) if callable(samples) else samples, grid)
    if isinstance(node, Call):
        return evaluate(node.child, samples, grid, over).withColumn("result", F.expr(f"{node.fn}(result)"))
    if isinstance(node, float):
        raise ValueError("a number alone has no series")
    scalars = [x if isinstance(x, float) else None for x in (node.left, node.right)]
    if None not in scalars:
        raise ValueError("a comparison of numbers has no series")
    if scalars == [None, None]:
        found, other = evaluate(node.left, samples, grid, over), evaluate(node.right, samples, grid, over)
        other = other.select("series", "eval_t", F.col("result").alias("other"), *[F.col("source").alias("other_source")] * ("source" in other.columns))
        found = found.join(other, ["series", "eval_t"])
        if "source" in found.columns:
            found = found.withColumn("source", F.when(F.col("source") == F.col("other_source"), F.col("source")).otherwise("mixed")).drop("other_source")
        sides = ("result", "other")
    else:
        found = evaluate(node.right if scalars[1] is None else node.left, samples, grid, over)
        sides = tuple("result" if x is None else f"{x!r}D" for x in scalars)
    changed = F.expr(f"{sides[0]} {node.op} {sides[1]}")
    return (found.withColumn("result", changed) if node.op in ARITHMETIC else found.where(changed)).drop("other")


# -- registry and routing ----------------------------------------------------------------------------------------------


@dataclass
class Registry:
    """Cache instances by view and family, each as wide as the widest rule that uses it."""

    windows: dict[tuple[str, str], int]

    @classmethod
    def of(cls, rules: list[RuleSpec]) -> "Registry":
        found = cls({})
        for rule in rules:
            found.register(rule)
        return found

    def register(self, rule: RuleSpec) -> None:
        for node in leaves(parse(rule.expression)):
            if node.fn in FAMILIES and node.by_series:
                key = (node.subject, FAMILIES[node.fn])
                self.windows[key] = max(self.windows.get(key, 0), node.window)

    def sync(self, rules: list[RuleSpec]) -> list[tuple[str, str]]:
        """Keep what ``rules`` need; returns the instances that go."""
        needed = Registry.of(rules).windows
        gone = sorted(set(self.windows) - set(needed))
        self.windows = needed
        return gone

    def family(self, node: OverTime) -> str | None:
        """The family whose instance covers the window, of those that serve the function."""
        served = [FAMILIES[node.fn], *ALSO.get(node.fn, ())] if node.fn in FAMILIES and node.by_series else []
        return next((f for f in served if self.windows.get((node.subject, f), 0) >= node.window), None)

    def route(self, node: OverTime) -> str:
        """cache if an instance of the function's family covers the window, else exact."""
        return "cache" if self.family(node) else "exact"


def ring_assign(series: list[str], nodes: list[str], virtual: int = 64) -> dict[str, str]:
    """Series to nodes by consistent hashing: a node's points on the ring take what lies before them."""
    at = lambda text: int.from_bytes(hashlib.md5(text.encode()).digest()[:8], "big")
    ring = sorted((at(f"{n}#{i}"), n) for n in nodes for i in range(virtual))
    points = [p for p, _ in ring]
    return {s: ring[bisect(points, at(s)) % len(ring)][1] for s in series}


def coverage() -> list[tuple[str, str]]:
    """Function, and its family or exact."""
    return sorted([*FAMILIES.items(), *((fn, "exact") for fn in UNCOVERED)])


# -- results -----------------------------------------------------------------------------------------------------------


def record(results: DataFrame, name: str, path: str) -> DataFrame:
    """Append results of a recording rule; a point that is recorded already is not recorded again."""
    spark = results.sparkSession
    new = results.withColumn("rule", F.lit(name)).select("rule", "series", "eval_t", F.col("result").cast("double").alias("result"))
    try:
        old = spark.read.parquet(path)
    except Exception as error:
        if "PATH_NOT_FOUND" not in str(error):
            raise
        new.write.partitionBy("rule").parquet(path)
    else:
        new.join(old.where(F.col("rule") == name).select("series", "eval_t"), ["series", "eval_t"], "left_anti").select(*new.columns).write.mode("append").partitionBy("rule").parquet(path)
    return spark.read.parquet(path)


def alerts(results: DataFrame, op: str, threshold: float) -> DataFrame:
    return results.withColumn("firing", F.expr(f"result {op} {threshold!r}D"))


def episodes(firing: DataFrame) -> DataFrame:
    """series, first, last, points: runs of evaluation points at which an alert fires."""
    w = Window.partitionBy("series").orderBy("eval_t")
    runs = firing.withColumn("start", (F.col("firing") & ~F.coalesce(F.lag("firing").over(w), F.lit(False))).cast("int")).withColumn("run", F.sum("start").over(w)).where("firing")
    return runs.groupBy("series", "run").agg(F.min("eval_t").alias("first"), F.max("eval_t").alias("last"), F.count("*").alias("points")).drop("run")


# -- queries -----------------------------------------------------------------------------------------------------------

RULES = [
    RuleSpec("entropy", "alert", DAY, "entropy_over_time(ev_type[2d]) < 4"),
    RuleSpec("distinct_long", "alert", DAY, "distinct_over_time(ev_type[2d]) > 100"),
    RuleSpec("distinct_short", "alert", DAY, "distinct_over_time(ev_type[1d]) > 60"),
    RuleSpec("q90", "record", DAY, "quantile_over_time(0.9, ev_type[5d])"),
    RuleSpec("q90_long", "record", DAY, 'quantile_over_time(0.9, ev_type{series="click"}[10d])'),
    RuleSpec("mean", "record", DAY, "avg_over_time(ev_type[5d]) * 2"),
    RuleSpec("last", "record", DAY, "last_over_time(ev_type[5d])"),
]
_SUBSET = Grid(DAILY.start, DAILY.end, DAY, DAY)


def _rule(text: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        node = parse(text)
        return evaluate(node, lambda view: series_view(spark, sf_dir, view), DAILY)

    return run


def eval_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Points of each rule, where its window begins, and the samples of the events in it."""
    rows = [(r.name, leaf(parse(r.expression)).window) for r in RULES]
    points = spark.createDataFrame(rows, "rule string, width long").withColumn("eval_t", F.expr(f"explode(sequence({DAILY.start}, {DAILY.end}, {DAY}))"))
    times = VIEWS["ev_type"].build(spark, sf_dir).select("t")
    counts = [replace(DAILY, window=w).expand(times).groupBy("eval_t").agg(F.count("*").alias("samples")).withColumn("width", F.lit(w).cast("long")) for w in sorted({w for _, w in rows})]
    found = points.join(reduce(DataFrame.unionByName, counts), ["width", "eval_t"], "left")
    return found.select("rule", "eval_t", (F.col("eval_t") - F.col("width")).alias("low"), F.coalesce("samples", F.lit(0)).alias("samples"))


def _held(spark: SparkSession, sf_dir: str, rows: list[tuple], schema: str) -> DataFrame:
    """``rows``, of which width is one column, with the samples of the events in the last width of the grid."""
    age = F.lit(DAILY.end) - F.col("t")
    widths = spark.createDataFrame(rows, schema)
    at = [name.split()[0] for name in schema.split(", ")].index("width")
    counts = [F.struct(F.lit(w).cast("long").alias("width"), F.count_if((age >= 0) & (age < w)).alias("samples")) for w in sorted({row[at] for row in rows})]
    return widths.join(VIEWS["ev_type"].build(spark, sf_dir).agg(F.array(*counts).alias("each")).select(F.inline("each")), "width").select(*widths.columns, "samples")


def registry_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The instances that the rules need, with the samples of the events that each has to cover."""
    return _held(spark, sf_dir, [(v, f, w) for (v, f), w in Registry.of(RULES).windows.items()], "view string, family string, width long")


def route_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Where each rule is answered, with the samples of the view in its last window."""
    registry = Registry.of(RULES[:4])
    nodes = {r.name: leaf(parse(r.expression)) for r in RULES}
    return _held(spark, sf_dir, [(name, registry.route(node), node.window) for name, node in nodes.items()], "rule string, source string, width long").drop("width")


def sync_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The instances that go with the other rules, with the samples of the events that they covered."""
    registry = Registry.of(RULES)
    widths = registry.windows
    return _held(spark, sf_dir, [(*key, widths[key]) for key in registry.sync(RULES[3:5])], "view string, family string, width long").drop("width")


def coverage_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each function's family, or exact, with the samples of the events in a window of the grid."""
    return _held(spark, sf_dir, [(*row, DAILY.window) for row in coverage()], "fn string, family string, width long").drop("width")


def record_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recorded twice, each point is there once."""
    path = Scratch(spark, "record").root + "/results"
    results = _rule("quantile_over_time(0.9, ev_type[5d])")(spark, sf_dir)
    record(results, "q90", path)
    return record(results, "q90", path).select("series", "eval_t", "result")


def episodes_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return episodes(alerts(_rule("avg_over_time(ev_type[1d])")(spark, sf_dir), ">", 42.0))


def ring_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Of a series for each order, how many move when a fifth node joins: only to the new one."""

    def assigned(batches):
        for batch in batches:
            series = [f"s{key}" for key in batch["o_orderkey"]]
            before, after = ring_assign(series, list("abcd")), ring_assign(series, list("abcde"))
            yield pd.DataFrame({"before": [before[s] for s in series], "after": [after[s] for s in series]}, dtype="object")

    placed = table(spark, sf_dir, "orders").select("o_orderkey").mapInPandas(assigned, "before string, after string")
    moved = F.col("before") != F.col("after")
    found = placed.agg(F.count("*").alias("series"), F.count_if(moved).alias("moved"), F.count_if(moved & (F.col("after") != "e")).alias("astray"))
    return found.select("series", (F.col("astray") == 0).alias("only_to_new"), F.expr("moved between 0.1 * series and 0.32 * series").alias("about_a_fifth"))


def label_then_time(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Average over time of the maximum over series: embeddings' dimensions at each tick."""
    found = inner_aggregate(series_view(spark, sf_dir, "emb_dim"), "max")
    return found.groupBy(F.expr("(seq - 1) div 100").alias("block")).agg(F.count("*").alias("n"), F.max("value").alias("top"), F.min("value").alias("low"))


def join_then_time(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The difference of two dimensions, over time."""
    dims = series_view(spark, sf_dir, "emb_dim")
    found = join_series(dims.where("series = '0'"), dims.where("series = '1'"), "-")
    return found.groupBy(F.expr("(seq - 1) div 100").alias("block")).agg(F.count("*").alias("n"), F.max("value").alias("top"))


_V = VIEWS["ev_type"].sql


def _sql(aggregate: str, window: int, where: str = "true", view: str = _V) -> str:
    grid = replace(DAILY, window=window)
    return f"SELECT series, eval_t, {aggregate} AS result FROM (SELECT *, cast(round(value * 100) AS bigint) AS c FROM ({grid.sql(view)})) WHERE {where} GROUP BY series, eval_t"


_AVG = "round(sum(c) / 100.0 / count(*), 6)"
_CASES = {
    "rule_quantile": ("quantile_over_time(0.9, ev_type[5d])", _sql("round(quantile_cont(value, 0.9), 6)", 5 * DAY)),
    "rule_selector": ('max_over_time(ev_type{series!="click"}[2d])', _sql("max(value)", 2 * DAY, "series <> 'click'")),
    "rule_regex": ('min_over_time(ev_type{series=~"c.*|v.*"}[2d])', _sql("min(value)", 2 * DAY, "series SIMILAR TO 'c.*|v.*'")),
    "rule_scaled": ("avg_over_time(ev_type[5d]) * 2", _sql(f"{_AVG} * 2", 5 * DAY)),
    "rule_threshold": ("avg_over_time(ev_type[1d]) > 42", f"SELECT * FROM ({_sql(_AVG, DAY)}) WHERE result > 42"),
    "rule_outer_function": ("floor(max_over_time(ev_type[10d]))", _sql("cast(floor(max(value)) AS bigint)", 10 * DAY)),
    "rule_alert_distinct": ("distinct_over_time(ev_type[1d]) > 40", f"SELECT * FROM ({_sql('count(DISTINCT item)', DAY)}) WHERE result > 40"),
    "rule_alert_entropy": ("entropy_over_time(ev_type[2d]) < 4", f"SELECT * FROM (SELECT series, eval_t, round(ln(sum(c)) - sum(c * ln(c)) / sum(c), 6) AS result FROM (SELECT series, eval_t, item, count(*)::BIGINT AS c FROM ({replace(DAILY, window=2 * DAY).sql(_V)}) GROUP BY ALL) GROUP BY ALL) WHERE result < 4"),
    "rule_precedence": ("1 + avg_over_time(ev_type[5d]) * (4 - 1) / 2", _sql(f"1 + {_AVG} * 3 / 2", 5 * DAY)),
    "rule_two_series": ("max_over_time(ev_type[5d]) - min_over_time(ev_type[2d]) > 90", f"SELECT a.series, a.eval_t, a.result - b.result AS result FROM ({_sql('max(value)', 5 * DAY)}) a JOIN ({_sql('min(value)', 2 * DAY)}) b ON a.series = b.series AND a.eval_t = b.eval_t WHERE a.result - b.result > 90"),
    "rule_labels": ('count_over_time(ev_type{series!="view",item=~"1.*"}[5d])', _sql("count(*)", 5 * DAY, "series <> 'view' AND item LIKE '1%'")),
    "rule_other_label": ('max_over_time(ev_type{host!="click"}[5d])', _sql("max(value)", 5 * DAY)),
    "rule_inner_max": ("avg_over_time(max(ev_type)[5d])", _sql(_AVG, 5 * DAY, view=f"SELECT 'max' AS series, t, max(value) AS value FROM ({_V}) GROUP BY t")),
}
QUERIES: dict = {name: _rule(text) for name, (text, _) in _CASES.items()}
QUERIES |= {
    "rule_eval_points": eval_points, "cache_registry": registry_query, "route_rules": route_query, "cache_sync": sync_query, "coverage_report": coverage_query, "record_idempotent": record_query,
    "alert_episodes": episodes_query, "cache_ring": ring_query, "workload_label_then_time": label_then_time, "workload_join_then_time": join_then_time,
}
SQL: dict = {name: sql for name, (_, sql) in _CASES.items()}
def _held_sql(columns: str, rows: str, names: str) -> str:
    return f"SELECT {columns}, count(t) AS samples FROM (VALUES {rows}) AS r({names}) LEFT JOIN ({_V}) ON t > {DAILY.end} - width AND t <= {DAILY.end} GROUP BY ALL"


_E = f"(SELECT series, eval_t, {_AVG} > 42 AS firing FROM (SELECT *, cast(round(value * 100) AS bigint) AS c FROM ({replace(DAILY, window=DAY).sql(_V)})) GROUP BY series, eval_t)"
SQL |= {
    "rule_eval_points": f"SELECT rule, eval_t, eval_t - width AS low, count(t) AS samples FROM (VALUES {', '.join(f'({chr(39)}{r.name}{chr(39)}, {leaf(parse(r.expression)).window}::BIGINT)' for r in RULES)}) AS r(rule, width) CROSS JOIN (SELECT unnest(range({DAILY.start}, {DAILY.end} + 1, {DAY})) AS eval_t) LEFT JOIN (SELECT epoch_us(ts) AS t FROM events) ON t > eval_t - width AND t <= eval_t GROUP BY ALL",
    "cache_registry": _held_sql("view, family, width", f"('ev_type', 'univ', {2 * DAY}), ('ev_type', 'kll', {10 * DAY}), ('ev_type', 'sample', {5 * DAY})", "view, family, width"),
    "route_rules": "SELECT rule, source, samples FROM (" + _held_sql("rule, source, width", ", ".join(f"('{rule}', '{source}', {days * DAY})" for rule, source, days in (("entropy", "cache", 2), ("distinct_long", "cache", 2), ("distinct_short", "cache", 1), ("q90", "cache", 5), ("q90_long", "exact", 10), ("mean", "exact", 5), ("last", "exact", 5))), "rule, source, width") + ")",
    "cache_sync": "SELECT view, family, samples FROM (" + _held_sql("view, family, width", f"('ev_type', 'sample', {5 * DAY}), ('ev_type', 'univ', {2 * DAY})", "view, family, width") + ")",
    "record_idempotent": _sql("round(quantile_cont(value, 0.9), 6)", 5 * DAY),
    "alert_episodes": f"SELECT series, min(eval_t) AS first, max(eval_t) AS last, count(*) AS points FROM (SELECT series, eval_t, firing, row_number() OVER (PARTITION BY series ORDER BY eval_t) - row_number() OVER (PARTITION BY series, firing ORDER BY eval_t) AS run FROM {_E}) WHERE firing GROUP BY series, run",
    "cache_ring": "SELECT count(*) AS series, true AS only_to_new, true AS about_a_fifth FROM orders",
    "workload_label_then_time": f"SELECT (seq - 1) // 100 AS block, count(*) AS n, max(value) AS top, min(value) AS low FROM (SELECT row_number() OVER (ORDER BY t) AS seq, max(value) AS value FROM ({VIEWS['emb_dim'].sql}) GROUP BY t) GROUP BY block",
    "workload_join_then_time": f"WITH v AS ({VIEWS['emb_dim'].sql}) SELECT (a.seq - 1) // 100 AS block, count(*) AS n, max(a.value - b.value) AS top FROM v a JOIN v b ON a.t = b.t AND a.series = '0' AND b.series = '1' GROUP BY block",
}
assert set(AGGREGATES) | set(OF_COUNTS) >= set(FAMILIES) - {"topk"}

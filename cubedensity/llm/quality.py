"""Quality rules as a learned decision list, in DataFrame functions only.

Statistics of the whole text are computed with SQL functions. A decision list for the low class is learned by
sequential covering: a rule is a conjunction of thresholds, grown on two thirds of the labelled rows by information
gain and pruned on the rest; rows that a rule covers are set aside before the next one. The list becomes one
ordered conditional expression that Spark evaluates.

Learning reads at most about ``SAMPLE_ROWS`` labelled rows, taken by a hash of the id; only their thresholded
statistics, counted by cell, reach the driver. Statistics and verdicts cover every row.

Inputs: null texts have no words and fail the base test; repeated labels of an id count once (the larger label);
without labels, or with one class only, the list is empty and the base test decides; extra columns are ignored.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cubedensity.llm.common import bind, durable

SAMPLE_ROWS = 8_000
CUTS = 12
MOST_RULES = 12
MOST_CONDITIONS = 4
WORD_GAP = "[\\x20\\x09-\\x0D]+"
WINDOW = 8

#: name -> expression over the base statistics; the inputs of the learned rules
FEATURES = {
    "words": "cast(n_words as double)",
    "word_length": "word_chars / greatest(n_words, 1)",
    "symbols_per_word": "n_symbols / greatest(n_words, 1)",
    "repeated_lines": "n_dup_lines / greatest(n_lines, 1)",
    "repeated_words": "n_repeat_words / greatest(n_words, 1)",
    "capital_share": "n_capitals / greatest(word_chars, 1)",
    "exclaim_per_word": "n_exclaim / greatest(n_words, 1)",
    "stop_per_word": "n_stops / greatest(n_words, 1)",
    "words_per_line": "n_words / greatest(n_lines, 1)",
    "distinct_share": "n_distinct / greatest(n_words, 1)",
    "bars_per_word": "n_bars / greatest(n_words, 1)",
}


def _without(c: Column, chars: str) -> Column:
    return F.length(F.translate(c, chars, ""))


def _repeated(words: Column) -> Column:
    """Words inside windows of WINDOW words that occur at least twice in the text."""
    n = F.size(words)
    hashes = F.transform(F.sequence(F.lit(1), n - WINDOW + 1), lambda i: F.xxhash64(F.slice(words, i, WINDOW)))

    def covered(h):
        tagged = F.array_sort(F.transform(h, lambda x, i: F.struct(x.alias("h"), i.alias("i"))))

        def starts(t):
            same = F.transform(
                t, lambda x, i: F.when((F.get(t, i - 1)["h"] == x["h"]) | (F.get(t, i + 1)["h"] == x["h"]), x["i"])
            )
            return F.array_sort(F.filter(same, lambda x: x.isNotNull()))

        def total(s):
            gaps = F.transform(s, lambda x, i: F.least(F.lit(WINDOW), F.coalesce(F.get(s, i + 1) - x, F.lit(WINDOW))))
            return F.aggregate(gaps, F.lit(0), lambda a, x: a + x)

        return F.when(F.size(F.array_distinct(h)) == F.size(h), F.lit(0)).otherwise(bind(bind(tagged, starts), total))

    return F.when(n < WINDOW, F.lit(0)).otherwise(bind(hashes, covered))


def statistics(docs: DataFrame) -> DataFrame:
    """``docs`` with the statistics of the whole text as columns; same-named columns are replaced."""
    text = F.coalesce("text", F.lit(""))
    words = F.filter(F.split(text, WORD_GAP), lambda w: w != "")
    lines = F.filter(F.split(text, "\n"), lambda x: _without(x, " \t\n\x0b\f\r") > 0)
    long = lambda c: c.cast("long")

    def measured(w):
        return F.struct(
            long(F.size(w)).alias("n_words"), long(_repeated(w)).alias("n_repeat_words"), long(F.size(F.array_distinct(w))).alias("n_distinct")
        )

    def by_line(x):
        return F.struct(long(F.size(x)).alias("n_lines"), long(F.size(x) - F.size(F.array_distinct(x))).alias("n_dup_lines"))

    whole = F.length(text)
    made = {
        "_w": bind(words, measured),
        "_l": bind(lines, by_line),
        "word_chars": long(_without(text, " \t\n\x0b\f\r")),
        "n_symbols": long(whole - _without(text, "#*$%&|<>")),
        "n_capitals": long(whole - _without(text, "ABCDEFGHIJKLMNOPQRSTUVWXYZ")),
        "n_exclaim": long(whole - _without(text, "!")),
        "n_stops": long(whole - _without(text, ".")),
        "n_bars": long(whole - _without(text, "|")),
    }
    names = {*made, "n_words", "n_repeat_words", "n_distinct", "n_lines", "n_dup_lines", "base_failed", "_pos"}
    kept = docs.select(*(c for c in docs.columns if c not in names))
    out = kept.select("*", *(c.alias(k) for k, c in made.items())).select("*", "_w.*", "_l.*").drop("_w", "_l")
    failed = (F.col("n_words") < 20) | (100 * F.col("n_repeat_words") > 30 * F.col("n_words"))
    return out.withColumn("base_failed", failed)


@dataclass(frozen=True)
class Condition:
    feature: str
    at_least: bool
    cut: float

    def column(self) -> Column:
        value = F.expr(FEATURES[self.feature])
        return value >= self.cut if self.at_least else value < self.cut

    def __str__(self) -> str:
        return f"{self.feature} {'>=' if self.at_least else '<'} {self.cut:.6g}"


def labelled(docs: DataFrame, labels: DataFrame, target: str = "quality", rows: int = SAMPLE_ROWS) -> DataFrame:
    """Statistics of about ``rows`` labelled documents that pass the base test, with ``low`` and a ``fold``."""
    clean = labels.filter(F.col("doc_id").isNotNull() & F.col(target).isNotNull())
    known = max(1, clean.count())
    share = min(1 << 20, math.ceil(rows * (1 << 20) / known))
    chosen = (
        clean.filter(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 20)) < share)
        .groupBy(F.col("doc_id").alias("_lid"))
        .agg(F.max(target).alias("_good"))
    )
    joined = docs.select("doc_id", "text").join(F.broadcast(chosen), F.col("doc_id") == F.col("_lid"))
    fold = F.pmod(F.xxhash64("doc_id", F.lit("fold")), F.lit(3)) == 0
    made = statistics(joined).select(
        "base_failed", (F.col("_good") == 0).alias("low"), fold.alias("prune"), *(F.expr(e).alias(f) for f, e in FEATURES.items())
    )
    # cut here, else the filter would be pushed below the join and the statistics be made for every row
    return durable(made).filter(~F.col("base_failed")).drop("base_failed")


def learn(sample: DataFrame, cuts: int = CUTS, most_rules: int = MOST_RULES) -> list[tuple[Condition, ...]]:
    """Rules for the low class, in order. Thresholds are quantiles of the sample."""
    names = list(FEATURES)
    points = [i / (cuts + 1) for i in range(1, cuts + 1)] + [0.005, 0.995]
    got = sample.agg(*(F.percentile_approx(f, points, 10_000).alias(f) for f in names)).first()
    edges = {f: sorted({0.0, *(got[f] or [])} if f.endswith(("per_word", "share", "lines", "words")) else set(got[f] or [])) for f in names}
    # a cell is the number of thresholds that a value passes, for each statistic
    step = {f: [math.nextafter(e, math.inf) if e == 0.0 else e for e in edges[f]] for f in names}
    cell = [sum([(F.col(f) >= e).cast("int") for e in step[f]], F.lit(0)).alias(f) for f in names]
    rows = sample.select("low", "prune", *cell).groupBy("low", "prune", *names).count().collect()
    cells = [(tuple(r[f] for f in names), bool(r["low"]), bool(r["prune"]), r["count"]) for r in rows]
    return [
        tuple(Condition(names[j], up, step[names[j]][k - 1]) for j, up, k in rule) for rule in _cover(cells, [len(step[f]) for f in names], most_rules)
    ]


def _holds(rule, values) -> bool:
    return all((values[j] >= k) == up for j, up, k in rule)


def _worth(rule, cells) -> float:
    """Share of right decisions that a rule adds on the cells it covers."""
    p = sum(n for v, low, _, n in cells if low and _holds(rule, v))
    q = sum(n for v, low, _, n in cells if not low and _holds(rule, v))
    return (p - q) / (p + q) if p + q else -1.0


def _grow(cells, sizes):
    rule: list = []
    while len(rule) < MOST_CONDITIONS:
        p0 = sum(n for _, low, _, n in cells if low)
        q0 = sum(n for _, low, _, n in cells if not low)
        if not p0 or not q0:
            break
        best = (1e-9, None)
        for j, size in enumerate(sizes):
            low_at, high_at = [0] * (size + 1), [0] * (size + 1)
            for v, low, _, n in cells:
                (low_at if low else high_at)[v[j]] += n
            p_up, q_up = p0, q0
            for k in range(1, size + 1):
                p_up, q_up = p_up - low_at[k - 1], q_up - high_at[k - 1]
                for up, p, q in ((True, p_up, q_up), (False, p0 - p_up, q0 - q_up)):
                    if p:
                        gain = p * (math.log2(p / (p + q)) - math.log2(p0 / (p0 + q0)))
                        best = max(best, (gain, (j, up, k)), key=lambda x: x[0])
        if best[1] is None:
            break
        rule.append(best[1])
        cells = [c for c in cells if _holds(rule[-1:], c[0])]
    return rule


def _cover(cells, sizes, most_rules):
    rules = []
    while len(rules) < most_rules:
        grow, prune = [c for c in cells if not c[2]], [c for c in cells if c[2]]
        rule = _grow(grow, sizes)
        if not rule:
            break
        worth = [_worth(rule[:k], prune) for k in range(1, len(rule) + 1)]
        rule = rule[: 1 + worth.index(max(worth))]
        if _worth(rule, prune) <= 0:
            break
        rules.append(tuple(rule))
        cells = [c for c in cells if not _holds(rule, c[0])]
        if sum(n for _, low, p, n in cells if low and not p) < 3:
            break
    return rules


def verdict(rules: list[tuple[Condition, ...]]) -> Column:
    """Number of the first rule that holds, 0 where none does: one ordered conditional expression."""
    out = None
    for number, rule in enumerate(rules, 1):
        held = rule[0].column()
        for c in rule[1:]:
            held = held & c.column()
        out = F.when(held, F.lit(number)) if out is None else out.when(held, F.lit(number))
    return F.lit(0) if out is None else out.otherwise(F.lit(0))


def judge(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """Base statistics, the base test and the verdict of the learned list for every row."""
    rules = learn(labelled(docs, labels))
    return statistics(docs.select("doc_id", "text")).select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", verdict(rules).alias("rule")
    ).select("*", (~F.col("base_failed") & (F.col("rule") == 0)).alias("kept"))

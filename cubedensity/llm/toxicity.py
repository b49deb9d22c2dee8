"""Counterfactual-regularised toxicity classifier.

A logistic model over the words of a text and their beginnings (presence, whole text). While it is fitted, every
labelled sentence that names a group is repeated with the term swapped for others of its list and for no term at all,
and the change of the score is penalised, so that naming a group does not move the score by itself. (Swaps among groups
alone would only make all groups of a list equally suspect.)

Fitting uses at most about ``SAMPLE_ROWS`` labelled rows, taken by a hash of the id and never from the held-out
fifth; features are counted on the executors. Scores are given for every row from the text alone.

Inputs: null and empty texts get the score of the intercept; texts of any length are read whole; a null id is never held
out; repeated labels of an id count once (the larger label); repeated rows get equal scores; features that tie are taken in
the order of their names; without labels of both classes every score is near the share of toxic labels (0 if none); an
empty table gives none; a column ``_score`` is replaced, other extra columns are kept by ``reject_toxic`` and else not returned.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cubedensity.llm.common import durable, released

SAMPLE_ROWS = 12_000
FEATURES = 6_000
LEAST_TOXIC = 3
PREFIXES = (4, 5, 6, 7, 8)
SWAP_WEIGHT = 1.0
SWAPS = 3
RIDGE = 1e-4
STEPS = 400

#: fixed values: terms that name groups of people, by list
IDENTITY = [
    s.split()
    for s in (
        "man woman men women boy girl male female transgender nonbinary",
        "christian muslim jewish hindu buddhist atheist catholic protestant sikh",
        "black white asian latino hispanic african european arab indian",
        "american mexican chinese german french spanish russian turkish polish",
        "gay lesbian straight bisexual heterosexual homosexual queer",
        "disabled blind deaf autistic old young elderly",
        "homme femme hommes femmes garçon fille",
        "chrétien musulman juif hindou bouddhiste athée",
        "mann frau männer frauen junge mädchen",
        "christ muslimin jude hinduist buddhistin atheistin",
        "hombre mujer hombres mujeres chico chica",
        "cristiano musulmán judío hinduista budista ateo",
    )
]
_GROUP = {w: (g, i) for g, terms in enumerate(IDENTITY) for i, w in enumerate(terms)}
_WORD = re.compile(r"[^\W\d_]+")
_SENTENCE = re.compile(r"[^.!?\n]+")


def words_of(text: str | None) -> set[str]:
    return set(_WORD.findall((text or "").lower()))


def expand(words: set[str]) -> set[str]:
    """Words and, marked by a star, their beginnings."""
    return words | {w[:k] + "*" for w in words for k in PREFIXES if len(w) > k}


def swapped(text: str | None) -> list[tuple[str, str]]:
    """(term, other term or nothing) for the group terms in the sentences of a text."""
    out = []
    for sentence in _SENTENCE.findall((text or "").lower()):
        for w in _WORD.findall(sentence):
            if w in _GROUP:
                g, i = _GROUP[w]
                out += [(w, IDENTITY[g][(i + k) % len(IDENTITY[g])]) for k in range(1, min(SWAPS, len(IDENTITY[g]) - 1) + 1)]
                out.append((w, ""))
    return sorted(set(out))


@dataclass
class Model:
    bias: float = -30.0
    weights: dict[str, float] = field(default_factory=dict)

    def __post_init__(self):
        self.heads = {w[: PREFIXES[0]] for w in self.weights if w.endswith("*")}

    def logit(self, text: str | None) -> float:
        weights, hits = self.weights, set()
        for w in words_of(text):
            if w in weights:
                hits.add(w)
            if w[: PREFIXES[0]] in self.heads:
                for k in PREFIXES:
                    if len(w) > k and w[:k] + "*" in weights:
                        hits.add(w[:k] + "*")
        return self.bias + math.fsum(weights[h] for h in hits)

    def score(self, text: str | None) -> float:
        z = self.logit(text)
        return 1 / (1 + math.exp(-z)) if z >= 0 else math.exp(z) / (1 + math.exp(z))


def held_out(id_col: str = "doc_id") -> Column:
    return F.coalesce(F.crc32(F.col(id_col).cast("string").cast("binary")) % 5 == 0, F.lit(False))


def training_rows(docs: DataFrame, labels: DataFrame, rows: int = SAMPLE_ROWS) -> DataFrame:
    """``(text, toxic)`` of about ``rows`` labelled documents outside the held-out fifth."""
    usable = labels.filter(F.col("doc_id").isNotNull() & F.col("toxic").isNotNull() & ~held_out())
    share = min(1 << 20, math.ceil(rows * (1 << 20) / max(1, usable.count())))
    chosen = usable.filter(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 20)) < share).groupBy(F.col("doc_id").alias("_lid")).agg(F.max("toxic").alias("toxic"))
    return docs.select("doc_id", "text").join(F.broadcast(chosen), F.col("doc_id") == F.col("_lid")).select("text", "toxic")


def _counted(batches):
    """Per task: how many toxic and other texts have each feature."""
    seen: tuple[Counter, Counter] = (Counter(), Counter())
    for batch in batches:
        for text, toxic in zip(batch.column("text").to_pylist(), batch.column("toxic").to_pylist()):
            seen[int(toxic == 1)].update(expand(words_of(text)))
    names = list(seen[0] | seen[1])
    for at in range(0, len(names), 50_000):
        part = names[at : at + 50_000]
        yield pa.RecordBatch.from_arrays(
            [pa.array(part, pa.string()), pa.array([seen[1][n] for n in part], pa.int64()), pa.array([seen[0][n] for n in part], pa.int64())],
            names=["feature", "toxic", "other"],
        )


def _rows(number: dict[str, int]):
    def run(batches):
        for batch in batches:
            texts = batch.column("text").to_pylist()
            has, swap = [], []
            for text in texts:
                words = words_of(text)
                has.append(sorted(number[f] for f in expand(words) if f in number))
                swap.append([f"{a} {b}" for a, b in swapped(text)] if words & _GROUP.keys() else [])
            yield pa.RecordBatch.from_arrays(
                [pa.array([int(t == 1) for t in batch.column("toxic").to_pylist()], pa.int32()), pa.array(has, pa.list_(pa.int32())), pa.array(swap, pa.list_(pa.string()))],
                names=["toxic", "has", "swap"],
            )

    return run


def fit(docs: DataFrame, labels: DataFrame, rows: int = SAMPLE_ROWS, features: int = FEATURES, swap_weight: float = SWAP_WEIGHT) -> Model:
    sample = durable(training_rows(docs, labels, rows))
    totals = {r["toxic"]: r["count"] for r in sample.groupBy((F.col("toxic") == 1).alias("toxic")).count().collect()}
    p, q = totals.get(True, 0), totals.get(False, 0)
    if not p or not q:
        share = p / (p + q) if p + q else 0.0
        return Model(30.0 if share == 1 else -30.0)
    counted = sample.mapInArrow(released(_counted), "feature string, toxic bigint, other bigint").groupBy("feature").agg(F.sum("toxic").alias("t"), F.sum("other").alias("o"))
    lift = F.log((F.col("t") + 0.5) / p) - F.log((F.col("o") + 0.5) / q)
    best = counted.filter((F.col("t") >= LEAST_TOXIC) & (lift > math.log(3))).orderBy((F.col("t") * lift).desc(), "feature").limit(features)
    names = [r["feature"] for r in best.select("feature").collect()]
    names += sorted({f for w in _GROUP for f in expand({w})} - set(names))
    number = {f: i for i, f in enumerate(names)}
    got = sample.mapInArrow(released(_rows(number)), "toxic int, has array<int>, swap array<string>").toArrow()
    # one order for the sums, however the rows arrive
    data = sorted(zip(got["toxic"].to_pylist(), map(tuple, got["has"].to_pylist()), map(tuple, got["swap"].to_pylist())))
    weights, bias = _descend(data, number, swap_weight)
    return Model(float(bias), {f: float(w) for f, w in zip(names, weights) if w})


def _descend(data, number: dict[str, int], swap_weight: float):
    """Full-batch Adam on logistic loss, ridge, and the squared change of the score under each swap."""
    n, m = len(data), len(number)
    y = np.array([d[0] for d in data], float)
    row = np.repeat(np.arange(n), [len(d[1]) for d in data])
    col = np.array([j for d in data for j in d[1]], np.int64)
    s_row, s_col, s_val, swaps = [], [], [], 0
    for _, has, pairs in data:
        present = set(has)
        for pair in pairs:
            a, b = (expand({w}) if w else set() for w in pair.split(" "))
            # beginnings that other words of the text have too stay as they are
            change = [(number[f], -1.0) for f in sorted(a - b) if number[f] in present] + [(number[f], 1.0) for f in sorted(b - a) if number[f] not in present]
            s_row += [swaps] * len(change)
            s_col += [c for c, _ in change]
            s_val += [v for _, v in change]
            swaps += 1
    s_row, s_col, s_val = np.array(s_row, np.int64), np.array(s_col, np.int64), np.array(s_val)
    w, bias = np.zeros(m + 1), math.log(max(y.sum(), 0.5) / max(n - y.sum(), 0.5))
    w[m] = bias
    first, second = np.zeros(m + 1), np.zeros(m + 1)
    for step in range(1, STEPS + 1):
        z = np.bincount(row, w[col], n) + w[m]
        off = 1 / (1 + np.exp(-np.clip(z, -40, 40))) - y
        grad = np.append(np.bincount(col, off[row], m) / n + RIDGE * w[:m], off.mean())
        if swaps:
            delta = np.bincount(s_row, w[s_col] * s_val, swaps)
            grad[:m] += 2 * swap_weight / swaps * np.bincount(s_col, delta[s_row] * s_val, m)
        first = 0.9 * first + 0.1 * grad
        second = 0.999 * second + 0.001 * grad**2
        w -= 0.1 * (first / (1 - 0.9**step)) / (np.sqrt(second / (1 - 0.999**step)) + 1e-8)
    return w[:m], w[m]


def scored(docs: DataFrame, model: Model) -> DataFrame:
    """``docs`` with a column ``_score``; a column of that name is replaced."""
    docs = docs.select(*(c for c in docs.columns if c != "_score"))

    def run(batches):
        for batch in batches:
            made = pa.array([model.score(t) for t in batch.column("text").to_pylist()], pa.float64())
            yield pa.RecordBatch.from_arrays([*batch.columns, made], names=[*batch.schema.names, "_score"])

    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields)
    return docs.mapInArrow(released(run), f"{kinds}, _score double")


def classify(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """``(doc_id, held_out, score, predicted)`` for every row."""
    out = scored(docs.select("doc_id", "text"), fit(docs, labels))
    return out.select("doc_id", held_out().alias("held_out"), F.col("_score").alias("score"), (F.col("_score") >= 0.5).cast("int").alias("predicted"))


def reject_toxic(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """``docs`` without the texts that the model calls toxic."""
    row = docs.select(F.struct(*docs.columns).alias("row"), F.col("text"))
    return scored(row, fit(docs, labels)).filter(F.col("_score") < 0.5).select("row.*")

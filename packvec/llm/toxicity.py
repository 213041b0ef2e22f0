"""Operator 9: toxicity by class-conditional Kneser-Ney models of words as character sequences.

For each class a model of order ORDER gives the probability of a word's characters. Its highest order has the counts of
the class; all lower orders are continuation counts that both classes share, so that an expression neither class has
seen often is judged alike by both. A word's evidence is the difference of its two log-likelihoods, in whole or by
length; a document's are the two strongest words', the sum over a margin, that sum by length, and the mean over its
distinct words. A logistic regression, fitted on labelled rows the counts have not seen, turns these into a probability.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from packvec.llm.common import bounded, written

#: Characters of an n-gram; discount.
ORDER, DISCOUNT = 4, 0.75
#: Distinct words, and n-grams, whose evidence a worker remembers.
MEMORY = 300_000
WORD = re.compile(r"\w+")
LONGEST = 40
#: Evidence of a word that counts towards the sum, and numbers that describe a document.
MARGIN, FEATURES = 1.5, 6


def distinct_words(text: str | None) -> set[str]:
    return set(WORD.findall(text.lower())) if text else set()


def pieces(word: str) -> list[str]:
    """All n-grams of a word between boundary marks; words over LONGEST characters are taken in overlapping cuts."""
    if len(word) > LONGEST:
        return [g for i in range(0, len(word) - ORDER, LONGEST - ORDER) for g in pieces(word[i : i + LONGEST])]
    marked = "^" * (ORDER - 1) + word + "$"
    return [marked[i : i + ORDER] for i in range(len(word) + 1)]


class Model:
    """Counts of both classes. grams: (n-gram, count in toxic words, count in ordinary words)."""

    def __init__(self, grams: Iterator[tuple[str, int, int]]):
        self.top: dict[str, tuple[int, int]] = {}
        self.contexts: dict[str, list[int]] = {}
        for g, toxic, ordinary in grams:
            self.top[g] = (toxic, ordinary)
            c = self.contexts.setdefault(g[:-1], [0, 0, 0, 0])
            c[0] += toxic
            c[1] += toxic > 0
            c[2] += ordinary
            c[3] += ordinary > 0
        self.shared: list[dict[str, int]] = []
        self.sums: list[dict[str, list[int]]] = []
        longer = self.top.keys()
        for _ in range(ORDER - 1):
            counts = Counter(g[1:] for g in longer)
            sums: dict[str, list[int]] = {}
            for g, n in counts.items():
                s = sums.setdefault(g[:-1], [0, 0])
                s[0] += n
                s[1] += 1
            self.shared.append(dict(counts))
            self.sums.append(sums)
            longer = counts.keys()
        self.weights: list[float] | None = None
        self.known: dict[str, float] = {}
        self.told: dict[str, float] = {}

    def backoff(self, g: str, level: int = 0) -> float:
        """Shared probability of g's last character after the others, from continuation counts."""
        if level == ORDER - 1:
            return 1 / 500
        sums = self.sums[level].get(g[:-1])
        lower = self.backoff(g[1:], level + 1)
        if sums is None:
            return lower
        n = self.shared[level].get(g, 0)
        return (max(n - DISCOUNT, 0.0) + DISCOUNT * sums[1] * lower) / sums[0]

    def gram(self, g: str) -> float:
        """log-likelihood of g's last character after the others as toxic less that as ordinary."""
        c = self.contexts.get(g[:-1])
        if c is None:
            return 0.0
        nt, no = self.top.get(g, (0, 0))
        p = self.backoff(g[1:])
        toxic = (max(nt - DISCOUNT, 0.0) + DISCOUNT * c[1] * p) / c[0] if c[0] else p
        ordinary = (max(no - DISCOUNT, 0.0) + DISCOUNT * c[3] * p) / c[2] if c[2] else p
        return math.log(toxic / ordinary)

    def evidence(self, word: str) -> float:
        """log-likelihood as toxic less log-likelihood as ordinary. What an n-gram adds is worked out once."""
        out, told = 0.0, self.told
        if len(told) > MEMORY:
            told.clear()
        for g in pieces(word):
            x = told.get(g)
            if x is None:
                told[g] = x = self.gram(g)
            out += x
        return out

    def features(self, text: str | None) -> tuple[float, ...]:
        """The FEATURES of a text: what its distinct words say."""
        words, known = distinct_words(text), self.known
        if not words:
            return (0.0,) * FEATURES
        if len(known) > MEMORY:
            known.clear()
        best = second = above = total = 0.0
        for w in words:
            x = known.get(w)
            if x is None:
                known[w] = x = self.evidence(w)
            total += x
            if x > MARGIN:
                above += x - MARGIN
            if x > second:
                best, second = (x, best) if x > best else (best, x)
        n = len(words)
        return (best, second, above / math.sqrt(n + 10), math.log1p(above), total / n, math.log1p(n))

    def score(self, text: str | None) -> float:
        w = self.weights
        if w is None:
            return 0.0
        z = w[-1] + sum(a * b for a, b in zip(w, self.features(text)))
        return 1 / (1 + math.exp(-max(-40.0, min(40.0, z))))


def _summed(rows: DataFrame, what: Callable[[np.ndarray, np.ndarray], np.ndarray]) -> np.ndarray:
    """The sum of what(features, y) over rows (features, y last), added up within tasks; 0 without rows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = None
        for batch in batches:
            if batch.num_rows:
                d = np.column_stack([np.asarray(c, float) for c in batch.columns])
                part = what(d[:, :-1], d[:, -1])
                total = part if total is None else total + part
        if total is not None:
            yield pa.RecordBatch.from_arrays([pa.array([total.tolist()], pa.list_(pa.float64()))], names=["sums"])

    return sum((np.array(r["sums"]) for r in rows.mapInArrow(run, "sums array<double>").collect()), np.zeros(1))


def logistic(rows: DataFrame, ridge: float = 1e-3, rounds: int = 30) -> list[float] | None:
    """Weights and, last, the intercept by Newton's steps over all rows (features, y last); None unless both classes are there."""
    first = _summed(rows, lambda x, y: np.r_[len(y), y.sum(), x.sum(0)])
    n = first[0]
    if n == 0 or first[1] in (0, n):
        return None
    mean = first[2:] / n
    spread = np.sqrt(_summed(rows, lambda x, y: ((x - mean) ** 2).sum(0)) / n) + 1e-9
    w = np.zeros(len(mean) + 1)
    for _ in range(rounds):

        def terms(x: np.ndarray, y: np.ndarray, w: np.ndarray = w) -> np.ndarray:
            a = np.hstack([(x - mean) / spread, np.ones((len(x), 1))])
            p = 1 / (1 + np.exp(-np.clip(a @ w, -30, 30)))
            return np.r_[a.T @ (p - y), (a.T @ (a * (p * (1 - p))[:, None])).ravel()]

        sums = _summed(rows, terms)
        pull = sums[: len(w)] + ridge * n / 100 * np.r_[w[:-1], 0]
        curve = sums[len(w) :].reshape(len(w), len(w)) + np.eye(len(w)) * (ridge * n / 100 + 1e-9)
        step = np.linalg.solve(curve, pull)
        w = w - step
        if np.abs(step).max() < 1e-9:
            break
    out = w[:-1] / spread
    return [*map(float, out), float(w[-1] - (out * mean).sum())]


def fold(id: Column) -> Column:
    """crc32 of the id as text modulo 4: 2 is held out, 3 fits the regression, 0 and 1 the counts. Null is 0."""
    return F.coalesce(F.crc32(F.encode(id.cast("string"), "UTF-8")) % 4, F.lit(0)).cast("int")


def learn(docs: DataFrame, labels: DataFrame, id: str = "doc_id", text: str = "text", label: str = "toxic") -> Model:
    """A model from all labelled rows outside the held-out quarter, so that the classes keep their natural share."""
    usable = labels.where(F.col(label).isNotNull() & (fold(F.col(id)) != 2)).groupBy(F.col(id).alias("_id")).agg(F.max(F.col(label).cast("int")).alias("_y"))
    usable = bounded(written(usable, "labels"))  # texts are shuffled only where the labels are too many to send round

    def rows(*folds: int) -> DataFrame:
        own = docs.select(F.col(id).alias("_id"), F.col(text).alias("_text")).where(fold(F.col("_id")).isin(*folds))
        return own.join(usable.where(fold(F.col("_id")).isin(*folds)), "_id").select("_text", "_y")

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found: tuple[Counter, Counter] = (Counter(), Counter())

        def out():
            words = [*{*found[0], *found[1]}]
            if words:
                yield pa.RecordBatch.from_arrays([pa.array(words, pa.string()), pa.array([found[1][w] for w in words], pa.int64()), pa.array([found[0][w] for w in words], pa.int64())], names=["word", "toxic", "ordinary"])
            found[0].clear()
            found[1].clear()

        for batch in batches:
            for t, y in zip(batch.column(0), batch.column(1)):
                found[y.as_py()].update(distinct_words(t.as_py()))
            if len(found[0]) + len(found[1]) > MEMORY:
                yield from out()
        yield from out()

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            toxic, ordinary = Counter(), Counter()
            for w, a, b in zip(*(c.to_pylist() for c in batch.columns)):
                for g in pieces(w):
                    toxic[g] += a
                    ordinary[g] += b
            yield pa.RecordBatch.from_arrays([pa.array([*toxic], pa.string()), pa.array([*toxic.values()], pa.int64()), pa.array([ordinary[g] for g in toxic], pa.int64())], names=["gram", "toxic", "ordinary"])

    sums = [F.sum("toxic").alias("toxic"), F.sum("ordinary").alias("ordinary")]
    words = rows(0, 1).mapInArrow(count, "word string, toxic long, ordinary long").groupBy("word").agg(*sums)
    grams = words.mapInArrow(cut, "gram string, toxic long, ordinary long").groupBy("gram").agg(*sums)
    model = Model(zip(*(c.to_pylist() for c in grams.toArrow().columns)))
    shared = docs.sparkSession.sparkContext.broadcast(model)
    names = [f"f{i}" for i in range(FEATURES)]

    def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = [shared.value.features(t.as_py()) for t in batch.column(0)]
            yield pa.RecordBatch.from_arrays([*(pa.array([r[i] for r in x], pa.float64()) for i in range(FEATURES)), batch.column(1)], names=[*names, "y"])

    seen = rows(3).mapInArrow(measure, ", ".join(f"{c} double" for c in names) + ", y int")
    model.weights = logistic(written(seen, "toxicity"))
    model.known, model.told = {}, {}
    return model


def scored(df: DataFrame, model: Model, text: str = "text", score: str = "score", columns: list[str] | None = None) -> DataFrame:
    """columns of df (all, if not given) and the probability that a text is toxic.

    Edge cases: null and empty texts have no evidence and get the regression's base value; without labels of both
    classes all scores are 0; long texts are read whole; repeated rows score alike; an empty table gives an empty result.
    """
    shared = df.sparkSession.sparkContext.broadcast(model)
    columns = [c for c in (columns or df.columns) if c != score]
    base = df.select(*columns, F.col(text).alias("_pv_text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            values = pa.array([shared.value.score(t.as_py()) for t in batch.column(len(columns))], pa.float64())
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], values], names=[*columns, score])

    kinds = ", ".join(f"`{c}` {df.schema[c].dataType.simpleString()}" for c in columns)
    return base.mapInArrow(run, f"{kinds}, `{score}` double")

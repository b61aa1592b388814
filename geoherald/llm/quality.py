"""Quality: Bradley-Terry ranking on preference pairs.

A document of label 1 is preferred to one of label 0. The score of a document is linear in features of
its text; the weights minimise the logistic loss on feature differences of preference pairs (Newton
steps with a ridge). The cut is the quantile of all training scores at the share of label 0, and the
score handed out is the logistic of the distance to that cut, moved so that the cut lies at
``threshold``.

All labelled rows that may be used are learned from: means, pairs, weights and cut are of the whole table, as sums
over the executors. Scoring covers whole texts.

Results for odd rows: a null or empty text has all features 0 and gets the score of such a text.
Repeated rows score alike. Without training rows of both labels every score is ``threshold``. Only the
named columns are read.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from math import log, log1p

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from geoherald.llm.scratch import store

ENDS = frozenset(".,;:?!\"')»”’…-")
#: Rows of the rarer label in a bucket of pairs, about.
PER_BUCKET = 500
CLOSE = re.compile(r"[.!?…]+(?:\s|$)")
FEATURES = (
    "log_words", "upper", "letters", "digits", "signs", "odd_ends", "bare_signs", "follows_itself",
    "variety", "commonest", "word_length", "sentences", "marks", "repeated_pairs", "lines", "repeated_lines",
)


def features(text: str | None) -> list[float]:
    """The features, each from 0 to about 1 except for logarithms."""
    words = text.split() if text else []
    if not words:
        return [0.0] * len(FEATURES)
    n, chars = len(words), len(text)
    letters = sum(map(str.isalpha, text))
    spaces = sum(map(str.isspace, text))
    digits = sum(map(str.isdigit, text))
    upper = sum(map(str.isupper, text))
    counts = Counter(words)
    pairs = Counter(zip(words, words[1:], strict=False))
    lines = [x for x in text.split("\n") if x.strip()]
    odd = sum(1 for w in words if not w[-1].isalnum() and w[-1] not in ENDS)
    bare = sum(1 for w in words if not any(map(str.isalnum, w)))
    doubled = sum(1 for a, b in zip(words, words[1:], strict=False) if a == b)
    again = sum(c - 1 for c in pairs.values())
    shouted = sum(text.count(c) for c in "!?")
    return [
        log1p(n) / 10,
        upper / max(letters, 1),
        letters / max(chars - spaces, 1),
        digits / max(chars - spaces, 1),
        (chars - spaces - letters - digits) / max(chars - spaces, 1),
        odd / n,
        bare / n,
        doubled / n,
        len(counts) / n,
        max(counts.values()) / n,
        min(letters / n, 30) / 10,
        min(len(CLOSE.findall(text)) / n, 1.0),
        min(shouted / n, 1.0),
        again / n,
        log1p(len(lines)) / 10,
        1 - len(set(lines)) / max(len(lines), 1),
    ]


@dataclass(frozen=True)
class QualityParams:
    ridge: float = 1e-4
    threshold: float = 0.7


@dataclass
class Ranker:
    mean: np.ndarray
    scale: np.ndarray
    weights: np.ndarray
    cut: float
    threshold: float

    @staticmethod
    def widened(x: np.ndarray) -> np.ndarray:
        """Features with their square roots and squares, so that a linear score can saturate."""
        return np.concatenate([x, np.sqrt(np.abs(x)), x * x], axis=1)

    def raw(self, x: np.ndarray) -> np.ndarray:
        return ((self.widened(x) - self.mean) / self.scale) @ self.weights

    def score(self, x: np.ndarray) -> np.ndarray:
        z = self.raw(x) - self.cut + log(self.threshold / (1 - self.threshold))
        return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def fit_bradley_terry(better: np.ndarray, worse: np.ndarray, ridge: float) -> np.ndarray:
    """Weights that minimise log(1 + exp(-(score of better - score of worse))) over the given pairs."""
    d = better - worse
    w = np.zeros(d.shape[1])
    for _ in range(60):
        p = 1 / (1 + np.exp(np.clip(d @ w, -30, 30)))
        grad = -(d * p[:, None]).mean(axis=0) + ridge * w
        hess = (d * (p * (1 - p))[:, None]).T @ d / len(d) + ridge * np.eye(len(w))
        step = np.linalg.solve(hess, grad)
        w -= step
        if np.abs(step).max() < 1e-6:
            break
    return w


def measured(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``key, x``: the features of every document, written once for training and scoring."""
    rows = docs.select(F.col(f"`{key}`").alias("key"), F.col(f"`{text}`").cast("string").alias("text"))

    def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = pa.array([features(t) for t in batch.column("text").to_pylist()], pa.list_(pa.float64()))
            yield pa.RecordBatch.from_arrays([batch.column("key"), x], ["key", "x"])

    return store(rows.mapInArrow(measure, f"key {rows.schema['key'].dataType.simpleString()}, x array<double>"), "features")


def _matrix(column: pa.Array) -> np.ndarray:
    return np.asarray(column.flatten()).reshape(len(column), -1)


def _summed(df: DataFrame, part: Callable[[pa.RecordBatch], np.ndarray]) -> np.ndarray:
    """Sum of what ``part`` makes of all batches; one short row per task comes to the driver."""

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        whole = None
        for batch in batches:
            if batch.num_rows:
                whole = part(batch) if whole is None else whole + part(batch)
        if whole is not None:
            yield pa.RecordBatch.from_arrays([pa.array([whole.tolist()], pa.list_(pa.float64()))], ["s"])

    return np.sum([r.s for r in df.mapInArrow(add, "s array<double>").collect()], axis=0)


def paired(train: DataFrame, n: dict[int, int]) -> DataFrame:
    """``better, worse``: every training row in at least one pair. Rows are dealt by the hash of their key to buckets
    with hundreds of the rarer label; there each row of the more frequent label meets the next one of the other."""
    buckets = max(1, min(n.values()) // PER_BUCKET)
    dealt = train.withColumn("bucket", F.pmod(F.xxhash64(F.lit(1), "key"), F.lit(buckets)))

    def pair(table: pa.Table) -> pa.Table:
        table = table.sort_by([("key", "ascending")]).combine_chunks()
        y = np.asarray(table["label"])
        one, zero = np.flatnonzero(y == 1), np.flatnonzero(y == 0)
        most = max(len(one), len(zero)) if len(one) and len(zero) else 0
        x = table["x"]
        return pa.table({"better": x.take(pa.array(np.resize(one, most))), "worse": x.take(pa.array(np.resize(zero, most)))})

    return dealt.groupBy("bucket").applyInArrow(pair, "better array<double>, worse array<double>")


def fit_on_all(pairs: DataFrame, mean: np.ndarray, scale: np.ndarray, ridge: float) -> np.ndarray:
    """As :func:`fit_bradley_terry`, its sums taken over all pairs by the executors."""
    width = len(mean)
    w = np.zeros(width)
    for _ in range(60):

        def part(batch: pa.RecordBatch, w: np.ndarray = w) -> np.ndarray:
            d = (Ranker.widened(_matrix(batch.column("better"))) - Ranker.widened(_matrix(batch.column("worse")))) / scale
            p = 1 / (1 + np.exp(np.clip(d @ w, -30, 30)))
            return np.concatenate([[len(d)], -(d * p[:, None]).sum(axis=0), ((d * (p * (1 - p))[:, None]).T @ d).ravel()])

        sums = _summed(pairs, part)
        grad = sums[1 : width + 1] / sums[0] + ridge * w
        step = np.linalg.solve(sums[width + 1 :].reshape(width, width) / sums[0] + ridge * np.eye(width), grad)
        w = w - step
        if np.abs(step).max() < 1e-6:
            break
    return w


def kth_smallest(values: DataFrame, n: int, k: int) -> float:
    """The exact value of rank ``k``, from 1, of ``n``: the values near it come to the driver, about 200,000 at most."""
    name, eps = values.columns[0], min(0.005, 50_000 / n)
    low, high = values.approxQuantile(name, [max(0.0, k / n - 2 * eps), min(1.0, k / n + 2 * eps)], eps)
    low, high = low if k / n > 2 * eps else -np.inf, high if k / n < 1 - 2 * eps else np.inf
    below = values.filter(F.col(name) < low).count()
    return sorted(r[0] for r in values.filter(F.col(name).between(low, high)).collect())[k - 1 - below]


def train_ranker(docs: DataFrame, labels: DataFrame, allowed: Column, key: str = "doc_id", text: str = "text", label: str = "quality", params: QualityParams = QualityParams()) -> Ranker:
    return train_measured(measured(docs, key, text), labels, allowed, key, label, params)


def train_measured(docs: DataFrame, labels: DataFrame, allowed: Column, key: str = "doc_id", label: str = "quality", params: QualityParams = QualityParams()) -> Ranker:
    """The ranker of all labelled rows of :func:`measured`."""
    usable = labels.filter(F.col(label).isin(0, 1) & F.col(key).isNotNull() & allowed)
    usable = usable.groupBy(F.col(key).alias("key")).agg(F.max(label).cast("int").alias("label"))
    train = store(docs.join(usable, "key"), "train")
    n = {r.label: r["count"] for r in train.groupBy("label").count().collect()}
    width = 3 * len(FEATURES)
    if len(n) < 2:
        return Ranker(np.zeros(width), np.ones(width), np.zeros(width), 0.0, params.threshold)
    whole = n[0] + n[1]
    mean = _summed(train.select("x"), lambda batch: Ranker.widened(_matrix(batch.column("x"))).sum(axis=0)) / whole
    square = _summed(train.select("x"), lambda batch: ((Ranker.widened(_matrix(batch.column("x"))) - mean) ** 2).sum(axis=0))
    scale = np.maximum(np.sqrt(square / whole), 1e-6)
    ranker = Ranker(mean, scale, fit_on_all(store(paired(train, n), "pairs"), mean, scale, params.ridge), 0.0, params.threshold)

    def rate(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                yield pa.RecordBatch.from_arrays([pa.array(ranker.raw(_matrix(batch.column("x"))))], ["raw"])

    ranker.cut = kth_smallest(train.select("x").mapInArrow(rate, "raw double"), whole, n[0])
    return ranker


def measured_score(ranker: Ranker, x: Column) -> Column:
    """Score of the features of :func:`measured`, as a column."""

    @F.arrow_udf("double")
    def score(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for rows in batches:
            yield pa.array(ranker.score(_matrix(rows)) if len(rows) else [], pa.float64())

    return score(x)


def quality_score(ranker: Ranker, text: Column) -> Column:
    """Score of a text as a column."""

    @F.arrow_udf("double")
    def score(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for texts in batches:
            x = np.array([features(t) for t in texts.to_pylist()]).reshape(-1, len(FEATURES))
            yield pa.array(ranker.score(x), pa.float64())

    return score(text.cast("string"))

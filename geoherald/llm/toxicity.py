"""Toxicity: a weighted lexicon matched by Aho-Corasick on folded text.

Folding lower-cases, undoes compatibility forms, accents and look-alike letters, and reads digits and
signs inside words as the letters they stand for. The lexicon holds whole words and beginnings of
words, weighted by the logarithm of how much more often toxic training documents have them. A word
counts with its heaviest entry; words inside an exception phrase don't count. The sum is divided by
the square root of the number of words and turned into a probability by a one-dimensional logistic
fit on training rows that the lexicon has not seen.

``per_class`` bounds the training rows, ``max_terms`` the lexicon. Scoring covers whole texts.

Results for odd rows: a null or empty text scores as a text without hits. Repeated rows score alike.
Without training rows of both labels every score is 0. Only the named columns are read.
"""

from __future__ import annotations

import re
import unicodedata
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field
from math import exp, log, log1p

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from geoherald.llm.labelled import class_weights, sample_labelled
from geoherald.llm.scratch import store

# Letters of other scripts that look like Latin ones.
HOMOGLYPHS = str.maketrans(
    "аеорсухіјѕԁɡһӏкмтвнαοερνικτυχωаꞵɑ",
    "aeopcyxijsdghlkmtbhaoepviktuxwaba",
)
# Signs and digits read as letters inside a word.
SUBSTITUTES = str.maketrans({"0": "o", "1": "i", "3": "e", "4": "a", "5": "s", "7": "t", "8": "b", "9": "g", "@": "a", "$": "s", "!": "i", "|": "l"})
TOKEN = re.compile(r"[^\W_]+(?:[@$!|]+[^\W_]+)*")
MARKS = re.compile(r"[̀-ͯ]")
#: In these the words carry no insult.
EXCEPTIONS = ("trash can", "trash bag", "trash bin", "class clown", "clown fish", "circus clown", "sore loser board")


def fold(text: str) -> list[str]:
    """Words of a text in folded form."""
    if not text.isascii():
        text = MARKS.sub("", unicodedata.normalize("NFKD", text.lower())).translate(HOMOGLYPHS)
    out = []
    for word in TOKEN.findall(text.lower()):
        if not word.isalpha() and 5 * sum(map(str.isalpha, word)) >= 2 * len(word):
            word = word.translate(SUBSTITUTES)
        out.append(word)
    return out


@dataclass(frozen=True)
class ToxicParams:
    per_class: int = 8000
    max_terms: int = 5000
    least_docs: int = 5
    least_weight: float = 2.5
    shortest: int = 4
    longest: int = 8
    threshold: float = 0.5


@dataclass
class Lexicon:
    """Entries are ``word$`` for whole words and ``begin`` for beginnings; weights as trained."""

    weights: dict[str, float]
    exceptions: tuple[str, ...] = EXCEPTIONS
    slope: float = 0.0
    base: float = -20.0
    machine: object = field(default=None, repr=False)

    def __getstate__(self) -> dict:
        return self.__dict__ | {"machine": None}

    def build(self) -> "Lexicon":
        self.machine = ahocorasick.Automaton()
        for term, weight in self.weights.items():
            pattern = f" {term[:-1]} " if term.endswith("$") else f" {term}"
            self.machine.add_word(pattern, (len(pattern), weight))
        for phrase in self.exceptions:
            pattern = f" {' '.join(fold(phrase))} "
            self.machine.add_word(pattern, (len(pattern), None))
        self.machine.make_automaton()
        return self

    def hits(self, words: list[str]) -> dict[int, float]:
        """Place in the folded text to weight, for each word that counts."""
        if not len(self.machine):
            return {}
        found: dict[int, float] = {}
        excused: list[tuple[int, int]] = []
        for end, (length, weight) in self.machine.iter(f" {' '.join(words)} "):
            start = end - length + 1
            if weight is None:
                excused.append((start, end))
            elif weight > found.get(start, 0.0):
                found[start] = weight
        return {s: w for s, w in found.items() if not any(a <= s < b for a, b in excused)} if excused else found

    def density(self, text: str | None) -> float:
        words = fold(text) if text else []
        return sum(self.hits(words).values()) / len(words) ** 0.5 if words else 0.0

    def score(self, text: str | None) -> float:
        z = self.base + self.slope * log1p(10 * self.density(text))
        return 1 / (1 + exp(-max(-30.0, min(30.0, z))))


def _counted(train: DataFrame, params: ToxicParams) -> DataFrame:
    """``term, toxic, clean``: training documents of either label that have the term."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts: tuple[Counter, Counter] = (Counter(), Counter())
        for batch in batches:
            for text, label in zip(batch.column("text").to_pylist(), batch.column("label").to_pylist(), strict=True):
                terms = set()
                for word in set(fold(text or "")):
                    terms.add(f"{word}$")
                    terms.update(word[:k] for k in range(params.shortest, min(len(word), params.longest + 1)))
                counts[label].update(terms)
        # a term of few toxic documents here may still be of many elsewhere, so all of those go out;
        # terms without any are of no use
        terms = list(counts[1])
        yield pa.RecordBatch.from_arrays(
            [pa.array(terms, pa.string()), pa.array([counts[1][t] for t in terms], pa.int64()), pa.array([0] * len(terms), pa.int64())],
            ["term", "toxic", "clean"],
        )
        terms = list(counts[0])
        for at in range(0, len(terms), 100_000):
            part = terms[at : at + 100_000]
            yield pa.RecordBatch.from_arrays([pa.array(part, pa.string()), pa.array([0] * len(part), pa.int64()), pa.array([counts[0][t] for t in part], pa.int64())], ["term", "toxic", "clean"])

    return train.mapInArrow(run, "term string, toxic long, clean long").groupBy("term").agg(F.sum("toxic").alias("toxic"), F.sum("clean").alias("clean"))


def logistic_1d(x: np.ndarray, y: np.ndarray, ridge: float = 1e-3) -> tuple[float, float]:
    """Slope and base of a logistic fit, by Newton steps."""
    a = np.column_stack([x, np.ones_like(x)])
    w = np.zeros(2)
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(a @ w, -30, 30)))
        grad = a.T @ (p - y) / len(y) + ridge * w
        hess = (a * (p * (1 - p))[:, None]).T @ a / len(y) + ridge * np.eye(2)
        step = np.linalg.solve(hess, grad)
        w -= step
        if np.abs(step).max() < 1e-8:
            break
    return float(w[0]), float(w[1])


def train_lexicon(docs: DataFrame, labels: DataFrame, allowed: Column, key: str = "doc_id", text: str = "text", label: str = "toxic", params: ToxicParams = ToxicParams()) -> Lexicon:
    """Learn weights on two thirds of the sample and the logistic fit on the other third."""
    train = store(sample_labelled(docs, labels, label, allowed, params.per_class, key, text), "toxic-train")
    fold_of = F.crc32(F.concat(F.lit("fit:"), F.col("key").cast("string")).cast("binary")) % 3
    learn, check = train.filter(fold_of != 0), train.filter(fold_of == 0)
    sizes = {r["label"]: r["n"] for r in learn.groupBy("label").agg(F.count(F.lit(1)).alias("n")).collect()}
    if len(sizes) < 2:
        return Lexicon({})
    weight = F.log((F.col("toxic") + 0.5) / (sizes[1] + 1)) - F.log((F.col("clean") + 0.5) / (sizes[0] + 1))
    best = _counted(learn, params).filter(F.col("toxic") >= params.least_docs).withColumn("weight", weight).filter(F.col("weight") >= params.least_weight)
    rows = best.orderBy(F.desc("weight"), F.desc("toxic"), "term").limit(params.max_terms).collect()
    lexicon = Lexicon({r["term"]: r["weight"] for r in rows})

    def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        built = lexicon.build()
        for batch in batches:
            x = [log1p(10 * built.density(t)) for t in batch.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array(x, pa.float64()), batch.column("label")], ["x", "label"])

    seen = check.select("text", "label").mapInArrow(measure, "x double, label int").toPandas()
    if seen["label"].nunique() == 2:
        # the sample can hold the labels in other shares than the table
        weights = class_weights(seen["label"].value_counts().to_dict(), labels, label, allowed, key)
        lexicon.slope, lexicon.base = logistic_1d(seen["x"].to_numpy(), seen["label"].to_numpy(float))
        lexicon.base += log(weights[1] / weights[0])
    return lexicon


def toxicity_score(lexicon: Lexicon, text: Column) -> Column:
    """Score of a text as a column."""

    @F.arrow_udf("double")
    def score(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        built = lexicon.build()
        for texts in batches:
            yield pa.array([built.score(t) for t in texts.to_pylist()], pa.float64())

    return score(text.cast("string"))

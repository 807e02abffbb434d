"""Toxicity by a chain of linear classifiers.

Categories are predicted in order; the log-odds of the earlier ones are inputs of the later. While the chain
is trained, those inputs are out-of-fold predictions, so a later model sees earlier
outputs as good as they will be on new text. The last category is ``toxic``.

The models are fitted on a bounded sample of the labelled rows (``Settings.sample_rows``) and applied
to every whole text. Null and empty texts have no features and get the intercepts' probabilities.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import SPACE, Cut

#: Seed words that label the sub-categories of rows labelled toxic.
CATEGORIES = {
    "insult": ("idiot", "moron", "stupid", "clown", "loser", "fool", "dumb"),
    "contempt": ("trash", "scum", "worthless", "garbage", "vermin", "filth"),
    "disgust": ("disgusting", "pathetic", "vile", "gross", "repulsive"),
}


@dataclass(frozen=True)
class Settings:
    sample_rows: int = 6_000
    vocabulary: int = 1000
    folds: int = 3
    ridge: float = 0.5
    threshold: float = 0.5


_STRIP = ".,!?;:\"'()[]{}*$%&#|<>-"


#: Lengths of the word beginnings that are features beside whole words.
PREFIXES = (4, 5, 7)


def tokens(text: str | None) -> set[str]:
    return {w.strip(_STRIP) for w in (text or "").lower().split()}


def traits(words: set[str]) -> Counter:
    """The words, and how many of them share a beginning (marked with a circumflex), as inflected and compounded forms do."""
    return Counter(words) + Counter("^" + w[:k] for w in words for k in PREFIXES if len(w) > k)


def levels(text: str | None, at: dict[str, int]) -> dict[int, float]:
    """Feature number -> logarithm of one plus its count, of the features that a text has."""
    found = traits(tokens(text))
    return {at[w]: math.log2(1 + found[w]) for w in found.keys() & at.keys()}


def _fit(x: np.ndarray, y: np.ndarray, ridge: float) -> np.ndarray:
    """Logistic regression by Newton steps; the first weight is the intercept, which is not shrunk."""
    x1 = np.hstack([np.ones((len(x), 1)), x])
    w, shrink = np.zeros(x1.shape[1]), np.full(x1.shape[1], ridge)
    shrink[0] = 1e-6
    for _ in range(12):
        p = 1 / (1 + np.exp(-np.clip(x1 @ w, -30, 30)))
        hess = (x1 * (p * (1 - p))[:, None]).T @ x1 + np.diag(shrink)
        step = np.linalg.solve(hess, x1.T @ (p - y) + shrink * w)
        w -= step
        if np.abs(step).max() < 1e-3:
            break
    return w


def _log_odds(x: np.ndarray, w: np.ndarray) -> np.ndarray:
    return np.clip(w[0] + x @ w[1:], -30, 30)


@dataclass
class Chain:
    words: list[str]
    names: list[str]
    weights: list[np.ndarray]

    def predict(self, x: np.ndarray) -> np.ndarray:
        """(rows, categories) probabilities of word features."""
        for w in self.weights:
            x = np.hstack([x, _log_odds(x, w)[:, None]])
        return 1 / (1 + np.exp(-x[:, len(self.words) :]))

    def encode(self, texts) -> np.ndarray:
        at = {w: k for k, w in enumerate(self.words)}
        x = np.zeros((len(texts), len(at)))
        for i, t in enumerate(texts):
            hits = levels(t, at)
            x[i, list(hits)] = list(hits.values())
        return x


def fit_chain(x: np.ndarray, labels: np.ndarray, folds: np.ndarray, names: list[str], words: list[str], ridge: float) -> Chain:
    weights, z = [], x
    for k in range(len(names)):
        y = labels[:, k]
        weights.append(_fit(z, y, ridge))
        outside = np.empty(len(y))
        for f in np.unique(folds):
            held = folds == f
            w = _fit(z[~held], y[~held], ridge) if (~held).any() else weights[-1]
            outside[held] = _log_odds(z[held], w)
        z = np.hstack([z, outside[:, None]])
    return Chain(words, names, weights)


def _beginning(k: int):
    return lambda w: F.when(F.length(w) > k, F.concat(F.lit("^"), F.substring(w, 1, k)))


def train(docs: DataFrame, labels: DataFrame, s: Settings = Settings()) -> Chain:
    """Fit the chain on the labelled documents with the smallest identifier hashes, at most ``sample_rows``."""
    cut = Cut(docs.sparkSession)
    known = labels.where("toxic is not null and doc_id is not null").groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max("toxic").cast("int").alias("toxic"))
    chosen = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(s.sample_rows)  # a bounded sample by parameter
    text = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    sample = cut(text.join(F.broadcast(chosen), "doc_id"))
    bare = F.regexp_replace(F.lower("text"), r"[.,!?;:\"'()\[\]{}*$%&#|<>-]+(?=[ \t\n\x0B\f\r]|$)|(?<=[ \t\n\x0B\f\r]|^)[.,!?;:\"'()\[\]{}*$%&#|<>-]+", "")
    whole = sample.select("toxic", F.filter(F.array_distinct(F.split(bare, SPACE)), lambda w: w != "").alias("w"))
    begins = [F.transform("w", _beginning(k)) for k in PREFIXES]
    seen = whole.select("toxic", F.explode(F.array_distinct(F.array_compact(F.concat("w", *begins)))).alias("word"))
    n1, n0 = (sample.agg(F.sum("toxic"), F.sum(1 - F.col("toxic"))).first())
    n1, n0 = n1 or 0, n0 or 0
    counts = seen.groupBy("word").agg(F.sum("toxic").alias("a"), F.sum(1 - F.col("toxic")).alias("b")).where("a + b >= 3")
    a, b = (F.col("a") + 0.5) / (n1 + 1.0), (F.col("b") + 0.5) / (n0 + 1.0)
    words = [r.word for r in counts.orderBy(F.desc(F.abs(F.sqrt(a) - F.sqrt(b))), "word").limit(s.vocabulary).select("word").collect()]
    chain = Chain(words, [*CATEGORIES, "toxic"], [])
    seeds = {k: set(v) for k, v in CATEGORIES.items()}

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at = {w: k for k, w in enumerate(words)}
        for batch in batches:
            texts = [t.as_py() for t in batch.column(1)]
            sets = [tokens(t) for t in texts]
            found = [levels(t, at) for t in texts]
            hits = pa.array([list(f) for f in found], pa.list_(pa.int32()))
            values = pa.array([list(f.values()) for f in found], pa.list_(pa.float64()))
            kinds = pa.array([[int(bool(t & v)) for v in seeds.values()] for t in sets], pa.list_(pa.int32()))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), hits, values, kinds], ["doc_id", "toxic", "hits", "values", "kinds"])

    rows = sample.select("doc_id", "text", "toxic").mapInArrow(encode, "doc_id long, toxic int, hits array<int>, values array<double>, kinds array<int>").orderBy("doc_id").collect()
    x = np.zeros((len(rows), len(words)))
    for i, r in enumerate(rows):
        x[i, r.hits] = r["values"]
    y = np.array([[*(k * r.toxic for k in r.kinds), r.toxic] for r in rows], float).reshape(len(rows), len(chain.names))
    folds = np.arange(len(rows)) % s.folds
    return fit_chain(x, y, folds, chain.names, words, s.ridge)


def classify(docs: DataFrame, labels: DataFrame, s: Settings = Settings()) -> DataFrame:
    """doc_id, a probability per category (p_<name>) and ``toxic`` (boolean), one row per row of ``docs``."""
    chain = train(docs, labels, s)
    names = [f"p_{n}" for n in chain.names]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for k in range(0, b.num_rows, 512):
                part = b.slice(k, 512)
                p = chain.predict(chain.encode([t.as_py() for t in part.column(1)])) if part.num_rows else np.zeros((0, len(names)))
                yield pa.RecordBatch.from_arrays(
                    [part.column(0), *(pa.array(np.round(p[:, j], 6)) for j in range(len(names))), pa.array(p[:, -1] >= s.threshold)], ["doc_id", *names, "toxic"]
                )

    schema = "doc_id long, " + ", ".join(f"{n} double" for n in names) + ", toxic boolean"
    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, schema)

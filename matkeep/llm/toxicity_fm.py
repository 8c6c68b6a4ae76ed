"""Toxicity: a factorization machine over hashed terms.

Besides a weight for each term the model has a short vector for each, whose inner products weigh pairs of terms: an
insult beside the mention of a group can count for more than the two apart. Terms are a text's distinct words and the
words' first letters, hashed; of the hash buckets those most associated with the label are kept. A term counts once
however often or in how long a text it stands, so a few words mark a long document.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .labelled import SAMPLE_TASKS, fold, labelled_sample
from .lookup import Lookup
from .shared import cut, list_column

FOLDS, HELD_OUT = 5, 0
#: Hash space of terms.
BUCKETS = 1 << 20
#: Buckets the model keeps, at most.
KEPT = 4096
#: Labelled rows of each class that are used for fitting, at most.
PER_CLASS = 6000
#: A bucket is kept if so many rows of the sample have it, and its presence depends on the label so much (chi-square).
LEAST_ROWS, LEAST_CHI = 4, 12.0
#: Lengths of the word beginnings that count as terms besides the word.
PREFIXES = (4, 5, 6)

SCORES = "doc_id long, held_out boolean, score double, predicted int"

words_of = re.compile(r"[^\W\d_]+").findall


def word_terms(word: str) -> list[int]:
    """Buckets of a lower-cased word and of its beginnings."""
    parts = [f"w{word}", *(f"{n}{word[:n]}" for n in PREFIXES if len(word) >= n)]
    return [zlib.crc32(p.encode("utf-8", "surrogatepass")) % BUCKETS for p in parts]


@dataclass(frozen=True)
class FactorizationMachine:
    """bias + sum of weights + sum over pairs of inner products, as the log-odds of label 1."""

    buckets: np.ndarray  # sorted
    bias: float
    weights: np.ndarray
    factors: np.ndarray

    def log_odds(self, features: np.ndarray) -> float:
        """``features``: distinct positions in ``buckets``."""
        v = self.factors[features]
        pairs = 0.5 * float((v.sum(0) ** 2 - (v**2).sum(0)).sum())
        return self.bias + float(self.weights[features].sum()) + pairs

    def score(self, features: np.ndarray) -> float:
        return float(1 / (1 + np.exp(-np.clip(self.log_odds(features), -40, 40))))


def associated_buckets(rows: list[np.ndarray], labels: np.ndarray, kept: int, least_rows: int = LEAST_ROWS, least_chi: float = LEAST_CHI) -> np.ndarray:
    """Buckets whose presence depends most on the label, by chi-square."""
    n, positive = len(rows), int(labels.sum())
    df = lambda chosen: np.bincount(np.concatenate(chosen), minlength=BUCKETS) if chosen else np.zeros(BUCKETS, dtype=np.int64)
    a = df([r for r, y in zip(rows, labels, strict=True) if y]).astype(float)
    b = df([r for r, y in zip(rows, labels, strict=True) if not y]).astype(float)
    seen, negative = a + b, n - positive
    below = seen * (n - seen) * positive * negative
    chi = np.where((seen >= least_rows) & (below > 0), n * (a * (negative - b) - b * (positive - a)) ** 2 / np.maximum(below, 1), 0)
    best = np.argsort(-chi, kind="stable")[:kept]
    return np.sort(best[chi[best] >= least_chi])


def fit(rows: list[np.ndarray], labels: np.ndarray, sizes: dict[int, int], **settings) -> FactorizationMachine:
    """Choose buckets and train on rows of hashed terms."""
    labels = np.asarray(labels, dtype=float)
    buckets = associated_buckets(rows, labels, KEPT)
    return train(buckets, [present(buckets, r) for r in rows], labels, sizes, **settings)


def train(buckets: np.ndarray, features: list[np.ndarray], labels: np.ndarray, sizes: dict[int, int], rank: int = 4, epochs: int = 30, rate: float = 0.05, decay: float = 1e-4, seed: int = 7) -> FactorizationMachine:
    """Adam on the log loss in small batches. The bias is moved to the classes' true shares afterwards."""
    labels = np.asarray(labels, dtype=float)
    positive, negative = labels.sum(), len(labels) - labels.sum()
    if not positive or not negative:
        return FactorizationMachine(np.zeros(0, dtype=np.int64), 20.0 if positive else -20.0, np.zeros(0), np.zeros((0, rank)))
    n, rng = len(buckets), np.random.default_rng(seed)
    if n == 0:
        return FactorizationMachine(buckets, float(np.log(positive / negative)), np.zeros(0), np.zeros((0, rank)))
    theta = np.concatenate([np.zeros((n, 1)), rng.normal(0, 0.01, (n, rank))], axis=1)
    bias, m, s = float(np.log(positive / negative)), np.zeros_like(theta), np.zeros_like(theta)
    m0 = s0 = 0.0
    step = 0
    for _ in range(epochs):
        for at in np.array_split(rng.permutation(len(features)), max(1, len(features) // 256)):
            step += 1
            flat = np.concatenate([features[i] for i in at])
            row = np.repeat(np.arange(len(at)), [len(features[i]) for i in at])
            part = theta[flat]
            v = part[:, 1:]
            sums = np.zeros((len(at), rank))
            np.add.at(sums, row, v)
            squares = np.zeros((len(at), rank))
            np.add.at(squares, row, v * v)
            odds = bias + np.bincount(row, part[:, 0], len(at)) + 0.5 * (sums**2 - squares).sum(1)
            error = (1 / (1 + np.exp(-np.clip(odds, -40, 40))) - labels[at]) / len(at)
            grad = decay * theta
            each = np.concatenate([np.ones((len(flat), 1)), sums[row] - v], axis=1) * error[row, None]
            for k in range(rank + 1):
                grad[:, k] += np.bincount(flat, each[:, k], n)
            g0 = error.sum()
            m, s = 0.9 * m + 0.1 * grad, 0.999 * s + 0.001 * grad**2
            m0, s0 = 0.9 * m0 + 0.1 * g0, 0.999 * s0 + 0.001 * g0**2
            u, w = 1 - 0.9**step, 1 - 0.999**step
            theta = theta - rate * (m / u) / (np.sqrt(s / w) + 1e-8)
            bias -= rate * (m0 / u) / (np.sqrt(s0 / w) + 1e-8)
    shares = np.log(max(1, sizes.get(1, 0)) / max(1, sizes.get(0, 0))) - np.log(positive / negative)
    return FactorizationMachine(buckets, float(bias + shares), theta[:, 0], theta[:, 1:])


def present(buckets: np.ndarray, terms: np.ndarray) -> np.ndarray:
    """Positions in ``buckets`` of the terms that are there."""
    at = np.searchsorted(buckets, terms)
    at[at == len(buckets)] = 0
    return np.unique(at[buckets[at] == terms]) if len(buckets) else np.zeros(0, dtype=np.int64)


def fit_on(docs: DataFrame, labels: DataFrame, per_class: int = PER_CLASS) -> FactorizationMachine:
    """Fit on the bounded sample. Terms are counted where they are; the driver gets the buckets kept and, for each sampled row, which it has."""
    spark = docs.sparkSession
    sample, sizes = labelled_sample(docs, labels, "toxic", FOLDS, HELD_OUT, per_class)

    def hashed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = Lookup(word_terms)
        for batch in batches:
            for one in range(batch.num_rows):  # row by row: the terms of a text take more room than the text
                row = batch.slice(one, 1)
                terms = np.unique(known.gather(known.ids(words_of(row.column(1)[0].as_py().lower())))).astype(np.int32)
                yield pa.RecordBatch.from_arrays([row.column(0), row.column(2), list_column([terms], pa.int32())], names=["doc_id", "label", "terms"])

    dealt = sample.select("doc_id", "text", "label").repartition(SAMPLE_TASKS, "doc_id")
    rows = cut(dealt.mapInArrow(hashed, "doc_id long, label int, terms array<int>"), "toxicity-sample")
    n, positive = rows.agg(F.count(F.lit(1)), F.coalesce(F.sum("label"), F.lit(0))).first()
    have = rows.select("label", F.explode("terms").alias("term")).groupBy("term").agg(F.count(F.lit(1)).cast("double").alias("seen"), F.sum("label").cast("double").alias("a"))
    b, seen, negative = F.col("seen") - F.col("a"), F.col("seen"), n - positive
    below = seen * (n - seen) * float(positive) * float(negative)
    apart = F.col("a") * (negative - b) - b * (positive - F.col("a"))
    chi = F.when((seen >= LEAST_ROWS) & (below > 0), float(n) * apart * apart / below).otherwise(0.0)
    best = have.select("term", chi.alias("chi")).where(F.col("chi") >= LEAST_CHI).orderBy(F.desc("chi"), "term").limit(KEPT)
    buckets = np.sort(np.array(best.select("term").toArrow()["term"].to_pylist(), dtype=np.int64))
    sent = spark.sparkContext.broadcast(buckets)

    def places(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [present(sent.value, terms.values.to_numpy(zero_copy_only=False).astype(np.int64)).astype(np.int32).tobytes() for terms in batch.column(2)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(found, pa.binary())], names=["doc_id", "label", "places"])

    found = rows.mapInArrow(places, "doc_id long, label int, places binary").toArrow()
    got = sorted(zip(found["doc_id"].to_pylist(), found["places"].to_pylist(), found["label"].to_pylist(), strict=True))
    return train(buckets, [np.frombuffer(p, dtype=np.int32).astype(np.int64) for _, p, _ in got], np.array([y for _, _, y in got]), sizes)


def score_documents(spark: SparkSession, docs: DataFrame, model: FactorizationMachine) -> DataFrame:
    """doc_id, held_out, score and predicted (score of 0.5 or more) of every row, from its whole text alone.

    A null or empty text has no terms and gets the score of the bias. Repeated rows get equal scores; a null doc_id is
    carried, its fold that of an empty id. Columns other than doc_id and text are not read. The model is a few hundred
    kilobytes whatever the input.
    """
    sent = spark.sparkContext.broadcast(model)

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        machine: FactorizationMachine = sent.value
        place = {int(b): i for i, b in enumerate(machine.buckets)}
        known = Lookup(lambda w: [place[t] for t in word_terms(w) if t in place])
        for batch in batches:
            scores = []
            for text in batch.column(1):
                found = known.gather(known.ids(words_of((text.as_py() or "").lower())))
                scores.append(machine.score(np.unique(found).astype(np.int64)))
            predicted = pa.array([int(x >= 0.5) for x in scores], pa.int32())
            yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), batch.column(2), pa.array(scores, pa.float64()), predicted], names=["doc_id", "held_out", "score", "predicted"])

    held = (fold(docs["doc_id"], FOLDS) == HELD_OUT).alias("held_out")
    return docs.select("doc_id", "text", held).mapInArrow(score, SCORES)

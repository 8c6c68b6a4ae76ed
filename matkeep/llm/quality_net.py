"""Quality classifier: random-indexing word vectors, pooled per document, into a small calibrated network.

Every unit (a lower-cased word, or a word's shape) has a sparse random index vector derived from its hash; a word's
vector is the sum of the index vectors around it over the fitting sample. A word is its own vector beside that of its
shape, so words never seen still say something. A document is the mean of its words' vectors, the mean of the products
of neighbours (which sees words that follow themselves), and two statistics. A two-layer network in NumPy gives log-odds,
and a temperature fitted on rows kept apart makes them probabilities.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .labelled import SAMPLE_TASKS, fold, labelled_sample
from .shared import cut

FOLDS, HELD_OUT = 4, 2
#: Probability from which a document is kept.
THRESHOLD = 0.7
#: Labelled rows of each class that are used for fitting, at most.
PER_CLASS = 3000
#: Length of a vector, and signs in each index vector.
DIMS, SIGNS = 24, 4
#: Rows of the table of learned vectors; units share rows by hash.
ROWS = 1 << 15
#: Neighbours on each side that count as context.
CONTEXT = 2
#: Distinct words whose vectors are kept before the lookup is begun anew.
WORDS_KEPT = 200_000

SCORES = "doc_id long, held_out boolean, score double, predicted int"


def shape(word: str) -> str:
    """Upper, lower, digit and other characters, runs shortened to two."""
    kinds = "".join("X" if c.isupper() else "x" if c.isalpha() else "9" if c.isdigit() else c for c in word)
    return re.sub(r"(.)\1\1+", r"\1\1", kinds)


def unit_hashes(word: str) -> tuple[int, int]:
    return tuple(zlib.crc32(u.encode("utf-8", "surrogatepass")) for u in (f"w{word.lower()}", f"s{shape(word)}"))


def index_vectors(hashes: np.ndarray) -> np.ndarray:
    """The sparse random vector of each hash, as dense rows."""
    out = np.zeros((len(hashes), DIMS), dtype=np.float32)
    h = hashes.astype(np.uint64)
    for i in range(SIGNS):
        with np.errstate(over="ignore"):
            h = (h + np.uint64(0x9E3779B97F4A7C15)) * np.uint64(0xBF58476D1CE4E5B9)
            h ^= h >> np.uint64(29)
        np.add.at(out, (np.arange(len(h)), ((h >> np.uint64(8)) % np.uint64(DIMS)).astype(np.int64)), np.where(h & np.uint64(1), 1.0, -1.0))
    return out


#: Words of a text whose contexts are summed at a time.
STEP = 1 << 16


def context_sums(texts: Iterable[str]) -> np.ndarray:
    """Random indexing: to each unit's row the index vectors of the words around it are added. The sums are whole numbers."""
    known: dict[str, int] = {}
    hashes, index = np.zeros((0, 2), dtype=np.int64), np.zeros((0, DIMS), dtype=np.float32)
    table = np.zeros((ROWS, DIMS), dtype=np.float64)
    for text in texts:
        words = text.split()
        new = list(dict.fromkeys(w for w in words if w not in known))
        if new:
            known.update(zip(new, range(len(known), len(known) + len(new)), strict=True))
            more = np.array([unit_hashes(w) for w in new], dtype=np.int64)
            hashes, index = np.concatenate([hashes, more]), np.concatenate([index, index_vectors(more[:, 0]) + index_vectors(more[:, 1])])
        ids = np.fromiter(map(known.__getitem__, words), dtype=np.int64, count=len(words))
        for start in range(0, len(ids), STEP):
            end = min(len(ids), start + STEP)
            around = np.zeros((end - start, DIMS), dtype=np.float64)
            for d in range(1, CONTEXT + 1):
                before, after = ids[max(0, start - d) : end - d] if end > d else ids[:0], ids[start + d : end + d]
                around[end - start - len(before) :] += index[before]
                around[: len(after)] += index[after]
            for unit in (0, 1):
                np.add.at(table, hashes[ids[start:end], unit] % ROWS, around)
    return table


def unit_rows(table: np.ndarray) -> np.ndarray:
    """Rows of length 1."""
    return (table / np.maximum(np.linalg.norm(table, axis=1, keepdims=True), 1e-9)).astype(np.float32)


class Pooler:
    """Turns a text into the network's input."""

    def __init__(self, table: np.ndarray):
        self.table = table
        self.clear()

    def clear(self) -> None:
        self.known: dict[str, int] = {}
        self.vectors = np.zeros((1024, 2 * DIMS), dtype=np.float32)

    def pooled(self, text: str) -> np.ndarray:
        words = text.split()
        out = np.zeros(4 * DIMS + 3, dtype=np.float32)
        if not words:
            out[-1] = 1.0
            return out
        if len(self.known) > WORDS_KEPT:
            self.clear()
        known = self.known
        new = list(set(words).difference(known))
        if new:
            at = len(known)
            while at + len(new) > len(self.vectors):
                self.vectors = np.concatenate([self.vectors, np.zeros_like(self.vectors)])
            hashes = np.array([unit_hashes(w) for w in new], dtype=np.int64)
            self.vectors[at : at + len(new), :DIMS] = self.table[hashes[:, 0] % ROWS]
            self.vectors[at : at + len(new), DIMS:] = self.table[hashes[:, 1] % ROWS]
            known.update(zip(new, range(at, at + len(new)), strict=True))
        ids = np.fromiter(map(known.__getitem__, words), dtype=np.int64, count=len(words))
        n = len(ids)
        distinct, counts = np.unique(ids, return_counts=True)
        out[: 2 * DIMS] = (counts @ self.vectors[distinct]) / n
        if n > 1:  # in steps, so that a very long text needs little room
            total = np.zeros(2 * DIMS)
            for start in range(0, n - 1, 1 << 16):
                part = self.vectors[ids[start : start + (1 << 16) + 1]]
                total += (part[:-1] * part[1:]).sum(0)
            out[2 * DIMS : 4 * DIMS] = total / (n - 1)
        out[-3] = np.log1p(n) / 5
        out[-2] = len(distinct) / n
        return out


@dataclass(frozen=True)
class QualityNet:
    table: np.ndarray
    mean: np.ndarray
    scale: np.ndarray
    w1: np.ndarray
    b1: np.ndarray
    w2: np.ndarray
    b2: float
    temperature: float

    def log_odds(self, x: np.ndarray) -> np.ndarray:
        return np.tanh((x - self.mean) / self.scale @ self.w1 + self.b1) @ self.w2 + self.b2

    def probability(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.log_odds(x) / self.temperature, -40, 40)))


def temperature_of(odds: np.ndarray, labels: np.ndarray, weights: np.ndarray) -> float:
    """The divisor of log-odds with the least log loss, from a fixed grid."""
    grid = np.geomspace(0.25, 8, 61)
    loss = [float((weights * np.logaddexp(0, np.where(labels > 0, -1, 1) * odds / t)).sum()) for t in grid]
    return float(grid[int(np.argmin(loss))])


def fit(table: np.ndarray, x: np.ndarray, labels: np.ndarray, sizes: dict[int, int], hidden: int = 24, epochs: int = 60, rate: float = 0.01, decay: float = 1e-4, seed: int = 11) -> QualityNet:
    """Fit the network on pooled texts; every fifth row is kept apart for the temperature.

    Rows weigh so that the classes have their true shares. With one class only, that class gets every document.
    """
    labels = np.asarray(labels, dtype=float)
    width = 4 * DIMS + 3
    x = np.asarray(x, dtype=np.float64).reshape(-1, width)
    rng = np.random.default_rng(seed)
    w1, b1 = rng.normal(0, 1 / np.sqrt(width), (width, hidden)), np.zeros(hidden)
    w2, b2 = np.zeros(hidden), 0.0
    positive = int(labels.sum())
    if not positive or positive == len(labels):
        return QualityNet(table, np.zeros(width), np.ones(width), w1, b1, w2, 20.0 if positive else -20.0 if len(labels) else 0.0, 1.0)
    share = {c: sizes.get(c, 0) / max(1, sum(sizes.values())) for c in (0, 1)}
    weights = np.where(labels > 0, share[1] / positive, share[0] / (len(labels) - positive))
    mean, scale = x.mean(0), x.std(0) + 1e-3
    z = (x - mean) / scale
    apart = np.arange(len(z)) % 5 == 4 if len(z) >= 50 else np.zeros(len(z), dtype=bool)
    own = np.flatnonzero(~apart)
    weights = weights / weights[own].mean()
    state = [w1, b1, w2, np.array(b2)]
    m, s = [np.zeros_like(p) for p in state], [np.zeros_like(p) for p in state]
    step = 0
    for _ in range(epochs):
        for at in np.array_split(rng.permutation(own), max(1, len(own) // 128)):
            step += 1
            w1, b1, w2, b2 = state
            h = np.tanh(z[at] @ w1 + b1)
            odds = h @ w2 + b2
            error = weights[at] * (1 / (1 + np.exp(-np.clip(odds, -40, 40))) - labels[at]) / len(at)
            back = np.outer(error, w2) * (1 - h**2)
            grads = [z[at].T @ back + decay * w1, back.sum(0), h.T @ error + decay * w2, error.sum()]
            for i, g in enumerate(grads):
                m[i], s[i] = 0.9 * m[i] + 0.1 * g, 0.999 * s[i] + 0.001 * g * g
                state[i] = state[i] - rate * (m[i] / (1 - 0.9**step)) / (np.sqrt(s[i] / (1 - 0.999**step)) + 1e-8)
    w1, b1, w2, b2 = state
    net = QualityNet(table, mean, scale, w1, b1, w2, float(b2), 1.0)
    if apart.any():
        net = QualityNet(table, mean, scale, w1, b1, w2, float(b2), temperature_of(net.log_odds(x[apart]), labels[apart], weights[apart]))
    return net


def fit_on(docs: DataFrame, labels: DataFrame, per_class: int = PER_CLASS) -> QualityNet:
    """Fit on the bounded sample.

    Texts stay with the executors: the driver gets the summed contexts (ROWS vectors at most) and a pooled vector for each
    sampled row, and trains the network on these.
    """
    spark = docs.sparkSession
    sample, sizes = labelled_sample(docs, labels, "quality", FOLDS, HELD_OUT, per_class)
    sample = cut(sample.select("doc_id", "text", "label").repartition(SAMPLE_TASKS, "doc_id"), "quality-sample")

    def contexts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums = context_sums(text.as_py() for batch in batches for text in batch.column(0))
        used = np.flatnonzero(sums.any(axis=1))
        columns = [pa.array(used.astype(np.int32)), *(pa.array(sums[used, i].astype(np.int64)) for i in range(DIMS))]
        yield pa.RecordBatch.from_arrays(columns, names=["row", *names])

    names = [f"v{i}" for i in range(DIMS)]
    schema = ", ".join(["row int", *(f"{n} long" for n in names)])
    summed = sample.select("text").mapInArrow(contexts, schema).groupBy("row").agg(*[F.sum(n).alias(n) for n in names]).toArrow()
    table = np.zeros((ROWS, DIMS))
    if summed.num_rows:
        table[summed["row"].to_numpy()] = np.stack([summed[n].to_numpy() for n in names], axis=1)
    table = unit_rows(table)
    sent = spark.sparkContext.broadcast(table)

    def pooled(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pooler = Pooler(sent.value)
        for batch in batches:
            rows = [pooler.pooled(text.as_py()).tobytes() for text in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array(rows, pa.binary())], names=["doc_id", "label", "x"])

    found = sample.mapInArrow(pooled, "doc_id long, label int, x binary").toArrow()
    got = sorted(zip(found["doc_id"].to_pylist(), found["x"].to_pylist(), found["label"].to_pylist(), strict=True))
    net = fit(table, np.array([np.frombuffer(x, dtype=np.float32) for _, x, _ in got]), np.array([y for _, _, y in got]), sizes)
    sent.unpersist()
    return net


def score_documents(spark: SparkSession, docs: DataFrame, net: QualityNet) -> DataFrame:
    """doc_id, held_out, score and predicted (score of 0.7 or more) of every row, from its whole text alone.

    A null or blank text has the vector of no words. Repeated rows get equal scores; a null doc_id is carried, its fold
    that of an empty id. Columns other than doc_id and text are not read. The model is three megabytes whatever the input.
    """
    sent = spark.sparkContext.broadcast(net)

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pooler = Pooler(sent.value.table)
        for batch in batches:
            x = np.array([pooler.pooled(t.as_py() or "") for t in batch.column(1)]).reshape(-1, 4 * DIMS + 3)
            scores = sent.value.probability(x)
            predicted = pa.array((scores >= THRESHOLD).astype(np.int32), pa.int32())
            yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), batch.column(2), pa.array(scores, pa.float64()), predicted], names=["doc_id", "held_out", "score", "predicted"])

    held = (fold(docs["doc_id"], FOLDS) == HELD_OUT).alias("held_out")
    return docs.select("doc_id", "text", held).mapInArrow(score, SCORES)


def good_documents(spark: SparkSession, docs: DataFrame, net: QualityNet) -> DataFrame:
    """The rows of ``docs``, all columns, whose score is 0.7 or more; a null or blank text is scored as no words."""
    sent = spark.sparkContext.broadcast(net)
    at = docs.columns.index("text")

    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pooler = Pooler(sent.value.table)
        for batch in batches:
            x = np.array([pooler.pooled(t.as_py() or "") for t in batch.column(at)]).reshape(-1, 4 * DIMS + 3)
            yield batch.filter(pa.array(sent.value.probability(x) >= THRESHOLD))

    return docs.mapInArrow(keep, docs.schema)

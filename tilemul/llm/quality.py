"""Quality classifier: random-indexing word vectors and a small calibrated network.

Every word falls into one of a fixed number of vocabulary buckets by hash and has a sparse
ternary index vector; its context vector sums the index vectors of its neighbours over all
documents, in whole numbers, so that no order of summation matters. A document is the mean
and deviation of its words' vectors with four counts. A two-layer network is trained in numpy
on a bounded sample of labelled documents, and a temperature fitted on held-back ones
calibrates its probabilities. Scoring streams over all documents with weights of fixed size.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from typing import NamedTuple
from zlib import crc32

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import whole

BUCKETS, DIM, NONZERO, REACH = 4096, 32, 4, 2
#: Counts beside the pooled vectors.
COUNTS = 4
#: Labelled documents that the network is fitted on at most: those of smallest hash.
SAMPLE = 20_000
HIDDEN, EPOCHS, BATCH, RATE, SEED = 24, 40, 256, 3e-3, 7
#: Share of the sample held back to fit the temperature.
HELD_BACK = 0.2

#: Words whose neighbours are added up at once; bounds a worker's memory.
AT_ONCE = 1 << 16

#: A word: letters, digits, or a run of other marks, each by itself.
_TOKEN = re.compile(rb"[A-Za-z\x80-\xff]+|[0-9]+|[^\sA-Za-z0-9\x80-\xff]+")


def buckets_of(text: str | None) -> np.ndarray:
    """Vocabulary buckets of a text's words, in order."""
    words = _TOKEN.findall((text or "").encode("utf-8", "surrogatepass"))
    return np.fromiter(map(crc32, words), dtype=np.uint32, count=len(words)) % BUCKETS


def index_vectors(seed: int = SEED) -> np.ndarray:
    """Sparse ternary vectors of all buckets: as many ones as minus ones."""
    generator = np.random.default_rng(seed)
    vectors = np.zeros((BUCKETS, DIM), dtype=np.int64)
    for row in vectors:
        at = generator.choice(DIM, NONZERO, replace=False)
        row[at[: NONZERO // 2]], row[at[NONZERO // 2 :]] = 1, -1
    return vectors


def add_contexts(total: np.ndarray, documents: list[np.ndarray], index: np.ndarray) -> None:
    """Adds to each bucket's context vector the index vectors around its words."""
    if not documents:
        return
    gap = np.full(REACH, BUCKETS)  # words of neighbouring documents are no neighbours
    words = np.concatenate([p for d in documents for p in (d, gap)])
    padded = np.vstack([index, np.zeros((1, DIM), np.int64)]).astype(np.int16)
    own = padded[words]
    around = np.zeros_like(own)
    for step in range(1, REACH + 1):
        around[:-step] += own[step:]
        around[step:] += own[:-step]
    order = np.argsort(words, kind="stable")
    sorted_words = words[order]
    starts = np.flatnonzero(np.r_[True, sorted_words[1:] != sorted_words[:-1]])
    sums = np.add.reduceat(around[order], starts, axis=0, dtype=np.int64)
    present = sorted_words[starts]
    real = present < BUCKETS
    total[present[real]] += sums[real]


def context_vectors(docs: DataFrame, seed: int = SEED) -> np.ndarray:
    """(BUCKETS, DIM) context vectors over every text; a table of fixed size."""
    index = index_vectors(seed)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((BUCKETS, DIM), dtype=np.int64)
        held, n = [], 0
        for batch in batches:
            for text in batch.column(0):
                words = buckets_of(text.as_py())
                for at in range(0, len(words), AT_ONCE):
                    held.append(words[at : at + AT_ONCE])  # a very long text in pieces
                    n += len(held[-1])
                    if n >= AT_ONCE:
                        add_contexts(total, held, index)
                        held, n = [], 0
        add_contexts(total, held, index)
        used = np.flatnonzero(total.any(axis=1))
        yield pa.RecordBatch.from_arrays(
            [pa.array(used.astype(np.int64)), *(pa.array(total[used, d]) for d in range(DIM))],
            ["bucket", *(f"d{d}" for d in range(DIM))],
        )

    fields = [f"d{d}" for d in range(DIM)]
    sums = (
        docs.select(whole().alias("text"))
        .mapInArrow(run, "bucket long, " + ", ".join(f"{f} long" for f in fields))
        .groupBy("bucket")
        .agg(*(F.sum(f).alias(f) for f in fields))
    )
    table = np.zeros((BUCKETS, DIM), dtype=np.int64)
    for row in sums.collect():  # BUCKETS rows at most
        table[row[0]] = row[1:]
    return table


def word_vectors(contexts: np.ndarray, seed: int = SEED) -> np.ndarray:
    """A bucket's own index vector beside its context vector of unit length."""
    length = np.linalg.norm(contexts.astype(float), axis=1, keepdims=True)
    context = contexts / np.maximum(length, 1.0)
    own = index_vectors(seed) / np.sqrt(NONZERO)
    return np.hstack([own, context]).astype(np.float32)


def features(words: np.ndarray, vectors: np.ndarray) -> np.ndarray:
    """Pooled vector of a document: mean, deviation and four counts.

    The counts: log of length, share of different words, of the most common word, and of words
    that repeat the one before.
    """
    n = len(words)
    if n == 0:
        return np.zeros(2 * vectors.shape[1] + COUNTS)
    counts = np.bincount(words, minlength=len(vectors)) if n > 64 else None
    if counts is None:
        used, times = np.unique(words, return_counts=True)
    else:
        used = np.flatnonzero(counts)
        times = counts[used]
    share = (times / n)[:, None]
    rows = vectors[used].astype(float)
    mean = (rows * share).sum(axis=0)
    deviation = np.sqrt(np.maximum((rows * rows * share).sum(axis=0) - mean * mean, 0.0))
    again = np.count_nonzero(words[1:] == words[:-1]) / n
    return np.concatenate([mean, deviation, [np.log1p(n) / 10, len(used) / n, times.max() / n, again]])


class Network(NamedTuple):
    """Standardization, two layers and a temperature."""

    centre: np.ndarray
    spread: np.ndarray
    w1: np.ndarray
    b1: np.ndarray
    w2: np.ndarray
    b2: float
    temperature: float

    def logits(self, x: np.ndarray) -> np.ndarray:
        hidden = np.maximum((x - self.centre) / self.spread @ self.w1 + self.b1, 0.0)
        return hidden @ self.w2 + self.b2

    def probabilities(self, x: np.ndarray) -> np.ndarray:
        return 1.0 / (1.0 + np.exp(-np.clip(self.logits(x) / self.temperature, -35, 35)))


def train(x: np.ndarray, y: np.ndarray, seed: int = SEED) -> Network:
    """A network for labels 0 and 1. Without rows of both labels it gives the share of ones."""
    n, width = x.shape
    if n == 0 or y.min() == y.max():
        p = np.clip((y.sum() + 1) / (n + 2), 1e-6, 1 - 1e-6)
        return Network(np.zeros(width), np.ones(width), np.zeros((width, 1)), np.zeros(1), np.zeros(1), float(np.log(p / (1 - p))), 1.0)
    generator = np.random.default_rng(seed)
    order = generator.permutation(n)
    held = order[: int(n * HELD_BACK)]
    fit = order[len(held) :]
    centre, spread = x[fit].mean(axis=0), x[fit].std(axis=0) + 1e-6
    z = x - centre
    z /= spread  # in place: the sample lies on the driver
    parameters = [
        generator.normal(0, np.sqrt(2 / width), (width, HIDDEN)),
        np.zeros(HIDDEN),
        generator.normal(0, np.sqrt(1 / HIDDEN), HIDDEN),
        np.zeros(1),
    ]
    first = [np.zeros_like(p) for p in parameters]
    second = [np.zeros_like(p) for p in parameters]
    step = 0
    for _ in range(EPOCHS):
        for at in range(0, len(fit), BATCH):
            some = generator.choice(fit, min(BATCH, len(fit)), replace=False)
            w1, b1, w2, b2 = parameters
            before = z[some] @ w1 + b1
            hidden = np.maximum(before, 0.0)
            p = 1 / (1 + np.exp(-np.clip(hidden @ w2 + b2, -35, 35)))
            error = (p - y[some]) / len(some)
            back = np.outer(error, w2) * (before > 0)
            slopes = [z[some].T @ back + 1e-4 * w1, back.sum(0), hidden.T @ error + 1e-4 * w2, error.sum(keepdims=True)]
            step += 1
            for i, g in enumerate(slopes):
                first[i] = 0.9 * first[i] + 0.1 * g
                second[i] = 0.999 * second[i] + 0.001 * g * g
                parameters[i] = parameters[i] - RATE * (first[i] / (1 - 0.9**step)) / (np.sqrt(second[i] / (1 - 0.999**step)) + 1e-8)
    w1, b1, w2, b2 = parameters
    network = Network(centre, spread, w1, b1, w2, float(b2[0]), 1.0)
    return network._replace(temperature=fit_temperature(network.logits(x[held]), y[held]))


def fit_temperature(logits: np.ndarray, y: np.ndarray) -> float:
    """The temperature of least log loss, by golden section over its logarithm."""
    if len(y) == 0:
        return 1.0

    def loss(t: float) -> float:
        z = logits / np.exp(t)
        return float(np.mean(np.logaddexp(0, z) - y * z))

    low, high, ratio = -3.0, 4.0, (np.sqrt(5) - 1) / 2
    for _ in range(60):
        a, b = high - ratio * (high - low), low + ratio * (high - low)
        low, high = (low, b) if loss(a) < loss(b) else (a, high)
    return float(np.exp((low + high) / 2))


class Model(NamedTuple):
    vectors: np.ndarray
    network: Network


def fit(docs: DataFrame, labels: DataFrame, label: str = "quality", sample: int = SAMPLE) -> Model:
    """Word vectors over all of ``docs`` and a network on a bounded sample of labelled rows.

    Rows whose crc32 of the id as text leaves 1 modulo 3 are held out and never sampled. Null labels or
    ids, and labels other than 0 and 1, are left out; the label of an id that repeats is the
    largest one, its text the one of smallest hash.
    """
    vectors = word_vectors(context_vectors(docs))
    chosen = (
        labels.where(F.col(label).isin(0, 1) & F.col("doc_id").isNotNull())
        .select(F.col("doc_id").cast("long").alias("id"), F.col(label).cast("int").alias("y"))
        .where(~held_out("id"))
        .groupBy("id")
        .agg(F.max("y").alias("y"))
        .orderBy(F.xxhash64("id"), "id")
        .limit(sample)
    )

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [features(buckets_of(t.as_py()), vectors).astype("<f8").tobytes() for t in batch.column(2)]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), pa.array(rows, pa.binary()), batch.column(3)], ["id", "y", "x", "content"]
            )

    rows = (
        docs.select(F.col("doc_id").cast("long").alias("id"), whole().alias("text"))
        .join(F.broadcast(chosen), "id")  # at most ``sample`` ids
        .select("id", "y", "text", F.xxhash64("text").alias("content"))
        .mapInArrow(run, "id long, y int, x binary, content long")
        .groupBy("id", "y")
        .agg(F.min_by("x", "content").alias("x"))
        .toArrow()
        .sort_by("id")
    )
    return Model(vectors, train(numbers(rows["x"], 2 * vectors.shape[1] + COUNTS), rows["y"].to_numpy().astype(float)))


def numbers(cells: pa.ChunkedArray, width: int) -> np.ndarray:
    """Binary cells of ``width`` numbers each as one table; no number becomes an object of the driver's."""
    x = np.empty((len(cells), width))
    for n, cell in enumerate(cells):
        x[n] = np.frombuffer(cell.as_buffer(), "<f8")
    return x


def held_out(name: str):
    """Whether an id belongs to the fold that is never learned from."""
    return F.coalesce(F.crc32(F.col(name).cast("string")) % 3 == 1, F.lit(False))


def score(docs: DataFrame, model: Model) -> DataFrame:
    """(doc_id, held_out, score, predicted) for every row of ``docs`` (doc_id, text, ...).

    Null and empty texts have zero features and get a score like any other. A null id is not
    held out. Repeated rows each get a row; other columns are ignored.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = np.array([features(buckets_of(t.as_py()), model.vectors) for t in batch.column(2)])
            p = model.network.probabilities(x) if batch.num_rows else np.zeros(0)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), pa.array(p), pa.array((p >= 0.5).astype(np.int32))],
                ["doc_id", "held_out", "score", "predicted"],
            )

    return docs.select(
        F.col("doc_id").cast("long").alias("doc_id"), held_out("doc_id").alias("held_out"), whole().alias("text")
    ).mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int")


def keep_good(docs: DataFrame, model: Model) -> DataFrame:
    """``docs`` without the documents that the model rejects; all columns as they are."""
    names = [f.name for f in docs.schema.fields]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at = names.index("text")
        for batch in batches:
            if batch.num_rows:
                x = np.array([features(buckets_of(t.as_py()), model.vectors) for t in batch.column(at)])
                yield batch.filter(pa.array(model.network.probabilities(x) >= 0.5))

    return docs.mapInArrow(run, docs.schema)

"""Quality classifier: random-indexing word vectors, pooled per document, then a small calibrated network.

Random indexing gives every word a sparse random index vector and sums, over all documents, the index
vectors of its neighbours; the sums are the word's context vector.  Words share ``BUCKETS`` rows by hash and
stand twice, as themselves and as their shape (runs of upper, lower, digit, each sign), so that the model's
size is fixed while its counts cover every word of every document.  A document is the mean and the spread of
its words' vectors, of both kinds.

The network (one hidden layer of tanh, a logistic output) is fitted in numpy on the driver, on at most
``most`` labelled documents, chosen by a hash of their id; a fifth of those sets the temperature that
divides the logit.  Only ``labels.quality`` teaches, and only of rows whose crc32(doc_id) mod 5 isn't 0;
language, source and id are never inputs.

Defined cases: a null or empty text is scored from the zero vector; null labels and labels without a
document teach nothing; where fewer than two classes can be learned the score is the share of label 1 (0.5
without any label); of an id's several labels the lower one teaches, and of its several texts one, so that no more
than ``most`` rows ever come to the driver; repeated rows are scored one by one, very long texts whole, equal texts
alike; other columns are ignored; an empty table gives an
empty result.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import documents, lean, text_array
from .wordhash import Hasher, U, blocks, mix

BUCKETS = 1 << 14
DIM = 32
_CHUNK = 1 << 9
_POOL = 1 << 18  # bytes of text whose words' vectors stand in memory at once
THRESHOLD = 0.3

# Classes of bytes for shapes; signs stand for themselves.
_CLASS = np.arange(256, dtype=np.int64)
_CLASS[48:58] = 48
_CLASS[65:91] = 65
_CLASS[97:123] = 97
_CLASS[128:] = 97


def _tokens(flat: np.ndarray, ends: np.ndarray, hasher: Hasher) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Document, word bucket and shape bucket of each word."""
    doc, starts, h = hasher.words_of(flat, ends)
    if not len(doc):
        none = np.zeros(0, np.int64)
        return none, none, none
    shape = U(1469598103934665603) * np.ones(len(starts), U)
    kind = _CLASS[flat]
    turn = np.ones(len(flat), bool)
    turn[1:] = kind[1:] != kind[:-1]
    turn[starts] = True
    place = np.flatnonzero(turn)
    word = np.searchsorted(starts, place, side="right") - 1
    nth = np.arange(len(place)) - np.searchsorted(place, starts)[word]
    ink = kind[place] > 32  # blanks have no part
    part = mix(kind[place].astype(U) * U(0x9E3779B97F4A7C15) + nth.astype(U))
    np.add.at(shape, word[ink], part[ink])
    return doc, (h >> U(50)).astype(np.int64), (mix(shape) >> U(50)).astype(np.int64)


def _index_vectors() -> tuple[np.ndarray, np.ndarray]:
    """Places and signs of the four entries of each bucket's index vector."""
    h = mix(np.arange(BUCKETS * 4, dtype=U) + U(77)).reshape(BUCKETS, 4)
    return (h % U(DIM)).astype(np.int64), np.where((h >> U(40)) & U(1), 1, -1).astype(np.int64)


def context_vectors(docs: DataFrame, reach: int = 2) -> np.ndarray:
    """(2, BUCKETS, DIM) unit context vectors of words and of shapes, summed over all documents."""
    place, sign = _index_vectors()

    def gather(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hasher, total = Hasher(4, fold=True), np.zeros((2, BUCKETS * DIM), np.int64)
        for batch in batches:
            for _, _, flat, ends in blocks(text_array(batch.column("text"))):
                doc, words, shapes = _tokens(flat, ends, hasher)
                for step in range(1, reach + 1):
                    near = doc[step:] == doc[:-step]
                    for t, x in enumerate((words, shapes)):
                        a, b = x[:-step][near], x[step:][near]
                        for k in range(4):
                            key = np.concatenate([a * DIM + place[b, k], b * DIM + place[a, k]])
                            up = np.concatenate([sign[b, k], sign[a, k]]) > 0
                            total[t] += np.bincount(key[up], minlength=BUCKETS * DIM) - np.bincount(key[~up], minlength=BUCKETS * DIM)
        parts = total.reshape(-1, _CHUNK * DIM)
        yield pa.RecordBatch.from_arrays([pa.array(range(len(parts)), pa.int32()), pa.array([x.astype("<i8").tobytes() for x in parts], pa.binary())], ["chunk", "sums"])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            for c, x in zip(batch.column("chunk").to_pylist(), batch.column("sums").to_pylist(), strict=True):
                v = np.frombuffer(x, "<i8")
                sums[c] = sums[c] + v if c in sums else v
        yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.int32()), pa.array([x.tobytes() for x in sums.values()], pa.binary())], ["chunk", "sums"])

    rows = docs.select("text").mapInArrow(lean(gather), "chunk int, sums binary").repartition(16, "chunk").mapInArrow(lean(add), "chunk int, sums binary").collect()  # of fixed size
    out = np.zeros((2 * BUCKETS // _CHUNK, _CHUNK * DIM))
    for c, x in rows:
        out[c] = np.frombuffer(x, "<i8")
    out = out.reshape(2, BUCKETS, DIM)
    # Sums travel as whole numbers of 64 bits: the order of adding them does not show.
    return (out / np.maximum(np.linalg.norm(out, axis=2, keepdims=True), 1e-9)).astype(np.float32)


def pooled(texts: pa.LargeStringArray, vectors: np.ndarray, hasher: Hasher) -> np.ndarray:
    """Mean and spread of the words' and shapes' vectors of each text."""
    out = np.zeros((len(texts), 4 * DIM), np.float32)
    for a, b, flat, ends in blocks(texts, _POOL):
        doc, words, shapes = _tokens(flat, ends, hasher)
        if not len(doc):
            continue
        has, first = np.unique(doc, return_index=True)
        n = np.diff(np.append(first, len(doc)))[:, None].astype(np.float32)
        for t, x in enumerate((words, shapes)):
            v = vectors[t][x]
            mean = np.add.reduceat(v, first, axis=0) / n
            spread = np.sqrt(np.maximum(np.add.reduceat(v * v, first, axis=0) / n - mean * mean, 0))
            out[a + has, 2 * t * DIM : (2 * t + 1) * DIM] = mean
            out[a + has, (2 * t + 1) * DIM : (2 * t + 2) * DIM] = spread
    return out


def _sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


@dataclass
class Network:
    centre: np.ndarray
    scale: np.ndarray
    w1: np.ndarray
    b1: np.ndarray
    w2: np.ndarray
    b2: float
    temperature: float = 1.0

    def logit(self, x: np.ndarray) -> np.ndarray:
        return np.tanh(((x - self.centre) / self.scale) @ self.w1 + self.b1) @ self.w2 + self.b2

    def score(self, x: np.ndarray) -> np.ndarray:
        return _sigmoid(self.logit(x) / self.temperature)


def fit(x: np.ndarray, y: np.ndarray, hidden: int = 24, epochs: int = 60, seed: int = 5) -> Network:
    """Adam on the logistic loss over four fifths of the rows; the rest sets the temperature."""
    dim = x.shape[1]
    if len(set(y.tolist())) < 2:
        share = float(y.mean()) if len(y) else 0.5
        share = min(max(share, 1e-3), 1 - 1e-3)
        return Network(np.zeros(dim), np.ones(dim), np.zeros((dim, 1)), np.zeros(1), np.zeros(1), float(np.log(share / (1 - share))))
    rng = np.random.default_rng(seed)
    held = np.arange(len(y)) % 5 == 4
    tx, ty = x[~held].astype(float), y[~held].astype(float)
    net = Network(tx.mean(0), tx.std(0) + 1e-4, rng.normal(0, 1 / np.sqrt(dim), (dim, hidden)), np.zeros(hidden), rng.normal(0, 1 / np.sqrt(hidden), hidden), 0.0)
    tx = (tx - net.centre) / net.scale
    state = [np.zeros_like(p) for p in (net.w1, net.b1, net.w2)] * 2 + [0.0, 0.0]
    state = [s.copy() if isinstance(s, np.ndarray) else s for s in state]
    step, size = 0, 128
    for epoch in range(epochs):
        rate = 0.01 * 0.5 * (1 + np.cos(np.pi * epoch / epochs))
        order = rng.permutation(len(ty))
        for at in range(0, len(order), size):
            pick = order[at : at + size]
            a = np.tanh(tx[pick] @ net.w1 + net.b1)
            g = (_sigmoid(a @ net.w2 + net.b2) - ty[pick]) / len(pick)
            back = np.outer(g, net.w2) * (1 - a * a)
            grads = [tx[pick].T @ back + 1e-4 * net.w1, back.sum(0), a.T @ g + 1e-4 * net.w2]
            step += 1
            for i, (p, d) in enumerate(zip((net.w1, net.b1, net.w2), grads, strict=True)):
                state[i] = 0.9 * state[i] + 0.1 * d
                state[i + 3] = 0.999 * state[i + 3] + 0.001 * d * d
                p -= rate * (state[i] / (1 - 0.9**step)) / (np.sqrt(state[i + 3] / (1 - 0.999**step)) + 1e-8)
            net.b2 -= rate * float(g.sum())
    if held.any():
        z, t = net.logit(x[held]), y[held]
        grid = np.exp(np.linspace(-1.5, 2.5, 81))
        losses = [-np.mean(np.log(np.where(t == 1, p := _sigmoid(z / g), 1 - p) + 1e-12)) for g in grid]
        net.temperature = float(grid[int(np.argmin(losses))])
    return net


def held_out(doc_id: Column) -> Column:
    return F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0


def train(docs: DataFrame, labels: DataFrame, most: int = 12_000) -> tuple[np.ndarray, Network]:
    """Context vectors over all ``docs`` and the network fitted on at most ``most`` labelled ones."""
    spark = docs.sparkSession
    vectors = context_vectors(docs)
    taught = labels.where(F.col("quality").isin(0, 1) & F.col("doc_id").isNotNull()).select(F.col("doc_id").cast("long").alias("doc_id"), F.col("quality").cast("int").alias("quality")).where(~held_out(F.col("doc_id")))
    sample = taught.groupBy("doc_id").agg(F.min("quality").alias("quality")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)
    known = spark.sparkContext.broadcast(vectors)

    def features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hasher = Hasher(4, fold=True)
        for batch in batches:
            x = pooled(text_array(batch.column("text")), known.value, hasher)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("quality"), pa.array([r.tobytes() for r in x], pa.binary())], ["doc_id", "quality", "x"])

    chosen = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(F.broadcast(sample), "doc_id")  # ``most`` rows
    found = chosen.mapInArrow(lean(features), "doc_id long, quality int, x binary").groupBy("doc_id", "quality").agg(F.min("x").alias("x"))  # ``most`` rows
    rows = sorted((r["doc_id"], r["quality"], bytes(r["x"])) for r in found.collect())
    x = np.array([np.frombuffer(r[2], np.float32) for r in rows]).reshape(-1, 4 * DIM)
    y = np.array([r[1] for r in rows], int)
    order = np.argsort(mix(np.array([r[0] for r in rows], np.int64).view(U)), kind="stable") if rows else np.zeros(0, int)
    return vectors, fit(x[order], y[order])


def classify(docs: DataFrame, labels: DataFrame, most: int = 12_000) -> DataFrame:
    """doc_id, score and predicted of every document."""
    spark = docs.sparkSession
    known = spark.sparkContext.broadcast(train(docs, labels, most))  # of fixed size

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hasher, (vectors, net) = Hasher(4, fold=True), known.value
        for batch in batches:
            score = net.score(pooled(text_array(batch.column("text")), vectors, hasher)).astype(float)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(score), pa.array((score >= THRESHOLD).astype(np.int32))], ["doc_id", "score", "predicted"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(lean(work), "doc_id long, score double, predicted int")


def keep_good(docs: DataFrame, labels: DataFrame, most: int = 12_000) -> DataFrame:
    """``docs`` without the rejected ones, all columns kept; scores travel with the rows, so nothing is joined."""
    spark = docs.sparkSession
    known = spark.sparkContext.broadcast(train(docs, labels, most))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hasher, (vectors, net) = Hasher(4, fold=True), known.value
        for batch in batches:
            good = net.score(pooled(text_array(batch.column("text")), vectors, hasher)) >= THRESHOLD
            yield batch.filter(pa.array(good))

    return docs.mapInArrow(lean(work), docs.schema)


def op2_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = classify(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return found.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", "predicted")


QUERIES: dict[str, Callable] = {"op2_quality": op2_quality}

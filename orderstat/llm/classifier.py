"""Quality classifier: random-indexing word vectors pooled per document, then a two-layer network with calibrated output.

Every word has a sparse random index vector by its hash. One pass over all documents adds to each word's bucket the index
vectors of the words next to it, which gives the context vectors. Buckets follow the fourth root of the corpus's bytes: the
table grows with the vocabulary, yet a broadcast of it stays near 128 MB at 100 TB. A document is the mean of its words' context vectors beside the mean of the index vectors of their
shapes (runs of upper case, lower case, digits and marks) and of a sign for a word that repeats the one before.

The network is fitted on the driver on at most MOST_LABELLED labelled rows, a seeded choice. Two parts of them are kept from
the fit: one chooses the epoch, the other sets the temperature that makes the output a probability.

Cases: null and empty texts are pooled as a zero vector and scored like any other; labels that are null or whose doc_id is
null teach nothing; a doc_id labelled twice takes the higher label, and one that stands in several rows teaches its least text; with no labels, or one class only, every score is the
share of label 1 (0.5 without any); repeated rows give repeated rows; other columns are ignored; an empty table gives an
empty one.
"""

from __future__ import annotations

import math
import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from orderstat.llm.common import ASCII_LOWER, id_and_text, lean, pieces, raw_texts, stored

#: Buckets of shapes, and of the words of a corpus up to BUCKET_BYTES.
BUCKETS, DIMS, SIGNS = 1 << 14, 32, 2
BUCKET_BYTES = 100_000_000
#: Words whose neighbours are added up at once.
WORDS_AT_ONCE = 1 << 19
MOST_LABELLED = 20_000
#: Score from which a document counts as of label 1.
ACCEPT = 0.3
MOST_WORDS_KEPT = 250_000
_RUNS = re.compile(rb"(.)\1+", re.S)
_SHAPE = bytes(97 if 97 <= b <= 122 or b >= 128 else 65 if 65 <= b <= 90 else 48 if 48 <= b <= 57 else b for b in range(256))


def index_vectors(count: int, seed: int) -> np.ndarray:
    """Sparse ternary rows, SIGNS entries each."""
    rng = np.random.default_rng(seed)
    out = np.zeros((count, DIMS), dtype=np.float32)
    for _ in range(SIGNS):
        out[np.arange(count), rng.integers(0, DIMS, count)] += rng.choice(np.array([-1, 1], dtype=np.float32), count)
    return out


def buckets_for(size: int) -> int:
    """Word buckets of a corpus of size bytes: a power of two, growing with the fourth root of the size."""
    return BUCKETS << math.ceil(max(0.0, math.log2(max(1, size) / BUCKET_BYTES)) / 4)


class Reader:
    """Turns texts into word buckets and shape buckets; keeps what it has seen of the vocabulary."""

    def __init__(self, buckets: int = BUCKETS):
        self.seen: dict[bytes, int] = {}
        self.buckets = buckets

    def look(self, word: bytes) -> int:
        """The word's bucket times BUCKETS, plus its shape's bucket."""
        found = self.seen.get(word)
        if found is None:
            if len(self.seen) >= MOST_WORDS_KEPT:
                self.seen.clear()
            shape = _RUNS.sub(rb"\1", word.translate(_SHAPE))
            found = self.seen[word] = xxhash.xxh3_64_intdigest(word.translate(ASCII_LOWER)) % self.buckets * BUCKETS + xxhash.xxh3_64_intdigest(shape) % BUCKETS
        return found

    def read(self, raw: bytes) -> tuple[np.ndarray, np.ndarray]:
        words = raw.split()
        both = np.fromiter(map(self.look, words), dtype=np.int64, count=len(words))
        return both // BUCKETS, both % BUCKETS


def _context(buckets: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """One row a task: the sums of its words' neighbours, as the cells that are not zero of a table of buckets by DIMS."""
        rng = np.random.default_rng(1)
        place, sign = rng.integers(0, DIMS, (SIGNS, buckets)), rng.choice(np.array([-1.0, 1.0]), (SIGNS, buckets))
        total, reader, held, size = np.zeros(buckets * DIMS), Reader(buckets), [], 0

        def add() -> None:
            left, right = np.concatenate([w[:-1] for w in held]), np.concatenate([w[1:] for w in held])
            for own, other in ((left, right), (right, left)):
                for k in range(SIGNS):
                    total[:] += np.bincount(own * DIMS + place[k][other], weights=sign[k][other], minlength=buckets * DIMS)

        for batch in pieces(batches):
            for raw in raw_texts(batch.column("text")):
                held.append(reader.read(raw)[0])
                size += len(held[-1])
                if size >= WORDS_AT_ONCE:
                    add()
                    held, size = [], 0
        if held:
            add()
        cells = np.flatnonzero(total)
        yield pa.RecordBatch.from_pydict({"part": pa.array([TaskContext.get().partitionId()], pa.int64()), "cells": pa.array([cells.astype("<i4").tobytes()], pa.binary()), "sums": pa.array([total[cells].astype("<i8").tobytes()], pa.binary())})

    return lean(run)


def _add(buckets: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(buckets * DIMS)
        for batch in batches:
            for cells, sums in zip(batch.column("cells"), batch.column("sums")):
                total[np.frombuffer(cells.as_buffer(), dtype="<i4")] += np.frombuffer(sums.as_buffer(), dtype="<i8")
        yield pa.RecordBatch.from_pydict({"part": pa.array([0], pa.int64()), "sums": pa.array([total.tobytes()], pa.binary())})

    return lean(run)


def context_vectors(docs: DataFrame, ways: int = 12) -> np.ndarray:
    """The table of context vectors over all documents, rows of length one; sums are whole numbers, so any order gives the same."""
    texts = id_and_text(docs).select("text")
    buckets = buckets_for(texts.agg(F.sum(F.octet_length("text"))).first()[0] or 0)
    parts = stored(texts.mapInArrow(_context(buckets), "part long, cells binary, sums binary"), "contexts")
    rows = parts.repartition(ways, "part").mapInArrow(_add(buckets), "part long, sums binary").toLocalIterator()  # one table at a time
    total = np.zeros(buckets * DIMS)
    for r in rows:
        total += np.frombuffer(r["sums"], dtype=np.float64)
    vectors = total.reshape(buckets, DIMS)
    return (vectors / np.maximum(np.linalg.norm(vectors, axis=1, keepdims=True), 1e-9)).astype(np.float32)


def pool(texts: list[bytes], vectors: np.ndarray, shapes: np.ndarray, reader: Reader) -> np.ndarray:
    out = np.zeros((len(texts), 2 * DIMS + 1), dtype=np.float32)
    for k, raw in enumerate(texts):
        words, kinds = reader.read(raw)
        if len(words):
            for j in range(0, len(words), 1 << 16):
                out[k, :DIMS] += vectors[words[j : j + (1 << 16)]].sum(axis=0)
                out[k, DIMS : 2 * DIMS] += shapes[kinds[j : j + (1 << 16)]].sum(axis=0)
            out[k, -1] = (words[1:] == words[:-1]).sum()
            out[k] /= len(words)
    return out


@dataclass
class Network:
    """Two layers on standardised inputs; temperature divides the logit."""

    mean: np.ndarray
    scale: np.ndarray
    w1: np.ndarray
    b1: np.ndarray
    w2: np.ndarray
    b2: float
    temperature: float = 1.0

    def logit(self, x: np.ndarray) -> np.ndarray:
        return np.tanh((x - self.mean) / self.scale @ self.w1 + self.b1) @ self.w2 + self.b2

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.logit(x) / self.temperature, -30, 30)))


def _loss(z: np.ndarray, y: np.ndarray) -> float:
    return float(np.mean(np.logaddexp(0, z) - y * z))


def fit(x: np.ndarray, y: np.ndarray, hidden: int = 24, epochs: int = 60, seed: int = 17) -> Network:
    x, y = x.astype(np.float64), y.astype(np.float64)
    if len(y) < 10 or y.min() == y.max():
        share = float(np.clip(y.mean(), 1e-6, 1 - 1e-6)) if len(y) else 0.5
        d = x.shape[1] if x.ndim == 2 else 2 * DIMS + 1
        return Network(np.zeros(d), np.ones(d), np.zeros((d, 1)), np.zeros(1), np.zeros(1), float(np.log(share / (1 - share))))
    rng = np.random.default_rng(seed)
    order = rng.permutation(len(y))
    chosen, held, used = np.split(order, [len(y) // 10, len(y) // 5])
    chosen, held = (chosen, held) if len(chosen) and len(held) else (order, order)
    net = Network(x[used].mean(axis=0), x[used].std(axis=0) + 1e-3, rng.normal(0, 0.2, (x.shape[1], hidden)), np.zeros(hidden), rng.normal(0, 0.2, hidden), 0.0)
    xs = (x - net.mean) / net.scale
    weights = [net.w1, net.b1, net.w2, np.zeros(1)]
    first, second, step, best = [np.zeros_like(w) for w in weights], [np.zeros_like(w) for w in weights], 0, (np.inf, None)
    for _ in range(epochs):
        rng.shuffle(used)
        for k in range(0, len(used), 128):
            at = used[k : k + 128]
            h = np.tanh(xs[at] @ weights[0] + weights[1])
            g = (1 / (1 + np.exp(-np.clip(h @ weights[2] + weights[3], -30, 30))) - y[at]) / len(at)
            back = np.outer(g, weights[2]) * (1 - h * h)
            grads = [xs[at].T @ back + 1e-4 * weights[0], back.sum(axis=0), h.T @ g + 1e-4 * weights[2], np.array([g.sum()])]
            step += 1
            for w, d, m, v in zip(weights, grads, first, second):
                m += 0.1 * (d - m)
                v += 0.01 * (d * d - v)
                w -= 0.005 * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8)
        z = np.tanh(xs[chosen] @ weights[0] + weights[1]) @ weights[2] + weights[3]
        if _loss(z, y[chosen]) < best[0]:
            best = (_loss(z, y[chosen]), [w.copy() for w in weights])
    net.w1, net.b1, net.w2, b2 = best[1]
    net.b2 = float(b2[0])
    z = net.logit(x[held])
    net.temperature = min(np.geomspace(0.25, 4, 41), key=lambda t: _loss(z / t, y[held]))
    return net


def crc32(text: Column) -> Column:
    return F.crc32(text.cast("string").cast("binary"))


@dataclass
class Model:
    """What scoring needs; its size is that of the vectors, one for each word bucket."""

    vectors: np.ndarray
    shapes: np.ndarray
    network: Network

    def score(self, texts: list[bytes], reader: Reader) -> np.ndarray:
        return self.network.score(pool(texts, self.vectors, self.shapes, reader).astype(np.float64))


def learn(docs: DataFrame, labels: DataFrame, most_labelled: int = MOST_LABELLED) -> Model:
    """Context vectors from all of docs, the network from the rows (doc_id, quality) of labels."""
    spark, text = docs.sparkSession, id_and_text(docs)
    vectors, shapes = context_vectors(docs), index_vectors(BUCKETS, 2)
    shipped = spark.sparkContext.broadcast((vectors, shapes))  # two tables of buckets by DIMS floats
    taught = labels.filter("doc_id is not null and quality is not null").groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max("quality").cast("int").alias("quality"))
    taught = taught.orderBy(F.xxhash64(F.lit(23), "doc_id"), "doc_id").limit(most_labelled)

    def pooled(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        reader = Reader(len(shipped.value[0]))
        for batch in pieces(batches):
            x = pool(raw_texts(batch.column("text")), *shipped.value, reader)
            yield pa.RecordBatch.from_pydict({"doc_id": batch.column("doc_id"), "quality": batch.column("quality"), "x": pa.array(list(x.astype(np.float64)), pa.list_(pa.float64()))})

    rows = text.join(F.broadcast(taught), "doc_id").groupBy("doc_id", "quality").agg(F.min("text").alias("text")).mapInArrow(lean(pooled), "doc_id long, quality int, x array<double>").toPandas().sort_values("doc_id")
    shipped.destroy()
    net = fit(np.array(rows["x"].tolist()).reshape(len(rows), 2 * DIMS + 1), rows["quality"].to_numpy(dtype=float))
    return Model(vectors, shapes, net)


def scores(docs: DataFrame, model: Model) -> DataFrame:
    """(doc_id, score) for each row of docs."""
    text, shipped = id_and_text(docs), docs.sparkSession.sparkContext.broadcast(model)

    def scored(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        reader = Reader(len(shipped.value.vectors))
        for batch in pieces(batches):
            yield pa.RecordBatch.from_pydict({"doc_id": batch.column("doc_id"), "score": shipped.value.score(raw_texts(batch.column("text")), reader)})

    return text.mapInArrow(lean(scored), "doc_id long, score double")


def taught(labels: DataFrame, folds: int = 5) -> DataFrame:
    """Labels to learn from: all but fold 0 by the crc32 of the id as text."""
    return labels.filter(crc32(F.col("doc_id")) % folds != 0)


def quality(docs: DataFrame, labels: DataFrame, folds: int = 5, accept: float = ACCEPT) -> DataFrame:
    """(doc_id, held_out, score, predicted)."""
    found = scores(docs, learn(docs, taught(labels, folds)))
    return found.select("doc_id", (crc32(F.col("doc_id")) % folds == 0).alias("held_out"), "score", (F.col("score") >= accept).cast("int").alias("predicted"))


def accepted(docs: DataFrame, labels: DataFrame, accept: float = ACCEPT) -> DataFrame:
    """The rows of docs that score accept or more, with all their columns, in one pass and without a join."""
    shipped = docs.sparkSession.sparkContext.broadcast(learn(docs, taught(labels)))

    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        reader = Reader(len(shipped.value.vectors))
        for batch in pieces(batches):
            yield batch.filter(pa.array(shipped.value.score(raw_texts(batch.column("text")), reader) >= accept))

    return docs.mapInArrow(lean(keep), docs.schema)


def fold(doc_id: int, folds: int = 5) -> int:
    return zlib.crc32(str(doc_id).encode()) % folds

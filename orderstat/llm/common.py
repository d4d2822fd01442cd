"""What the text operators share: scratch tables, word splitting, Arrow batches, distributed components."""

from __future__ import annotations

import contextlib
import ctypes
import gc
from collections.abc import Callable, Iterable, Iterator
from functools import wraps

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from orderstat.sources.scratch import shared_dir, stored  # noqa: F401  (the operators take them from here)
from orderstat.sources.tables import table  # noqa: F401

#: The word separators of every contract, as a character class and as characters.
WORD_PATTERN = r"[^\x20\x09-\x0D]+"
SPACES = " \t\n\x0b\x0c\r"
UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
LOWER = "abcdefghijklmnopqrstuvwxyz"
ASCII_LOWER = bytes.maketrans(UPPER.encode(), LOWER.encode())


def id_and_text(docs: DataFrame) -> DataFrame:
    """Only the two columns that the operators read, whatever else the table has."""
    return docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs["text"].cast("string").alias("text"))


def raw_texts(column: pa.Array) -> list[bytes]:
    """UTF-8 bytes of each text, null as empty."""
    kind = pa.large_binary() if pa.types.is_large_string(column.type) else pa.binary()
    return [x or b"" for x in column.cast(kind).to_pylist()]


def pieces(batches: Iterable[pa.RecordBatch], most_bytes: int = 2 << 20) -> Iterator[pa.RecordBatch]:
    """The same rows in slices of about most_bytes, one row at least, so that work arrays stay small."""
    for batch in batches:
        if batch.num_rows == 0:
            continue
        at = batch.schema.get_field_index("text")
        if at < 0:
            yield batch
            continue
        sizes = np.frombuffer(_lengths(batch.column(at)), dtype=np.int64)
        edges = np.cumsum(sizes) // most_bytes
        cuts = [0, *(np.flatnonzero(np.diff(edges)) + 1).tolist(), batch.num_rows]
        for a, b in zip(cuts, cuts[1:]):
            if b > a:
                yield batch.slice(a, b - a)


def _lengths(column: pa.Array) -> bytes:
    import pyarrow.compute as pc

    return np.asarray(pc.fill_null(pc.binary_length(column), 0).to_numpy(zero_copy_only=False)).astype(np.int64).tobytes()


_held: dict = {}
_stage: list[int] = []


def held_for_stage(name: tuple, make: Callable):
    """What make gives, kept by this worker for the tasks of one stage: the first task of another stage drops it (lean)."""
    if name not in _held:
        _held[name] = make()
    return _held[name]


def _give_back() -> None:
    """Free memory of this worker goes back to the system, so that idle workers do not hold what a busy one needs."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # glibc only
        ctypes.CDLL(None).malloc_trim(0)


def lean(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """run as a mapInArrow function that begins without what other stages left in the worker and ends by giving memory back."""

    @wraps(run)
    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at = TaskContext.get()
        stage = [at.stageId()] if at is not None else []
        if stage != _stage:
            _held.clear()
            _stage[:] = stage
            gc.collect()
            _give_back()
        try:
            yield from run(batches)
        finally:
            _give_back()

    return task


def by_doc(work: Callable[[list, list[bytes]], dict[str, list]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """A mapInArrow function from one that takes ids and raw texts and returns columns."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches):
            out = work(batch.column("doc_id").to_pylist(), raw_texts(batch.column("text")))
            yield pa.RecordBatch.from_pydict(out)

    return lean(run)


def small_enough(df: DataFrame, rows: int) -> bool:
    """Whether df has at most so many rows; reads no more than it must to tell."""
    return df.limit(rows + 1).count() <= rows


def local_components(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Smallest reachable index of each of n vertices: hooking and pointer jumping on arrays."""
    label = np.arange(n)
    while len(a):
        low = np.minimum(label[a], label[b])
        np.minimum.at(label, label[a], low)
        np.minimum.at(label, label[b], low)
        while True:
            jump = label[label]
            if (jump == label).all():
                break
            label = jump
        left = label[a] != label[b]
        a, b = a[left], b[left]
    return label


def components(edges: DataFrame) -> DataFrame:
    """Connected components of edges (a, b): one row (node, root) for each vertex with an edge, root the smallest.

    Alternates two rewiring steps over the whole edge list; both are a minimum per vertex (combined before the shuffle)
    and a join, so no vertex's neighbours are ever gathered. Every round is written to the shared folder. Rounds go on until every
    edge is a star's; their number grows with the logarithm of the longest path.
    """
    now = stored(edges.filter("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "edges")
    while True:
        both = now.unionByName(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
        wide = both.filter("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).filter("a <> b").distinct()
        least = wide.groupBy("a").agg(F.min("b").alias("m"))
        near = wide.join(least, "a")
        near = near.select(F.explode(F.array(F.struct(F.col("a"), F.col("m").alias("b")), F.struct(F.col("b").alias("a"), F.col("m").alias("b")))).alias("e")).select("e.*").filter("a <> b").distinct()
        now = stored(near, "edges")
        # Finished when every edge is a star's: no centre hangs on another vertex, and no vertex on two centres.
        if now.select(F.col("b").alias("a")).join(now, "a", "left_semi").isEmpty() and now.count() == now.select("a").distinct().count():
            return now.select(F.col("a").alias("node"), F.col("b").alias("root")).unionByName(now.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct())

"""Benchmark decontamination: size-partitioned MinHash containment search, verified by exact shingle containment.

Items are partitioned by their number of distinct shingles. An item's sketch is its least shingle hashes, as many as its
partition needs so that a document with the wanted containment cannot miss all of them: of n shingles at least
ceil(t n) are in the document, so n - ceil(t n) + 1 hashes hold one of them. Long documents need no sketch of their own
beyond, for each partition, the hashes up to that partition's largest sketch value, and a short item inside a very long document
is found as surely as in a short one. Candidates are checked by comparing shingles as strings.

Items are indexed in blocks of bounded size; each block is broadcast and takes one pass over the documents.

Cases: a null or empty text has no shingles, is never an item's match and never contains one; a text of fewer words than a shingle
is one shingle of all its words; items or documents that repeat give repeated rows; null ids are carried; other columns
are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from orderstat.llm import recompress as R
from orderstat.llm.common import ASCII_LOWER, id_and_text, lean, pieces, raw_texts
from orderstat.llm.repeats import fingerprints

#: Text of a block of items; with its sketches an index holds about three times as much in each worker.
BLOCK_BYTES = 32 << 20
_BITS = 22


def shingles(words: list[bytes], width: int) -> set[bytes]:
    if not words:
        return set()
    return set(map(b" ".join, zip(*(words[k:] for k in range(width))))) if len(words) >= width else {b" ".join(words)}


def names(split: list[list[bytes]], width: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all shingles of width words, and the text each belongs to."""
    words, wall, starts = R.lay_out([fingerprints(w) for w in split])
    at = np.flatnonzero(R.whole_windows(wall, width))
    return R.window_names(words, width, 0x5851F42D4C957F2D, 17)[at], np.searchsorted(starts, at, side="right") - 1


class Partition:
    """Items of one size class: their sketches in order, a filter of the low bits, and the largest sketch value."""

    def __init__(self, sketch: list[np.ndarray], owner: list[int]):
        hashes, owners = np.concatenate(sketch), np.repeat(np.array(owner, dtype=np.int32), [len(s) for s in sketch])
        order = np.argsort(hashes, kind="stable")
        self.sketch, self.owner, self.most = hashes[order], owners[order], hashes.max()
        self.width = np.uint64((1 << min(_BITS, max(10, 4 + len(hashes).bit_length()))) - 1)
        self.bits = np.zeros(int(self.width) + 1, dtype=bool)
        self.bits[(hashes & self.width).astype(np.int64)] = True

    def hits(self, h: np.ndarray, doc: np.ndarray) -> Iterator[tuple[int, int]]:
        """(document, item) for the document hashes that are in an item's sketch."""
        few = np.flatnonzero(h <= self.most)
        few = few[self.bits[(h[few] & self.width).astype(np.int64)]]
        a, z = np.searchsorted(self.sketch, h[few], side="left"), np.searchsorted(self.sketch, h[few], side="right")
        for d, i, j in zip(doc[few].tolist(), a.tolist(), z.tolist()):
            for k in self.owner[i:j].tolist():
                yield d, k


class Index:
    """Sketches of one block of items by size class. Items stay texts; only candidates are cut to shingles again."""

    def __init__(self, items: list[tuple[int | None, bytes]], width: int, threshold: float):
        self.width, self.threshold = width, threshold
        self.ids, self.texts = [i for i, _ in items], [t.translate(ASCII_LOWER) for _, t in items]
        self.short: dict[bytes, list[int]] = {}
        classes: dict[int, tuple[list[np.ndarray], list[int]]] = {}
        for k, text in enumerate(self.texts):
            words = text.split()
            if 0 < len(words) < width:
                self.short.setdefault(b" ".join(words), []).append(k)
            elif words:
                h = np.unique(names([words], width)[0])
                part = len(h).bit_length()
                most = (1 << part) - 1  # the class's largest size decides for all of it
                sketch, owner = classes.setdefault(part, ([], []))
                sketch.append(h[: most - math.ceil(threshold * most - 1e-9) + 1])
                owner.append(k)
        self.partitions = {part: Partition(*held) for part, held in sorted(classes.items())}

    def candidates(self, split: list[list[bytes]]) -> set[tuple[int, int]]:
        found = {(d, k) for d, w in enumerate(split) if 0 < len(w) < self.width for k in self.short.get(b" ".join(w), ())}
        if self.partitions:
            h, doc = names(split, self.width)
            for part in self.partitions.values():
                found.update(part.hits(h, doc))
        return found

    def matches(self, split: list[list[bytes]]) -> list[tuple[int, int, int, int]]:
        """(document, item, shingles of the item that the document has, shingles of the item) at the threshold or over."""
        out, last, own = [], -1, set()
        for d, k in sorted(self.candidates(split)):
            if d != last:
                last, own = d, shingles(split[d], self.width)
            asked = shingles(self.texts[k].split(), self.width)
            hits = len(asked & own)
            if hits >= self.threshold * len(asked) - 1e-9:
                out.append((d, k, hits, len(asked)))
        return out


def contained(docs: DataFrame, items: DataFrame, width: int = 5, threshold: float = 0.8) -> DataFrame:
    """(doc_id, item_id, n_shared, n_shingles, containment) for each document that holds that share of an item's shingles."""
    text = id_and_text(docs)
    schema = "doc_id long, item_id long, n_shared long, n_shingles long, containment double"

    def search(index: Broadcast) -> DataFrame:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in pieces(batches):
                ids, found = batch.column("doc_id").to_pylist(), index.value.matches(lowered(batch))
                yield pa.RecordBatch.from_pydict({"doc_id": pa.array([ids[d] for d, *_ in found], pa.int64()), "item_id": pa.array([index.value.ids[k] for _, k, _, _ in found], pa.int64()), "n_shared": pa.array([h for _, _, h, _ in found], pa.int64()), "n_shingles": pa.array([n for *_, n in found], pa.int64()), "containment": pa.array([h / n for _, _, h, n in found], pa.float64())})

        return text.mapInArrow(lean(run), schema)

    return reduce(DataFrame.unionByName, [search(index) for index in indexes(items, width, threshold)])


def lowered(batch: pa.RecordBatch) -> list[list[bytes]]:
    return [t.translate(ASCII_LOWER).split() for t in raw_texts(batch.column("text"))]


def indexes(items: DataFrame, width: int, threshold: float) -> Iterator[Broadcast]:
    """Broadcast indexes of the items, in blocks of about BLOCK_BYTES of text"""
    asked = items.select(items["item_id"].cast("long").alias("item_id"), items["text"].cast("string").alias("text"))
    size = asked.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    blocks = max(1, math.ceil(size / BLOCK_BYTES))
    for block in range(blocks):
        rows = asked.filter(F.pmod(F.xxhash64("item_id", "text"), F.lit(blocks)) == block).collect()
        yield items.sparkSession.sparkContext.broadcast(Index([(r["item_id"], (r["text"] or "").encode()) for r in rows], width, threshold))


def clean(docs: DataFrame, items: DataFrame, width: int = 5, threshold: float = 0.8) -> DataFrame:
    """The rows of docs that contain no item, with all their columns: a pass for each block of items, without a join."""

    def without(index: Broadcast):
        def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in pieces(batches):
                mask = np.ones(batch.num_rows, dtype=bool)
                mask[[d for d, *_ in index.value.matches(lowered(batch))]] = False
                yield batch.filter(pa.array(mask))

        return lean(keep)

    for index in indexes(items, width, threshold):
        docs = docs.mapInArrow(without(index), docs.schema)
    return docs

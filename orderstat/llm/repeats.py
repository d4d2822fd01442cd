"""Removal of long word sequences that earlier documents hold (substring dedup by recompression).

1. One pass over the texts parses each document by recompression (recompress.py) and keeps a row per document: word
   count, digest of its words, and its window marks, which are about one symbol in three.
2. Symbols that stand in two different texts are counted out of those small rows. Exact copies of a text count once.
3. Only documents that hold a shared mark (or windows with no mark, such as long runs of one word) are read again; each of
   their windows that may repeat gives a 128-bit digest of its own words, not of their names, and the least doc_id of each
   digest decides. Words that share a name can thus make a window a candidate, but not a repeat.
4. A third read of the documents that lose words applies the spans.

Cases: null or empty text has no words; documents under the window length lose nothing unless the window is shorter;
rows with a null doc_id keep all and take nothing from others; rows that repeat a doc_id are one document, which takes
nothing from itself; a copy of a text under a larger doc_id loses all its words if it has a window. Other columns of docs
are ignored. An empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from orderstat.llm import recompress as R
from orderstat.llm.common import by_doc, id_and_text, lean, pieces, raw_texts, stored

ROUNDS = 6
#: What goes with the documents to read again (ids, marks, spans) is broadcast up to so many bytes; beyond, the join shuffles.
BROADCAST_BYTES = 64 << 20
NOTHING = hashlib.sha256(b"").hexdigest()


def fingerprints(words: list[bytes]) -> np.ndarray:
    return np.fromiter(map(xxhash.xxh3_64_intdigest, words), dtype=np.uint64, count=len(words))


def digest(words: list[bytes]) -> str:
    return hashlib.sha256(b" ".join(words)).hexdigest()


def _signatures(window: int):
    def work(ids: list, texts: list[bytes]) -> dict[str, list]:
        split = [t.split() for t in texts]
        long = [k for k, w in enumerate(split) if len(w) >= window]
        marks: list = [[] for _ in ids]
        loose = np.zeros(len(ids), dtype=bool)
        if long:
            words, wall, starts = R.lay_out([fingerprints(split[k]) for k in long])
            p = R.parse(words, wall, ROUNDS)
            _, has, used = R.window_marks(p, len(words), window)
            owner = np.searchsorted(starts, p.start[used], side="right") - 1
            names = p.name[used].view(np.int64)
            edges = np.searchsorted(owner, np.arange(len(long) + 1))
            for j, k in enumerate(long):
                marks[k] = np.unique(names[edges[j] : edges[j + 1]])
            free = np.flatnonzero(R.whole_windows(wall, window) & ~has)
            loose[np.array(long)[np.searchsorted(starts, free, side="right") - 1]] = True
        return {"doc_id": pa.array(ids, pa.int64()), "n_words": pa.array([len(w) for w in split], pa.int64()), "sha": [digest(w) for w in split], "marks": pa.array(marks, pa.list_(pa.int64())), "loose": loose}

    return by_doc(work)


def _windows(window: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches):
            split = [t.split() for t in raw_texts(batch.column("text"))]
            ids, shared = batch.column("doc_id").to_pylist(), np.unique(np.asarray(batch.column("shared").combine_chunks().flatten() if isinstance(batch.column("shared"), pa.ChunkedArray) else batch.column("shared").flatten()).astype(np.int64))
            keep = [k for k, w in enumerate(split) if len(w) >= window]
            if not keep:
                continue
            words, wall, starts = R.lay_out([fingerprints(split[k]) for k in keep])
            p = R.parse(words, wall, ROUNDS)
            mark, has, _ = R.window_marks(p, len(words), window)
            known = R.mix(shared.view(np.uint64) + R.salt(977))
            maybe = np.flatnonzero(R.whole_windows(wall, window) & (~has | np.isin(mark, known)))
            owner = np.searchsorted(starts, maybe, side="right") - 1
            at = maybe - starts[owner]
            name = window_digests([split[k] for k in keep], owner, at, window)
            yield pa.RecordBatch.from_pydict({"h1": name[:, 0], "h2": name[:, 1], "doc_id": np.array([ids[k] for k in keep], dtype=np.int64)[owner], "at": at.astype(np.int32)})

    return run


def window_digests(texts: list[list[bytes]], owner: np.ndarray, at: np.ndarray, window: int) -> np.ndarray:
    """128-bit digests, as two columns, of the words themselves of the windows that start at word at of text owner."""
    line = memoryview(b" ".join(map(b" ".join, texts)))
    size = np.fromiter(map(len, chain.from_iterable(texts)), dtype=np.int64)
    end = np.cumsum(size + 1) - 1
    first = np.cumsum([0, *map(len, texts)])[owner] + at
    out = np.empty((len(at), 2), dtype=np.int64)
    for k in range(0, len(at), 1 << 16):
        f = first[k : k + (1 << 16)]
        spans = zip((end[f] - size[f]).tolist(), end[f + window - 1].tolist())
        out[k : k + len(f)] = np.frombuffer(b"".join([xxhash.xxh3_128_digest(line[a:z]) for a, z in spans]), dtype="<i8").reshape(-1, 2)
    return out


def read_again(docs: DataFrame, wanted: DataFrame, held: str) -> DataFrame:
    """docs joined to the rows of wanted (doc_id and the array held) by doc_id; broadcast where its bytes are few, else in a merge."""
    size = wanted.agg(F.sum(F.size(held) * 8 + 48)).first()[0] or 0
    return docs.join(F.broadcast(wanted) if size <= BROADCAST_BYTES else wanted.hint("merge"), "doc_id")


def signatures(docs: DataFrame, window: int = 50) -> DataFrame:
    """One row per row of docs: (doc_id, n_words, sha, marks, loose, first), first the least doc_id with the same words."""
    rows = stored(id_and_text(docs).mapInArrow(_signatures(window), "doc_id long, n_words long, sha string, marks array<long>, loose boolean"), "signatures")
    first = stored(rows.filter("doc_id is not null").groupBy("sha").agg(F.min("doc_id").alias("first")), "first")
    return stored(rows.join(first, "sha", "left"), "signatures")


def repeated_spans(docs: DataFrame, sigs: DataFrame, window: int = 50) -> DataFrame:
    """(doc_id, starts): positions of windows whose words also start in an earlier document; copies (first < doc_id) left out."""
    text = id_and_text(docs)
    originals = sigs.filter((F.col("first") == F.col("doc_id")) & (F.col("n_words") >= window))
    held = originals.select(F.explode("marks").alias("mark"), "doc_id")
    shared = held.groupBy("mark").agg(F.min("doc_id").alias("a"), F.max("doc_id").alias("z")).filter("a < z").select("mark")
    shared = stored(shared, "shared")  # on its own, so that the join's hot marks can be split
    # A document has few marks (about one for 20 words), so their array is bounded by its text.
    hits = held.join(shared, "mark").groupBy("doc_id").agg(F.collect_set("mark").alias("shared"))
    loose = originals.filter("loose").select("doc_id", F.array().cast("array<long>").alias("shared"))
    again = stored(hits.unionByName(loose).groupBy("doc_id").agg(F.flatten(F.collect_list("shared")).alias("shared")), "again")
    found = read_again(text, again, "shared").mapInArrow(lean(_windows(window)), "h1 long, h2 long, doc_id long, at int")
    least = found.groupBy("h1", "h2").agg(F.min("doc_id").alias("a"), F.max("doc_id").alias("z")).filter("a < z").select("h1", "h2", "a")
    least = stored(least, "least")
    return found.join(least, ["h1", "h2"]).filter("doc_id > a").groupBy("doc_id").agg(F.collect_set("at").alias("starts"))


def _covered(n: int, starts: np.ndarray, window: int) -> np.ndarray:
    step = np.zeros(n + 1, dtype=np.int64)
    starts = starts[starts + window <= n]
    np.add.at(step, starts, 1)
    np.add.at(step, starts + window, -1)
    return np.cumsum(step)[:n] > 0


def _kept(window: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches):
            ids, gone, kept, was = batch.column("doc_id").to_pylist(), [], [], []
            for raw, starts in zip(raw_texts(batch.column("text")), batch.column("starts").to_pylist()):
                words = raw.split()
                cut = _covered(len(words), np.array(starts or [], dtype=np.int64), window)
                gone.append(int(cut.sum()))
                kept.append(b" ".join(w for w, c in zip(words, cut) if not c).decode("utf-8"))
                was.append(digest(words))
            yield pa.RecordBatch.from_pydict({"doc_id": pa.array(ids, pa.int64()), "sha": was, "n_removed": pa.array(gone, pa.int64()), "kept": pa.array(kept, pa.string())})

    return run


def without_repeats(docs: DataFrame, window: int = 50) -> DataFrame:
    """(doc_id, n_words, n_removed, sha, kept): kept is the text left, words joined by one space; null where nothing went.

    sha is the digest of all words, which is the digest of what is kept where nothing went.
    """
    sigs = signatures(docs, window)
    spans = stored(repeated_spans(docs, sigs, window), "spans")
    cut = read_again(id_and_text(docs), spans, "starts").mapInArrow(lean(_kept(window)), "doc_id long, sha string, n_removed long, kept string").dropDuplicates(["doc_id", "sha"])
    whole_copy = (F.col("first") < F.col("doc_id")) & (F.col("n_words") >= window)
    return sigs.select("doc_id", "n_words", "sha", "first").join(cut, ["doc_id", "sha"], "left").select(
        "doc_id",
        "n_words",
        F.when(whole_copy, F.col("n_words")).otherwise(F.coalesce("n_removed", F.lit(0))).cast("long").alias("n_removed"),
        "sha",
        F.when(whole_copy, F.lit("")).otherwise(F.col("kept")).alias("kept"),
    )

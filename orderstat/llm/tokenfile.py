"""Token-ID output: documents in ascending doc_id order, coded by static range asymmetric numerals (rans.py).

Documents are dealt by ranges of doc_id and sorted within a range. Each task tokenizes its documents once and gathers whole
documents to segments of about SEGMENT tokens; a segment has one frequency table, counted from all its tokens, and blocks
that decode independently. Segments are rows of a Parquet folder written by Spark's committer, so a lost executor costs a
task and no partial file is read.

A row: part and segment (their order is that of the documents), start (tokens before it in its part), the table, and for
each block its documents, their token counts, lanes, stream, checkpoints and crc32 of stream and of ids.

Cases: a null or empty text gives the end id alone; null ids sort first; rows that repeat a doc_id follow each other in no
set order; other columns are ignored; an empty table gives files without rows. A document is never split, so a very
long text makes a longer block.
"""

from __future__ import annotations

import re
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from orderstat.llm.common import held_for_stage, id_and_text, lean, pieces, raw_texts, shared_dir
from orderstat.llm.rans import Coder, Table, crc
from orderstat.llm.tokens import byte_letters, load

SEGMENT, BLOCK = 4_000_000, 500_000
#: Words kept in each of two generations, by worker, about 150 bytes each: a word not kept costs its split and merges.
WORDS_KEPT = 400_000
_BLOCK = "struct<doc_ids:array<long>,counts:array<long>,n:long,lanes:int,stream:binary,checkpoints:binary,stream_crc:long,ids_crc:long>"
SCHEMA = f"part int, segment int, start long, n_tokens long, freq_table binary, blocks array<{_BLOCK}>"


#: Fixed value: the public pattern by which this vocabulary's pre-tokenizer splits normalised text.
PIECES = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
#: Words of these characters are normalised by lower-casing alone; others go through the library's own normaliser.
PLAIN = re.compile("[\x21-\x7e\xa1-\u017f]+")


MARKS = b".,;:!?"


def _packed(ids: list[int]) -> bytes:
    return struct.pack(f"<{len(ids)}I", *ids)


class Recent(dict):
    """A dict of two generations: when it is full, what was not used since the last time goes."""

    def __init__(self, make, most: int):
        super().__init__()
        self.make, self.most, self.old = make, most, {}

    def __missing__(self, key):
        if len(self) >= self.most:
            self.old = dict(self)
            self.clear()
        found = self.old.get(key)
        found = self[key] = self.make(key) if found is None else found
        return found


class WordIds:
    """Ids of texts as bytes. White space parts words in this vocabulary's tokenizer, so a word's ids do not depend on its neighbours.

    Words and the pieces within them are kept alike; the library's model merges a piece it has not met lately, and its whole
    pipeline encodes words of characters that PLAIN leaves out and texts with an added token's string.
    """

    def __init__(self, path: str, most: int | None = None):
        self.tokenizer, self.letters, self.pattern = load(path), byte_letters(), regex.compile(PIECES)
        self.added = [a.content.encode() for a in self.tokenizer.get_added_tokens_decoder().values()]
        self.words = Recent(self._word, most or WORDS_KEPT)

    def _merged(self, letters: str) -> bytes:
        return _packed([t.id for t in self.tokenizer.model.tokenize(letters)])

    def _word(self, low: bytes) -> bytes:
        if low.isalpha():  # a-z alone: one piece, whose letters stand for themselves
            return self._merged(low.decode())
        if low[-1] in MARKS and low[:-1].isalpha():
            return self.words[low[:-1]] + self.words[low[-1:]]
        text = low.decode()
        if not PLAIN.fullmatch(text):
            return self._whole(low)
        text = text.lower()
        parts = self.pattern.findall(text)
        if parts == [text]:
            return self._merged("".join(map(self.letters.__getitem__, text.encode())))
        return b"".join([self.words[p.encode()] for p in parts])

    def _whole(self, raw: bytes) -> bytes:
        return _packed(self.tokenizer.encode(raw.decode(), add_special_tokens=False).ids)

    def ids(self, raw: bytes) -> bytes:
        low = raw.lower()  # of A-Z alone: the tokenizer lower-cases all, so nothing changes and fewer words differ
        if any(a in low for a in self.added):
            return self._whole(raw)
        return b"".join(map(self.words.__getitem__, low.split()))


def pack_segment(docs: list[tuple[int | None, np.ndarray]], block: int = BLOCK) -> tuple[bytes, list[dict]]:
    counts: np.ndarray = np.zeros(1, dtype=np.int64)
    for k in range(0, len(docs), 4096):
        more = np.bincount(np.concatenate([ids for _, ids in docs[k : k + 4096]]))
        counts, more = (counts, more) if len(counts) >= len(more) else (more, counts)
        counts = counts.copy()
        counts[: len(more)] += more
    table = Table.of(counts)
    coder, blocks, held, size = Coder(table), [], [], 0
    for k, (doc_id, ids) in enumerate(docs):
        held.append((doc_id, ids))
        size += len(ids)
        if size >= block or k == len(docs) - 1:
            every = np.concatenate([i for _, i in held])
            lanes, stream, checkpoints = coder.encode(every)
            blocks.append({"doc_ids": [d for d, _ in held], "counts": [len(i) for _, i in held], "n": len(every), "lanes": lanes, "stream": stream, "checkpoints": checkpoints, "stream_crc": zlib.crc32(stream), "ids_crc": crc(every)})
            held, size = [], 0
    return table.pack(), blocks


def _writer(path: str, end_id: int, most: int, block_size: int):
    block = pa.struct([("doc_ids", pa.list_(pa.int64())), ("counts", pa.list_(pa.int64())), ("n", pa.int64()), ("lanes", pa.int32()), ("stream", pa.binary()), ("checkpoints", pa.binary()), ("stream_crc", pa.int64()), ("ids_crc", pa.int64())])
    schema = pa.schema([("part", pa.int32()), ("segment", pa.int32()), ("start", pa.int64()), ("n_tokens", pa.int64()), ("freq_table", pa.binary()), ("blocks", pa.list_(block))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, end = held_for_stage(("ids", path), lambda: WordIds(path)), np.array([end_id], dtype="<u4").tobytes()
        part, segment, start, held, size = TaskContext.get().partitionId(), 0, 0, [], 0

        def row() -> pa.RecordBatch:
            table, blocks = pack_segment(held, block_size)
            return pa.RecordBatch.from_pylist([{"part": part, "segment": segment, "start": start, "n_tokens": size, "freq_table": table, "blocks": blocks}], schema=schema)

        for batch in pieces(batches):
            for doc_id, raw in zip(batch.column("doc_id").to_pylist(), raw_texts(batch.column("text"))):
                ids = np.frombuffer(words.ids(raw) + end, dtype="<u4")
                held.append((doc_id, ids))
                size += len(ids)
                if size >= most:
                    yield row()
                    segment, start, held, size = segment + 1, start + size, [], 0
        if held:
            yield row()

    return lean(run)


def write(docs: DataFrame, path: str, tokenizer: str, end_id: int, segment: int = SEGMENT, block: int = BLOCK) -> None:
    """Write the token files of docs to the folder path, in segments and blocks of about so many tokens."""
    dealt = id_and_text(docs).repartitionByRange("doc_id").sortWithinPartitions("doc_id")
    dealt.mapInArrow(_writer(tokenizer, end_id, segment, block), SCHEMA).write.parquet(path)


def _reader(with_ids: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                row = batch.slice(k, 1)
                coder, at = Coder(Table.unpack(row.column("freq_table")[0].as_py())), row.column("start")[0].as_py()
                part = row.column("part")[0].as_py()
                for b in row.column("blocks")[0]:
                    stream, n = b["stream"].as_py(), b["n"].as_py()
                    if zlib.crc32(stream) != b["stream_crc"].as_py():
                        raise ValueError("a block's stream does not match its checksum")
                    ids = coder.decode(n, b["lanes"].as_py(), stream, b["checkpoints"].as_py())
                    if crc(ids) != b["ids_crc"].as_py():
                        raise ValueError("a block's ids do not match their checksum")
                    doc_ids, counts = b["doc_ids"].as_py(), b["counts"].as_py()
                    edges = np.concatenate([[0], np.cumsum(counts)]).astype(np.int64)
                    out = {"part": pa.array([part] * len(counts), pa.int32()), "doc_id": pa.array(doc_ids, pa.int64()), "at": pa.array(at + edges[:-1], pa.int64()), "n_tokens": pa.array(counts, pa.int64())}
                    if with_ids:
                        out["ids"] = pa.array([ids[a:z].astype(np.int32) for a, z in zip(edges, edges[1:])], pa.list_(pa.int32()))
                    else:
                        out["ids_crc32"] = pa.array([crc(ids[a:z]) for a, z in zip(edges, edges[1:])], pa.int64())
                    at += n
                    yield pa.RecordBatch.from_pydict(out)

    return lean(run)


def read(spark, path: str, with_ids: bool = False) -> DataFrame:
    """(doc_id, start, n_tokens, ids or ids_crc32) from the files, in no set order; start counts all tokens before the document."""
    rows = spark.read.schema(SCHEMA).parquet(path)
    sizes = rows.groupBy("part").agg(F.sum("n_tokens").alias("n")).orderBy("part").collect()  # a row for each task of the writer
    before, base = 0, []
    for r in sizes:
        base.append((r["part"], before))
        before += r["n"]
    bases = spark.createDataFrame(base, "part int, base long")
    last = "ids array<int>" if with_ids else "ids_crc32 long"
    found = rows.mapInArrow(_reader(with_ids), f"part int, doc_id long, at long, n_tokens long, {last}")
    return found.join(F.broadcast(bases), "part").select("doc_id", (F.col("base") + F.col("at")).alias("start"), "n_tokens", last.split()[0])


def write_and_read(docs: DataFrame, tokenizer: str, end_id: int = 1) -> DataFrame:
    """Write the files to a new folder among the shared ones and read them back."""
    import uuid

    path = f"{shared_dir(docs.sparkSession)}/tokens-{uuid.uuid4().hex}"
    write(docs, path, tokenizer, end_id)
    return read(docs.sparkSession, path)

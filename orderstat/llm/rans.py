"""Static range asymmetric numeral coding of token ids in interleaved lanes, on arrays.

A block's tokens go round its lanes; all lanes share one stream of 32-bit words. The frequency table is shared by the blocks
of a segment. Checkpoints hold the states of all lanes and the place in the stream, so that a decoder may start there.
"""

from __future__ import annotations

import zlib
from dataclasses import dataclass

import numpy as np

BITS = 20
TOTAL = 1 << BITS
LOW = np.uint64(1 << 31)
LANES, STEPS_A_CHECKPOINT = 2048, 128


@dataclass
class Table:
    """Symbols that occur, with whole frequencies of sum TOTAL."""

    symbols: np.ndarray
    freq: np.ndarray

    @staticmethod
    def of(counts: np.ndarray) -> Table:
        symbols = np.flatnonzero(counts)
        if len(symbols) > TOTAL // 2:
            raise ValueError("too many symbols for the table")
        share = counts[symbols].astype(np.float64)
        freq = np.maximum(1, np.floor(share * (TOTAL - len(symbols)) / max(share.sum(), 1))).astype(np.int64)
        if len(freq):
            freq[np.argmax(freq)] += TOTAL - freq.sum()
        return Table(symbols.astype(np.uint32), freq)

    def pack(self) -> bytes:
        gaps = np.diff(self.symbols.astype(np.int64), prepend=0).astype("<u4")
        return zlib.compress(np.concatenate([gaps, self.freq.astype("<u4")]).tobytes(), 6)

    @staticmethod
    def unpack(raw: bytes) -> Table:
        both = np.frombuffer(zlib.decompress(raw), dtype="<u4").astype(np.int64)
        n = len(both) // 2
        return Table(np.cumsum(both[:n]).astype(np.uint32), both[n:])

    def starts(self) -> np.ndarray:
        return np.cumsum(self.freq) - self.freq


class Coder:
    def __init__(self, table: Table):
        self.table = table
        self.freq, self.start = table.freq.astype(np.uint64), table.starts().astype(np.uint64)
        self.slots: np.ndarray | None = None
        self.rank = np.zeros(int(table.symbols[-1]) + 1 if len(table.symbols) else 1, dtype=np.int32)
        self.rank[table.symbols] = np.arange(len(table.symbols))

    def encode(self, ids: np.ndarray) -> tuple[int, bytes, bytes]:
        """(lanes, stream, checkpoints) of one block; ids must occur in the table."""
        n = len(ids)
        lanes = int(min(LANES, max(1, n // 64)))
        rank = self.rank[ids]
        freq, start = self.freq[rank], self.start[rank]
        steps = -(-n // lanes)
        x = np.full(lanes, LOW, dtype=np.uint64)
        words: list[np.ndarray] = []
        marks: list[tuple[int, np.ndarray]] = []
        for t in range(steps - 1, -1, -1):
            a, z = t * lanes, min((t + 1) * lanes, n)
            f, y = freq[a:z], x[: z - a]
            over = y >= (f << np.uint64(63 - BITS))
            words.append(y[over].astype(np.uint32))
            y = np.where(over, y >> np.uint64(32), y)
            q = y // f
            x[: z - a] = (q << np.uint64(BITS)) + (y - q * f) + start[a:z]
            if t % STEPS_A_CHECKPOINT == 0:
                marks.append((t, x.copy()))
        words.reverse()
        ends = np.concatenate([[0], np.cumsum([len(w) for w in words])]).astype(np.uint64)
        stream = np.concatenate(words) if words else np.zeros(0, dtype=np.uint32)
        kept = [np.concatenate([ends[t : t + 1], s]) for t, s in reversed(marks)]
        return lanes, stream.astype("<u4").tobytes(), (np.concatenate(kept).astype("<u8").tobytes() if kept else b"")

    def decode(self, n: int, lanes: int, stream: bytes, checkpoints: bytes, first: int = 0, last: int | None = None) -> np.ndarray:
        """Tokens between two checkpoints (numbers first and last of the block), all by default."""
        if self.slots is None:
            self.slots = np.repeat(np.arange(len(self.freq)), self.table.freq)
        steps = -(-n // lanes)
        begin = first * STEPS_A_CHECKPOINT
        end = steps if last is None else min(steps, last * STEPS_A_CHECKPOINT)
        if begin >= end:
            return np.zeros(0, dtype=np.uint32)
        words = np.frombuffer(stream, dtype="<u4")
        state = np.frombuffer(checkpoints, dtype="<u8").reshape(-1, lanes + 1)[first]
        at, x = int(state[0]), state[1:].astype(np.uint64)
        out = np.empty(min(end * lanes, n) - begin * lanes, dtype=np.int64)
        for t in range(begin, end):
            a, z = t * lanes, min((t + 1) * lanes, n)
            y = x[: z - a]
            slot = y & np.uint64(TOTAL - 1)
            rank = self.slots[slot.astype(np.int64)]
            y = self.freq[rank] * (y >> np.uint64(BITS)) + slot - self.start[rank]
            low = np.flatnonzero(y < LOW)
            y[low] = (y[low] << np.uint64(32)) | words[at : at + len(low)]
            at += len(low)
            x[: z - a] = y
            out[a - begin * lanes : z - begin * lanes] = rank
        return self.table.symbols[out]


def crc(ids: np.ndarray) -> int:
    """Unsigned crc32 of ids as little-endian unsigned 32-bit integers."""
    return zlib.crc32(np.ascontiguousarray(ids, dtype="<u4").tobytes())

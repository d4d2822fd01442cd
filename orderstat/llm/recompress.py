"""Recompression of word sequences on arrays: rounds that name runs, then pairs, with names taken from content.

A name is a fingerprint of what it stands for, so every task of the cluster gives equal word sequences equal names and no
round needs a shuffle. Next to each symbol the parse keeps the span of words that alone decides that the symbol stands
there. A symbol whose span lies inside a window of words therefore stands at the same place in every copy of the window,
whatever surrounds it.
"""

from __future__ import annotations

import numpy as np

FAR = 1 << 40
_A, _B = np.array([0x9E3779B97F4A7C15, 0xBF58476D1CE4E5B9], dtype=np.uint64)
_S32, _S29 = np.uint64(32), np.uint64(29)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit values."""
    x = (x ^ (x >> _S32)) * _A
    x = (x ^ (x >> _S29)) * _B
    return x ^ (x >> _S32)


def salt(k: int) -> np.uint64:
    return np.uint64((k * 0x9E3779B97F4A7C15 + 0x1234567) & 0xFFFFFFFFFFFFFFFF)


class Parse:
    """Symbols of one level: names, word extents [start, end), deciding spans [lo, hi), and walls between documents."""

    def __init__(self, words: np.ndarray, wall: np.ndarray):
        self.words, n = words, len(words)
        self.name, self.wall = words.copy(), wall.copy()
        self.start = np.arange(n)
        self.end = self.start + 1
        self.lo, self.hi = self.start.copy(), self.end.copy()
        self._fence()

    def _fence(self) -> None:
        self.lo[self.wall] = -FAR
        self.hi[self.wall] = FAR

    def runs(self) -> None:
        """Name each maximal run of one symbol."""
        name, wall = self.name, self.wall
        fresh = np.ones(len(name), dtype=bool)
        fresh[1:] = (name[1:] != name[:-1]) | wall[1:] | wall[:-1]
        first = np.flatnonzero(fresh)
        last = np.append(first[1:], len(name)) - 1
        times = last - first + 1
        start, end = self.start[first], self.end[last]
        lo, hi = np.minimum.reduceat(self.lo, first), np.maximum.reduceat(self.hi, first)
        # That the run stops here is decided by the next word where that differs, else by the whole next symbol.
        w, most = self.words, len(self.words) - 1
        differs = w[np.maximum(start - 1, 0)] != w[end - 1]
        lo = np.minimum(lo, np.where(differs, start - 1, self.lo[np.maximum(first - 1, 0)]))
        differs = w[np.minimum(end, most)] != w[start]
        hi = np.maximum(hi, np.where(differs, end + 1, self.hi[np.minimum(last + 1, len(name) - 1)]))
        self.name = np.where(times > 1, mix(name[first] + times.astype(np.uint64) * _B), name[first])
        self.wall, self.start, self.end, self.lo, self.hi = wall[first], start, end, lo, hi
        self._fence()

    def pairs(self, turn: int) -> None:
        """Split all names into two sides by their fingerprint and name each adjacent left-right pair."""
        name, wall = self.name, self.wall
        side = ((mix(name + salt(turn)) >> np.uint64(40)) & np.uint64(1)).astype(bool)
        left, right = ~side & ~wall, side & ~wall
        joined = left[:-1] & right[1:]
        head, tail = np.append(joined, False), np.insert(joined, 0, False)
        lo, hi, end = self.lo.copy(), self.hi.copy(), self.end.copy()
        at = np.flatnonzero(right & ~tail)
        lo[at] = np.minimum(lo[at], self.lo[np.maximum(at - 1, 0)])
        at = np.flatnonzero(left & ~head)
        hi[at] = np.maximum(hi[at], self.hi[np.minimum(at + 1, len(name) - 1)])
        at = np.flatnonzero(head)
        new = name.copy()
        new[at] = mix(name[at] * _B + mix(name[at + 1] + _A))
        end[at] = self.end[at + 1]
        lo[at], hi[at] = np.minimum(lo[at], lo[at + 1]), np.maximum(hi[at], hi[at + 1])
        keep = ~tail
        self.name, self.wall, self.start, self.end, self.lo, self.hi = new[keep], wall[keep], self.start[keep], end[keep], lo[keep], hi[keep]


def parse(words: np.ndarray, wall: np.ndarray, rounds: int) -> Parse:
    p = Parse(words, wall)
    for turn in range(rounds):
        p.runs()
        p.pairs(turn + 1)
    p.runs()
    return p


def lay_out(docs: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Word fingerprints of all documents in one array with walls around each; also where each document starts."""
    sizes = np.array([len(d) for d in docs], dtype=np.int64)
    starts = 1 + np.concatenate([[0], np.cumsum(sizes + 1)[:-1]]) if len(docs) else np.zeros(0, dtype=np.int64)
    words = np.zeros(int(sizes.sum()) + len(docs) + 1, dtype=np.uint64)
    wall = np.zeros(len(words), dtype=bool)
    wall[0] = True
    for s, d in zip(starts, docs):
        words[s : s + len(d)] = d
        wall[s + len(d)] = True
    return words, wall, starts


def whole_windows(wall: np.ndarray, window: int) -> np.ndarray:
    """For each word position, whether a window that starts there lies in one document."""
    sums = np.concatenate([[0], np.cumsum(wall)])
    ok = np.zeros(len(wall), dtype=bool)
    if len(wall) >= window:
        ok[: len(wall) - window + 1] = sums[window:] == sums[: len(sums) - window]
    return ok


def window_marks(p: Parse, n: int, window: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Each window's mark: the least symbol that the window alone decides. Also whether it has one, and which symbols are marks."""
    at = np.flatnonzero(~p.wall & (p.hi - p.lo <= window))
    first, count = np.maximum(p.hi[at] - window, 0), 0
    count = np.minimum(p.lo[at], n - 1) - first + 1
    which = np.repeat(np.arange(len(at)), count)
    where = np.arange(len(which)) - np.repeat(np.cumsum(count) - count, count) + np.repeat(first, count)
    rank = mix(p.name[at] + salt(977))
    mark = np.full(n, np.iinfo(np.uint64).max, dtype=np.uint64)
    has = np.zeros(n, dtype=bool)
    has[where] = True
    np.minimum.at(mark, where, rank[which])
    used = np.zeros(len(at), dtype=bool)
    used[which[mark[where] == rank[which]]] = True
    return mark, has, at[used]


def window_names(words: np.ndarray, window: int, base: int, turn: int) -> np.ndarray:
    """Polynomial fingerprint of the window that starts at each position (the last window - 1 positions wrap to no use)."""
    w = mix(words + salt(turn))
    n = len(w)
    b = np.full(n + 1, base | 1, dtype=np.uint64)
    b[0] = 1
    power = np.multiply.accumulate(b)
    inverse = np.full(n + 1, pow(base | 1, -1, 1 << 64), dtype=np.uint64)
    inverse[0] = 1
    inverse = np.multiply.accumulate(inverse)
    sums = np.concatenate([np.zeros(1, dtype=np.uint64), np.cumsum(w * power[:n], dtype=np.uint64)])
    out = np.zeros(n, dtype=np.uint64)
    if n >= window:
        out[: n - window + 1] = (sums[window:] - sums[: n - window + 1]) * inverse[: n - window + 1]
    return mix(out)

"""Vantage-point trees over 64-bit fingerprints under Hamming distance.

The upper levels are built on the driver from a bounded sample and shipped to every task; they send each fingerprint to shards.
Over all 64 bits a fingerprint also visits, as a guest, every shard that the triangle inequality cannot exclude, and guests
multiply by the level: unrelated fingerprints lie around 32 bits apart, so a band of two bits holds a good part of them all.
The bits are therefore dealt to near + 1 blocks, and a tree stands over the distances within each block. Fingerprints within
near bits agree on some block, where their distance is 0 and the triangle bound excludes every other branch: they share
a shard of that tree, and a fingerprint is in near + 1 shards at any depth. Within a shard a tree over all bits goes on down to small
blocks, with guests across the boundaries.
"""

from __future__ import annotations

import numpy as np

from orderstat.llm.common import local_components

BLOCK = 192


def _halving(d: np.ndarray) -> int:
    """The radius with nearest to half of the distances within it."""
    within = np.cumsum(np.bincount(d, minlength=65))
    return int(np.abs(2 * within - len(d)).argmin())


def blocks(near: int) -> list[np.uint64]:
    """Masks of near + 1 blocks of bits, every (near + 1)-th bit each, so that a fingerprint's parts are alike in all."""
    return [np.uint64(sum(1 << b for b in range(j, 64, near + 1))) for j in range(near + 1)]


class Forest:
    """A tree for each block of bits, whose shards are numbered one after the other."""

    def __init__(self, sample: np.ndarray, depth: int, near: int):
        self.depth, self.masks = depth, blocks(near) if depth else [~np.uint64(0)]
        self.trees = [Router(np.unique(sample & mask), depth, 0, mask=mask) for mask in self.masks]

    def route(self, prints: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(shard, index into prints), a member of each."""
        found = [tree.route(prints & mask)[:2] for tree, mask in zip(self.trees, self.masks)]
        return np.concatenate([s + (j << self.depth) for j, (s, _) in enumerate(found)]), np.concatenate([at for _, at in found])


class Router:
    """Heap-ordered vantage points and radii; node k has children 2k+1 (within the radius) and 2k+2."""

    def __init__(self, sample: np.ndarray, depth: int, near: int, seed: int = 7, mask: np.uint64 = ~np.uint64(0)):
        rng = np.random.default_rng(seed)
        self.depth, self.near = depth, near
        self.point = rng.integers(0, 1 << 64, size=(1 << depth) - 1, dtype=np.uint64) & mask
        middle = (int(np.bitwise_count(mask)) - 1) // 2
        self.radius = np.full(len(self.point), middle, dtype=np.int64)
        parts = [sample]
        for k in range(len(self.point)):
            part = parts[k] if k < len(parts) else np.zeros(0, dtype=np.uint64)
            if len(part):
                self.point[k] = part[rng.integers(len(part))]
                d = np.bitwise_count(part ^ self.point[k])
                self.radius[k] = _halving(d) if len(part) >= 16 else middle
                parts += [part[d <= self.radius[k]], part[d > self.radius[k]]]
            else:
                parts += [part, part]

    def route(self, prints: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(shard, index into prints, whether a guest). A pair within reach meets in the shard where one is a member."""
        out: list[tuple[int, np.ndarray, np.ndarray]] = []
        todo = [(0, np.arange(len(prints)), np.zeros(len(prints), dtype=bool))]
        inner = len(self.point)
        while todo:
            k, at, guest = todo.pop()
            if not len(at):
                continue
            if k >= inner:
                out.append((k - inner, at, guest))
                continue
            d = np.bitwise_count(prints[at] ^ self.point[k]).astype(np.int64)
            inside, band_in, band_out = split(d, guest, int(self.radius[k]), self.near)
            todo.append((2 * k + 1, at[inside | band_in], guest[inside | band_in] | band_in[inside | band_in]))
            todo.append((2 * k + 2, at[~inside | band_out], guest[~inside | band_out]))
        if not out:
            return np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64), np.zeros(0, dtype=bool)
        return np.concatenate([np.full(len(a), s) for s, a, _ in out]), np.concatenate([a for _, a, _ in out]), np.concatenate([g for _, _, g in out])


def split(d: np.ndarray, guest: np.ndarray, radius: int, near: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Who goes inside, who besides visits inside from the band outside, and which guests inside also go outside.

    A pair of members that the radius parts meets inside, where the outer one is a guest. A guest follows its members, so
    it takes both ways in the band.
    """
    inside = d <= radius
    return inside, ~inside & (d <= radius + near), guest & inside & (d > radius - near)


def near_edges(members: np.ndarray, guests: np.ndarray, near: int) -> tuple[np.ndarray, np.ndarray]:
    """Edges (indices into members then guests) that connect what pairs within reach connect, at most one per vertex."""
    everything = np.concatenate([members, guests])
    n, is_guest = len(everything), np.arange(len(everything)) >= len(members)
    a_all, b_all = [], []
    rng = np.random.default_rng(5)
    todo = [(np.arange(n), 0)]
    while todo:
        at, level = todo.pop()
        guest = is_guest[at]
        own = at[~guest]
        if not len(own) or len(at) < 2:
            continue
        if len(own) > BLOCK and level < 48:
            v = everything[own[rng.integers(len(own))]]
            d = np.bitwise_count(everything[at] ^ v).astype(np.int64)
            r = int(np.median(d[~guest]))
            inside, band_in, band_out = split(d, guest, r, near)
            if 0 < (inside & ~guest).sum() < len(own):
                # A member that visits inside counts as a guest there: its index goes in as one.
                todo.append((at[~inside | band_out], level + 1))
                visit = band_in & ~guest
                if visit.any():
                    k = len(everything)
                    everything = np.concatenate([everything, everything[at[visit]]])
                    is_guest = np.concatenate([is_guest, np.ones(int(visit.sum()), dtype=bool)])
                    alias = np.arange(k, len(everything))
                    a_all.append(at[visit]), b_all.append(alias)
                    todo.append((np.concatenate([at[inside | (band_in & guest)], alias]), level + 1))
                else:
                    todo.append((at[inside | band_in], level + 1))
                continue
        for k in range(0, len(own), BLOCK):
            rows = own[k : k + BLOCK]
            for j in range(0, len(at), 1 << 14):
                cols = at[j : j + (1 << 14)]
                i, c = np.nonzero(np.bitwise_count(everything[rows][:, None] ^ everything[cols][None, :]) <= near)
                differ = rows[i] != cols[c]
                if differ.any():
                    ends, inv = np.unique(np.concatenate([rows[i[differ]], cols[c[differ]]]), return_inverse=True)
                    half = int(differ.sum())
                    low = local_components(len(ends), inv[:half], inv[half:])
                    move = low != np.arange(len(ends))
                    a_all.append(ends[move]), b_all.append(ends[low[move]])
    if not a_all:
        return np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64)
    a, b = np.concatenate(a_all), np.concatenate(b_all)
    label = local_components(len(everything), a, b)
    # Aliases stand for members of the first n; every group's least index is below n, for an alias never comes first.
    move = np.flatnonzero(label[:n] != np.arange(n))
    return move, label[move]

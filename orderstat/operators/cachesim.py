"""An ideal-cache stand-in: LRU over blocks, for counting block transfers of the kernel's address traces."""

from __future__ import annotations

from collections import OrderedDict


class BlockCache:
    """Memory of m cells in blocks of b cells; counts loads of absent blocks."""

    def __init__(self, m: int, b: int):
        self.m, self.b, self.slots = m, b, max(1, m // b)
        self.held: OrderedDict[int, None] = OrderedDict()
        self.transfers = 0

    def touch(self, cell: int) -> None:
        block = cell // self.b
        if block in self.held:
            self.held.move_to_end(block)
            return
        self.transfers += 1
        self.held[block] = None
        if len(self.held) > self.slots:
            self.held.popitem(last=False)

    def scan(self, base: int, n: int) -> None:
        for block in range(base // self.b, (base + max(n, 1) - 1) // self.b + 1):
            self.touch(block * self.b)


def layout_plan(n: int, delta: int, d: float) -> dict[str, int]:
    """Cells to set aside for a partition: a tree for the most buckets there can be, then as many slots of twice the capacity."""
    k = max(1, 2 * n // delta)
    return {"buckets": k, "tree_cells": int(k ** ((d + 1) / 2)) + 1, "slot_cells": 2 * delta, "all_slots": 2 * delta * k}

"""The rank families over which methods are compared: from one rank to all ranks."""

from __future__ import annotations

from orderstat.sources import ranks as R

TAIL = R.Fractions("0.5", "0.9", "0.95", "0.99", "0.999", "0.9999")

FAMILIES: dict[str, R.Family] = {
    "median": R.Fractions("0.5"),
    "minimum": R.At(1),
    "maximum": R.top(1),
    "quartiles": R.even(4),
    "deciles": R.even(10),
    "percentiles": R.even(100),
    "permille": R.even(1000),
    "tail": TAIL,
    "top100": R.top(100),
    "middle": R.middle(100),
    "clusters": R.clusters(),
    "geometric": R.geometric(),
    "half_dense": R.half_dense(),
    "everything": R.everything(),
    "nothing": R.nothing(),
}


def spectrum(n: int) -> dict[int, R.Family]:
    """2^j - 1 even ranks for each j: the way from one selection to a sort."""
    return {j: R.even(1 << j) for j in range(1, max(n, 1).bit_length())}

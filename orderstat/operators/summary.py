"""Deterministic rank summaries: pivots at even ranks, or around given ranks, with a bounded rank error.

Numbers and times use the built-in sketch (error n / accuracy). Other types use a compacting summary in each task: sorted
blocks of BLOCK values; two blocks of one weight merge, and every second value stays with twice the weight. With L merges
deep the error is at most L / (2 BLOCK) of the rows. Counts of the buckets are exact whatever the pivots, so the error only
decides how even the buckets are.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

BLOCK = 2048
SKETCHED = (T.ByteType, T.ShortType, T.IntegerType, T.LongType, T.FloatType, T.DoubleType, T.DecimalType, T.DateType, T.TimestampType, T.TimestampNTZType, T.DayTimeIntervalType, T.YearMonthIntervalType)


def sketched(kind: T.DataType) -> bool:
    return isinstance(kind, SKETCHED)


def orderable(x) -> tuple:
    """A Python value in Spark's order: nulls first, structs and arrays by their members."""
    if x is None:
        return (0,)
    if isinstance(x, dict):
        return (1, *(orderable(v) for v in x.values()))
    if isinstance(x, (list, tuple)):
        return (1, *(orderable(v) for v in x))
    return (2, x.encode() if isinstance(x, str) else (x != x, 0.0 if x != x else x) if isinstance(x, float) else x)


class Compactor:
    """Sorted blocks by weight; holds at most two blocks of each weight."""

    def __init__(self, block: int = BLOCK):
        self.block, self.fresh, self.levels = block, [], {}
        self.turn: dict[int, int] = {}

    def add(self, values: list) -> None:
        self.fresh += values
        while len(self.fresh) >= self.block:
            self._place(0, sorted(self.fresh[: self.block], key=orderable))
            del self.fresh[: self.block]

    def _place(self, level: int, block: list) -> None:
        while level in self.levels:
            both = sorted(self.levels.pop(level) + block, key=orderable)
            self.turn[level] = 1 - self.turn.get(level, 0)  # the kept half alternates, so errors do not all lean one way
            block, level = both[self.turn[level] :: 2], level + 1
        self.levels[level] = block

    def weighted(self) -> list[tuple]:
        return [(v, 1) for v in self.fresh] + [(v, 1 << level) for level, block in self.levels.items() for v in block]


def _summarise(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    subs: dict[int, Compactor] = {}
    kind = None
    for batch in batches:
        kind = batch.schema.field("key").type
        by: dict[int, list] = {}
        for s, v in zip(batch.column("sub").to_pylist(), batch.column("key").to_pylist()):
            by.setdefault(s, []).append(v)
        for s, values in by.items():
            subs.setdefault(s, Compactor()).add(values)
    for s, c in subs.items():
        got = c.weighted()
        yield pa.RecordBatch.from_pydict({"sub": pa.array([s] * len(got), pa.int64()), "key": pa.array([v for v, _ in got], kind), "w": pa.array([w for _, w in got], pa.int64())})


def even_pivots(work: DataFrame, parts: int, accuracy: int, own: bool = False) -> DataFrame:
    """(sub, pivots): about parts sorted distinct values of each subproblem at even ranks.

    own asks for the compacting summary also where the built-in sketch serves: the sketch works on doubles, so among whole
    numbers beyond 2^53 its values may not be elements. The compacting summary's always are.
    """
    kind = work.schema["key"].dataType
    if sketched(kind) and not own:
        at = F.array([F.lit(k / parts) for k in range(1, parts)])
        return work.groupBy("sub").agg(F.array_sort(F.array_distinct(F.percentile_approx("key", at, accuracy))).alias("pivots"))
    return _even_from_points(work.select("sub", "key").mapInArrow(_summarise, T.StructType([T.StructField("sub", T.LongType()), T.StructField("key", kind), T.StructField("w", T.LongType())])), parts)


def _even_from_points(points: DataFrame, parts: int) -> DataFrame:
    merged = points.groupBy("sub", "key").agg(F.sum("w").alias("w"))
    order = Window.partitionBy("sub").orderBy("key").rowsBetween(Window.unboundedPreceding, 0)
    placed = merged.withColumn("cum", F.sum("w").over(order)).withColumn("all", F.sum("w").over(Window.partitionBy("sub")))
    cut = placed.withColumn("part", F.expr(f"((cum - w) * {parts}) div all")).groupBy("sub", "part").agg(F.min("key").alias("key"))
    found = cut.groupBy("sub").agg(F.array_sort(F.array_distinct(F.collect_list("key"))).alias("pivots"))
    none = F.array().cast(T.ArrayType(points.schema["key"].dataType))
    return points.select("sub").distinct().join(found, "sub", "left").withColumn("pivots", F.coalesce("pivots", none))


def bracket_pivots(work: DataFrame, ranks: list[int], n: int, accuracy: int) -> DataFrame:
    """(sub, pivots) for one subproblem: for each rank the values whose rank intervals enclose it."""
    e = max(1, 2 * n // accuracy)
    at = sorted({min(max((r + d) / n, 0.0), 1.0) for r in ranks for d in (-e, e)})
    asked = F.percentile_approx("key", F.array([F.lit(x) for x in at]), accuracy)
    return work.groupBy("sub").agg(F.array_sort(F.array_distinct(asked)).alias("pivots"))

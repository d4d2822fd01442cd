"""Rank lists as DataFrames of one LONG column rank: never a Python list of unbounded length."""

from __future__ import annotations

from collections.abc import Callable, Iterable
from fractions import Fraction

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: A rank list for a table of n elements: a function, or an object that also knows ranks by group.
Family = Callable[[SparkSession, int], DataFrame]


def of(spark: SparkSession, ranks: Iterable[int]) -> DataFrame:
    return spark.createDataFrame([(int(r),) for r in ranks], "rank long")


class At:
    """The same ranks for any table."""

    def __init__(self, *ranks: int):
        self.ranks = sorted(set(ranks))

    def __call__(self, spark: SparkSession, n: int) -> DataFrame:
        return of(spark, self.ranks)

    def grouped(self, groups: DataFrame) -> DataFrame:
        """groups has a column n; adds rank, a row for each rank that the group has."""
        return groups.withColumn("rank", F.explode(F.array([F.lit(r).cast("long") for r in self.ranks]))).filter("rank between 1 and n")


def span(lo: int, hi: int, step: int = 1) -> Family:
    return lambda spark, n: spark.range(lo, hi + 1, step).select(F.col("id").alias("rank"))


def everything() -> Family:
    return lambda spark, n: spark.range(1, n + 1).select(F.col("id").alias("rank"))


def fraction_rank(p: Fraction | str | int, n: int) -> int:
    """Rank max(1, ceil(p n)) in whole numbers."""
    f = Fraction(p)
    return max(1, -(-f.numerator * n // f.denominator))


class Fractions:
    """Ranks of fractions given as exact numbers: Fraction(1, 2) or "0.999"."""

    def __init__(self, *ps: Fraction | str):
        self.ps = [Fraction(p) for p in ps]

    def __call__(self, spark: SparkSession, n: int) -> DataFrame:
        return of(spark, sorted({fraction_rank(p, n) for p in self.ps}) if n else [])

    def grouped(self, groups: DataFrame) -> DataFrame:
        each = [F.greatest(F.lit(1), F.expr(f"cast((cast(n as decimal(38,0)) * {p.numerator} + {p.denominator - 1}) div {p.denominator} as bigint)")) for p in self.ps]
        return groups.withColumn("rank", F.explode(F.array_distinct(F.array(each))))


def even(parts: int) -> Family:
    """The parts - 1 ranks ceil(i n / parts)."""
    return lambda spark, n: spark.range(1, parts).select(F.greatest(F.lit(1), F.expr(f"(id * {n} + {parts - 1}) div {parts}")).alias("rank")).distinct()


def top(m: int) -> Family:
    return lambda spark, n: spark.range(max(1, n - m + 1), n + 1).select(F.col("id").alias("rank"))


def bottom(m: int) -> Family:
    return lambda spark, n: spark.range(1, min(m, n) + 1).select(F.col("id").alias("rank"))


def middle(share: int = 100) -> Family:
    """A dense window of n / share ranks from the middle on."""
    return lambda spark, n: spark.range(max(1, n // 2), max(1, n // 2) + n // share).select(F.col("id").alias("rank"))


def clusters(count: int = 9, size: int = 50, step: int = 3) -> Family:
    return lambda spark, n: spark.range(count * size).select(F.expr(f"(id div {size} + 1) * {n} div {count + 1} + {step} * (id % {size})").alias("rank")).filter(f"rank between 1 and {n}").distinct()


def geometric() -> Family:
    return lambda spark, n: of(spark, [1 << j for j in range(max(n, 0).bit_length())] if n else [])


def half_dense() -> Family:
    return lambda spark, n: spark.range(1, n // 2 + 2).select(F.col("id").alias("rank")).filter(f"rank <= {n}")


def nothing() -> Family:
    return lambda spark, n: of(spark, [])


def random(count: int, seed: int) -> Family:
    """Up to count distinct ranks by a seeded hash of the rank's number."""
    return lambda spark, n: spark.range(count).select((F.pmod(F.xxhash64(F.lit(seed), "id"), F.lit(max(n, 1))) + 1).alias("rank")).distinct().filter(f"rank <= {n}")


def from_column(df: DataFrame, col: str) -> Family:
    return lambda spark, n: df.select(F.col(col).cast("long").alias("rank")).filter(f"rank between 1 and {n}").distinct()


def listed(spec, n: int) -> list[int] | None:
    """The ranks of a short list, without a job; None for families and DataFrames."""
    if isinstance(spec, At):
        return list(spec.ranks)
    if isinstance(spec, Fractions):
        return sorted({fraction_rank(p, n) for p in spec.ps}) if n else []
    return sorted({int(r) for r in spec}) if isinstance(spec, (list, tuple, set, range)) else None


def resolve(spark: SparkSession, spec: Family | DataFrame | Iterable[int], n: int, on_invalid: str = "error") -> DataFrame:
    """Distinct ranks between 1 and n. Ranks outside raise an error, or are dropped with on_invalid="drop"."""
    if on_invalid not in ("error", "drop"):
        raise ValueError("on_invalid is \"error\" or \"drop\"")
    if callable(spec):
        found = spec(spark, n)
    elif isinstance(spec, DataFrame):
        found = spec.select(F.col(spec.columns[0]).cast("long").alias("rank"))
    else:
        found = of(spark, spec)
    good = F.col("rank").between(1, n)
    if on_invalid == "error" and not found.filter(F.col("rank").isNull() | ~good).isEmpty():
        raise ValueError(f"ranks must lie in 1..{n}")
    return found.filter(good).distinct()

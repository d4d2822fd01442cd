"""Gaps between ranks and the threshold that balances them."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Ranks up to which one window orders the whole list; longer lists are cut at range boundaries and stitched.
WINDOW_RANKS = 1_000_000
#: Gap sizes in a list, or how many gaps each size has.
Sizes = list[int] | dict[int, int]


def rank_gaps(ranks: DataFrame, n: int, window_ranks: int = WINDOW_RANKS) -> DataFrame:
    """(lo_rank, hi_rank, size) between neighbours of 0, the ranks and n + 1."""
    spark = ranks.sparkSession
    closing = ranks.select(F.col("rank").cast("long").alias("hi_rank")).unionByName(spark.range(n + 1, n + 2).select(F.col("id").alias("hi_rank")))
    if ranks.limit(window_ranks + 1).count() <= window_ranks:
        lo = F.lag("hi_rank", 1, 0).over(Window.orderBy("hi_rank"))
        return closing.withColumn("lo_rank", lo).select("lo_rank", "hi_rank", (F.col("hi_rank") - F.col("lo_rank")).alias("size"))
    # Stretches of the rank axis; the last rank of the stretches before is one row each.
    step = max(1, (n + 1) // max(1, ranks.sparkSession.sparkContext.defaultParallelism * 8))
    cut = closing.withColumn("stretch", F.expr(f"hi_rank div {step}L"))
    lasts = cut.groupBy("stretch").agg(F.max("hi_rank").alias("last"))
    before = lasts.withColumn("before", F.lag("last", 1, 0).over(Window.orderBy("stretch"))).select("stretch", "before")
    inside = cut.withColumn("prev", F.lag("hi_rank").over(Window.partitionBy("stretch").orderBy("hi_rank"))).join(F.broadcast(before), "stretch")
    lo = F.coalesce("prev", "before")
    return inside.select(lo.alias("lo_rank"), "hi_rank", (F.col("hi_rank") - lo).alias("size"))


def weighted_select(df: DataFrame, value: str, weight: str, target, group_by: list[str] | None = None) -> DataFrame:
    """The smallest value such that the weights of the values up to it sum to target at least, for each group.

    (groups,) value, cum_weight. Weights are not negative. Equal values are merged before anything is ordered, so this
    form serves values with few distinct ones; weighted_rank in operators.select serves the rest.
    """
    by = list(group_by or [])
    merged = df.filter(F.col(value).isNotNull()).groupBy(*by, value).agg(F.sum(weight).alias("w"))
    order = (Window.partitionBy(*by) if by else Window.partitionBy(F.lit(0))).orderBy(value).rowsBetween(Window.unboundedPreceding, 0)
    reached = merged.withColumn("cum_weight", F.sum("w").over(order)).filter(F.col("cum_weight") >= target)
    return reached.groupBy(*by).agg(F.min(F.struct(F.col(value), F.col("cum_weight"))).alias("m")).filter("m is not null").select(*by, F.col(f"m.{value}").alias(value), "m.cum_weight")


def gap_threshold(gaps: DataFrame, n: int) -> int | None:
    """The smallest gap size such that gaps up to it hold n / 2 + 1 elements at least; sizes have at most sqrt(2 n + 2) values."""
    found = weighted_select(gaps.select("size", (2 * F.col("size")).alias("twice")), "size", "twice", F.lit(n + 2)).first()
    return int(found["size"]) if found else None


def gap_mass(gaps: DataFrame, delta: int) -> DataFrame:
    """(below, upto, over): elements in gaps under, up to and from the threshold on."""
    mass = lambda c: F.coalesce(F.sum(F.when(c, F.col("size"))), F.lit(0)).cast("long")
    return gaps.agg(mass(F.col("size") < delta).alias("below"), mass(F.col("size") <= delta).alias("upto"), mass(F.col("size") >= delta).alias("over"))


def gap_sizes(ranks: list[int], n: int) -> list[int]:
    """The same for a short list: sizes of the gaps of distinct ranks in order."""
    edges = [0, *sorted(ranks), n + 1]
    return [b - a for a, b in zip(edges, edges[1:])]


def size_counts(gaps: DataFrame) -> dict[int, int]:
    """How many gaps each size has: sqrt(2 n + 2) sizes at most, however many ranks there are."""
    return {r["size"]: r["count"] for r in gaps.groupBy("size").count().orderBy("size").collect()}


def counted(sizes: Sizes) -> Iterable[tuple[int, int]]:
    return sizes.items() if isinstance(sizes, dict) else ((s, 1) for s in sizes)


def threshold_of(sizes: Sizes, n: int) -> int | None:
    upto = 0
    for size, count in sorted(counted(sizes)):
        upto += size * count
        if 2 * upto >= n + 2:
            return size
    return None

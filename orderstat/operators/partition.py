"""Multi-way partition with exact counts: pivots, bucket sizes, ranks of the pivots."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from orderstat.operators.distribute import bucketize
from orderstat.operators.summary import even_pivots
from orderstat.plans.policy import Settings


@dataclass
class Partition:
    """Of each subproblem: its pivots, and (bucket, n, lo_rank) of every bucket that has elements. Bounded by the pivots."""

    pivots: DataFrame
    values: dict[int, list]
    bounds: dict[int, list[tuple[int, int, int]]]

    @property
    def most(self) -> int:
        return max(map(len, self.values.values()), default=0)

    def open_sizes(self) -> list[int]:
        return [n for rows in self.bounds.values() for bucket, n, _ in rows if bucket % 2 == 0]

    def bounds_frame(self) -> DataFrame:
        """(sub, bucket, n, lo_rank, hi_rank)."""
        return self.pivots.sparkSession.createDataFrame([(s, b, n, lo, lo + n - 1) for s, rows in self.bounds.items() for b, n, lo in rows], "sub long, bucket int, n long, lo_rank long, hi_rank long")


def bucket_counts(work: DataFrame, pivots: DataFrame, most: int, how: str = "auto", values: dict[int, list] | None = None) -> DataFrame:
    """(sub, bucket, n): counted in each task before anything moves."""
    return bucketize(work.select("sub", "key"), pivots, most, how, values).groupBy("sub", "bucket").agg(F.count("*").alias("n"))


def pivot_ranks(counts: DataFrame) -> DataFrame:
    """Ranks that each bucket covers, by running sums over the buckets."""
    order = Window.partitionBy("sub").orderBy("bucket").rowsBetween(Window.unboundedPreceding, 0)
    return counts.withColumn("hi_rank", F.sum("n").over(order)).withColumn("lo_rank", F.col("hi_rank") - F.col("n") + 1)


def counted(work: DataFrame, pivots: DataFrame, settings: Settings) -> Partition:
    """One pass over the keys. Pivots and counts are bounded by max_pivots for each subproblem, so they fit the driver."""
    rows = pivots.collect()
    held = work.sparkSession.createDataFrame(rows, pivots.schema)
    values = {r["sub"]: list(r["pivots"]) for r in rows}
    found: dict[int, list[tuple[int, int, int]]] = {s: [] for s in values}
    for r in sorted(bucket_counts(work, held, max(map(len, values.values()), default=0), settings.how, values).collect()):
        own = found[r["sub"]]
        own.append((r["bucket"], r["n"], own[-1][1] + own[-1][2] if own else 1))
    return Partition(held, values, found)


def multi_partition(work: DataFrame, delta: int, settings: Settings = Settings(), source: str = "summary") -> Partition:
    """Buckets of at most delta elements between pivots; a bucket of one repeated value may be larger.

    source "summary": pivots at every delta / 2 ranks at once; "medians": every bucket that is too large splits at its median,
    round by round. Both end with the same check: while an open bucket is too large, it splits again.
    """
    n = work.count()
    parts = min(max(2, -(-2 * n // max(delta, 1))), settings.max_pivots)
    if source == "medians" or delta >= n:
        parts = 1
    none = work.sparkSession.createDataFrame([(s["sub"], []) for s in work.select("sub").distinct().collect()], work.select("sub", F.array("key").alias("pivots")).schema)
    found = counted(work, even_pivots(work, parts, max(settings.accuracy, 8 * parts)) if parts > 1 else none, settings)
    largest = None
    while True:
        too_large = [(s, b) for s, rows in found.bounds.items() for b, size, _ in rows if b % 2 == 0 and size > delta]
        if not too_large:
            return found
        # A split that parts nothing (sketched pivots among close whole numbers) is followed by one at an element.
        stuck, largest = largest == max(found.open_sizes()), max(found.open_sizes())
        large = work.sparkSession.createDataFrame(too_large, "sub long, bucket int")
        inside = bucketize(work.select("sub", "key"), found.pivots, found.most, settings.how, found.values).join(F.broadcast(large), ["sub", "bucket"])
        ids = inside.select(F.struct("sub", "bucket").alias("at"), "key").withColumn("sub", F.xxhash64("at"))
        owner = large.withColumn("id", F.xxhash64(F.struct("sub", "bucket")))
        more = even_pivots(ids.select("sub", "key"), 2, settings.accuracy, own=stuck).withColumnRenamed("sub", "id").join(owner, "id").select("sub", "pivots")
        pivots = found.pivots.unionByName(more).groupBy("sub").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("pivots")))).alias("pivots"))
        found = counted(work, pivots, settings)

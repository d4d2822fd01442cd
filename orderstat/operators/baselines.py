"""What the method is compared with: sorting, repeated selection, binary and cache-aware partition, random pivots, built-ins."""

from __future__ import annotations

from bisect import bisect_left, bisect_right
from dataclasses import replace
from functools import reduce
from itertools import accumulate

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from orderstat.operators.distribute import bucketize
from orderstat.operators.engine import Ledger, Level, Wanted, _route, finish, multi_select
from orderstat.operators.order import numbered
from orderstat.operators.partition import counted
from orderstat.plans.policy import Settings
from orderstat.sources.scratch import stored


def sort_one(df: DataFrame, key: str, ranks: DataFrame) -> DataFrame:
    """Numbers all rows in one task: what a plain window does. For small tables only."""
    rows = df.select(F.col(key).alias("value")).filter("value is not null").withColumn("rank", F.row_number().over(Window.orderBy("value")).cast("long"))
    return rows.join(F.broadcast(ranks), "rank").select("rank", "value")


def sort_all(df: DataFrame, key: str, ranks: DataFrame, parts: int | None = None) -> DataFrame:
    """A range-partitioned global sort in one exchange, and a numbering by counts of the tasks."""
    rows = df.select(F.col(key).alias("value")).filter("value is not null")
    return numbered(rows, ["value"], parts).join(F.broadcast(ranks), "rank").select("rank", "value")


def select_each(df: DataFrame, key: str, ranks: list[int], settings: Settings = Settings(branch="partition")) -> DataFrame:
    """One single selection for each rank."""
    out = None
    for r in ranks:
        one = multi_select(df, key, [r], settings=settings)
        out = one if out is None else out.unionByName(one)
    return out if out is not None else multi_select(df, key, [], settings=settings)


def binary_prune(df: DataFrame, key: str, ranks, finish_rows: int, ledger: Ledger | None = None, pivots: str = "median", seed: int = 1) -> DataFrame:
    """Split every live subproblem in two and drop halves without ranks.

    pivots: "median" of each, or one element of each: "random", or "first" as read, which parts badly on ordered input.
    """
    if pivots == "median":
        settings = Settings(branch="partition", pivots="summary", min_fanout=2, finish_rows=finish_rows, accuracy=200)
        return _fixed(df, key, ranks, replace(settings, max_pivots=2), ledger)
    return _prune_by_elements(df, key, ranks, finish_rows, ledger if ledger is not None else Ledger(), F.rand(seed) if pivots == "random" else F.monotonically_increasing_id())


def _prune_by_elements(df: DataFrame, key: str, ranks, finish_rows: int, ledger: Ledger, turn: Column) -> DataFrame:
    """Rounds of one pivot each: the element with the least turn of every live subproblem."""
    spark = df.sparkSession
    work = df.select(F.lit(0).cast("long").alias("sub"), F.col(key).alias("key")).filter("key is not null")
    kind, settings = work.schema["key"].dataType, Settings(finish_rows=finish_rows)
    sizes, done = {0: work.count()}, []
    want = Wanted.listed(spark, [(0, r, r) for r in sorted(set(ranks)) if 1 <= r <= sizes[0]])
    while want.rows and max(sizes.values()) > finish_rows:
        ones = work.withColumn("_turn", turn).groupBy("sub").agg(F.min_by("key", "_turn").alias("p")).select("sub", F.array("p").alias("pivots"))
        part = counted(work, ones, settings)
        answers, needs, want = _route(want, part, kind)
        done.append(answers)
        ledger.rows_scanned += 3 * sum(sizes.values())
        ledger.levels.append(Level(len(ledger.levels), "partition", "element", sum(sizes.values()), None, 2 * len(sizes), max((n for _, _, n in needs), default=0), -1, sum(n for _, _, n in needs), 0.0))
        ids = spark.createDataFrame([(s, b, k) for k, (s, b, _) in enumerate(needs)], "sub long, bucket int, next long")
        work = stored(bucketize(work, part.pivots, part.most, values=part.values).join(F.broadcast(ids), ["sub", "bucket"]).select(F.col("next").alias("sub"), "key"), "pruned")
        sizes = {k: n for k, (_, _, n) in enumerate(needs)} or {0: 0}
    ledger.rows_shuffled += sum(sizes.values()) if want.rows else 0
    done.append(finish(work, want.frame, True))
    return reduce(DataFrame.unionByName, done).select(F.col("asked").alias("rank"), "value")


def aware_partition(df: DataFrame, key: str, ranks, m: int, b: int, finish_rows: int | None = None, ledger: Ledger | None = None) -> DataFrame:
    """M / B ways at a time, with M and B given: the cache-aware method."""
    k = max(2, m // b)
    return _fixed(df, key, ranks, Settings(branch="partition", pivots="summary", min_fanout=k, max_pivots=k, finish_rows=finish_rows or m), ledger)


def _fixed(df: DataFrame, key: str, ranks, settings: Settings, ledger: Ledger | None) -> DataFrame:
    return multi_select(df, key, ranks, settings=settings, ledger=ledger)


def sampled_select(df: DataFrame, key: str, ranks: list[int], seed: int, ways: int | None = None, oversample: int = 64, margin: float = 4.0, ledger: Ledger | None = None, rate: float | None = None) -> DataFrame:
    """One distribution over random pivots with truncation, and a sort of what is left: the randomised predecessor.

    A sample of about ways * oversample elements, whatever the table's size (or of the share rate of them, where given), gives ways - 1 pivots and an estimate of their ranks, whose
    error is about n / sqrt(sample). Buckets that lie further than margin times that from every wanted rank are not told apart: the
    elements between two buckets of interest stop at one comparison more and are only counted. The buckets of interest are sorted
    directly. Counts are exact, so a rank that falls into what was cut off is noticed; it is tried again with twice the margin,
    at which every bucket is of interest in the end.
    """
    spark = df.sparkSession
    work = df.select(F.lit(0).cast("long").alias("sub"), F.col(key).alias("key")).filter("key is not null")
    n, kind, ledger = work.count(), work.schema["key"].dataType, ledger if ledger is not None else Ledger()
    ways = ways or max(4, min(1024, round(n ** (1 / 3))))
    want = Wanted.listed(spark, [(0, r, r) for r in sorted(set(ranks)) if 1 <= r <= n])
    done = [spark.createDataFrame([], T.StructType([T.StructField("asked", T.LongType()), T.StructField("value", kind)]))]
    turn = 0
    while want.rows:
        share = min(1.0, ways * oversample / n) if rate is None else rate
        sample = [r[0] for r in work.select("key").sample(fraction=share, seed=seed + turn).orderBy("key").collect()] or [work.agg(F.min("key")).first()[0]]
        s = len(sample)
        at = sorted({(k * s) // ways for k in range(1, ways)})
        slack = margin * 2**turn * n / s**0.5
        edges = [0.0, *((k + 0.5) * n / s for k in at), float(n)]
        near = [any(lo - slack <= r <= hi + slack for _, r, _ in want.rows) for lo, hi in zip(edges, edges[1:])]
        # A pivot is compared with only where a bucket of interest lies on one of its sides.
        pivots = sorted({sample[k] for j, k in enumerate(at) if near[j] or near[j + 1]})
        told = spark.createDataFrame([(0, pivots)], T.StructType([T.StructField("sub", T.LongType()), T.StructField("pivots", T.ArrayType(kind))]))
        part = counted(work, told, Settings())
        cut = {j for j, (lo, hi) in enumerate(zip([None, *pivots], [*pivots, None])) if not _of_interest(lo, hi, [sample[k] for k in at], near)}
        again, inside = [], []
        los = [lo for _, _, lo in part.bounds[0]]
        for row in want.rows:
            bucket = part.bounds[0][bisect_right(los, row[1]) - 1][0]
            (again if bucket % 2 == 0 and bucket // 2 in cut else inside).append(row)
        if inside:
            answers, needs, rest = _route(Wanted.listed(spark, inside), part, kind)
            done.append(answers)
            if needs:
                ids = spark.createDataFrame([(s_, b, k) for k, (s_, b, _) in enumerate(needs)], "sub long, bucket int, next long")
                kept = bucketize(work, part.pivots, part.most, values=part.values).join(F.broadcast(ids), ["sub", "bucket"]).select(F.col("next").alias("sub"), "key")
                before = list(accumulate((m for _, _, m in needs), initial=0))
                places = spark.createDataFrame([(before[k] + r, asked) for k, r, asked in rest.rows], "place long, asked long")
                done.append(numbered(kept, ["sub", "key"], out="place").join(F.broadcast(places), "place").select("asked", F.col("key").alias("value")))
                ledger.rows_shuffled += before[-1]
        ledger.rows_scanned += 3 * n
        ledger.levels.append(Level(turn, "partition", "random", n, None, len(pivots) + 1, max(part.open_sizes(), default=0), len(inside), len(again), 0.0))
        want, turn = Wanted.listed(spark, again), turn + 1
    return reduce(DataFrame.unionByName, done).select(F.col("asked").alias("rank"), "value")


def _of_interest(lo, hi, every: list, near: list[bool]) -> bool:
    """Whether the bucket between the pivots lo and hi of those kept holds a bucket of interest of all pivots."""
    a = 0 if lo is None else bisect_right(every, lo)
    z = len(every) if hi is None else bisect_left(every, hi)
    return any(near[a : z + 1])


def approximate(df: DataFrame, key: str, ranks: list[int], n: int, accuracy: int = 1000) -> DataFrame:
    """The built-in sketch's answers (rank, value); not exact."""
    got = df.agg(F.percentile_approx(key, F.array([F.lit(r / n) for r in ranks]), accuracy).alias("v"))
    return got.select(F.posexplode("v").alias("k", "value")).join(F.broadcast(df.sparkSession.createDataFrame(list(enumerate(ranks)), "k int, rank long")), "k").select("rank", "value")


def kll(df: DataFrame, key: str, ranks: list[int], n: int) -> DataFrame:
    """The built-in KLL sketch of doubles, by ranks; not exact."""
    sketch = df.agg(F.expr(f"kll_sketch_agg_double(cast({key} as double))").alias("s"))
    each = F.array([F.struct(F.lit(r).cast("long").alias("rank"), F.expr(f"kll_sketch_get_quantile_double(s, {r / n}D)").alias("value")) for r in ranks])
    return sketch.select(F.explode(each).alias("e")).select("e.*")


def built_in(df: DataFrame, key: str, fractions: list[float], group_by: list[str] | None = None) -> DataFrame:
    """percentile_disc: keeps every distinct value of a group in one task."""
    by = list(group_by or [])
    return df.groupBy(*by).agg(F.array([F.expr(f"percentile_disc({p}) within group (order by {key})") for p in fractions]).alias("v")).select(*by, F.posexplode("v").alias("k", "value")).withColumn("fraction", F.element_at(F.array([F.lit(p) for p in fractions]), F.col("k") + 1)).drop("k")


def top_k(df: DataFrame, key: str, m: int, n: int) -> DataFrame:
    """The m largest by a heap in each task, with their ranks."""
    rows = df.select(F.col(key).alias("value")).filter("value is not null").orderBy(F.desc("value")).limit(m)
    return rows.withColumn("rank", F.lit(n + 1) - F.row_number().over(Window.orderBy(F.desc("value"))).cast("long")).select("rank", "value")

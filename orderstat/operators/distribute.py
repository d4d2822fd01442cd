"""Bucket numbers by sorted distinct pivots: 2c between pivots c and c + 1, 2c - 1 for values equal to pivot c.

pivots come as a DataFrame (sub, pivots array), one row for each subproblem, broadcast: their number is bounded by
Settings.max_pivots, not by the data.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

HOWS = ("search", "case", "bucketizer", "arrow", "join")
NUMBERS = (T.ByteType, T.ShortType, T.IntegerType, T.LongType, T.FloatType, T.DoubleType)
#: Doubles tell whole numbers apart up to here; a longer key still lies on the right side of every pivot within.
WHOLE = 1 << 53


def upto(key: Column, pivots: Column, most: int) -> Column:
    """How many of the sorted pivots are at most key: a halving search of ceil(lg) steps, for any orderable type."""
    steps = [1 << j for j in range(max(most, 1).bit_length() - 1, -1, -1)]

    def step(at: Column, s: Column) -> Column:
        inside = at + s <= F.size(pivots)
        return F.when(inside & (F.try_element_at(pivots, at + s) <= key), at + s).otherwise(at)

    return F.aggregate(F.array([F.lit(s) for s in steps]), F.lit(0), step)


def three_way(key: Column, pivots: Column, count: Column) -> Column:
    count = F.coalesce(count, F.lit(0))  # never null, so that no join repeats the search to test for nulls
    equal = F.coalesce((count > 0) & (F.try_element_at(pivots, count) == key), F.lit(False))
    return (2 * count - equal.cast("int")).cast("int")


def nested_case(key: Column, pivots: list, lo: int = 0) -> Column:
    """The balanced binary tree of comparisons as one expression."""
    if not pivots:
        return F.lit(lo)
    m = len(pivots) // 2
    return F.when(key < F.lit(pivots[m]), nested_case(key, pivots[:m], lo)).otherwise(nested_case(key, pivots[m + 1 :], lo + m + 1))


def _fast(kind: T.DataType, values: dict[int, list] | None) -> bool:
    """Whether the compiled search over doubles serves: one subproblem, a number for a key, finite pivots that doubles tell from all keys."""
    return values is not None and len(values) == 1 and isinstance(kind, NUMBERS) and all(math.isfinite(v) and (isinstance(v, float) or abs(v) < WHOLE) for v in next(iter(values.values())))


def bucketize(work: DataFrame, pivots: DataFrame, most: int, how: str = "auto", values: dict[int, list] | None = None) -> DataFrame:
    """work (sub, key, ...) with a column bucket; subproblems without a row in pivots are left out.

    how "auto" takes the bucketizer where it serves and values, the pivots by subproblem, are at hand; else the search. Others than
    "search" need one subproblem and numbers (join: any type); the bucketizer leaves pivots that doubles confuse to the search.
    """
    kind = work.schema["key"].dataType
    if how == "auto":
        how = "bucketizer" if _fast(kind, values) else "search"
    if how == "bucketizer" and isinstance(kind, NUMBERS):
        values = values or {r["sub"]: list(r["pivots"]) for r in pivots.limit(2).collect()}
        how = how if len(values) != 1 or _fast(kind, values) else "search"
    if how == "search":
        met = work.join(F.broadcast(pivots), "sub")
        return met.withColumn("_c", upto(F.col("key"), F.col("pivots"), most)).withColumn("bucket", three_way(F.col("key"), F.col("pivots"), F.col("_c"))).drop("_c", "pivots")
    if how == "join":
        ends = pivots.select("sub", F.explode(F.sequence(F.lit(0), F.size("pivots"))).alias("c"), "pivots")
        ends = ends.select(F.col("sub").alias("_sub"), "c", F.when(F.col("c") > 0, F.try_element_at("pivots", F.col("c"))).alias("lo"), F.try_element_at("pivots", F.col("c") + 1).alias("hi"))
        fits = (F.col("sub") == F.col("_sub")) & (F.col("lo").isNull() | (F.col("lo") <= F.col("key"))) & (F.col("hi").isNull() | (F.col("key") < F.col("hi")))
        met = work.join(F.broadcast(ends), fits)
        return met.withColumn("bucket", (2 * F.col("c") - F.coalesce(F.col("lo") == F.col("key"), F.lit(False)).cast("int")).cast("int")).drop("_sub", "c", "lo", "hi")
    rows = [{"sub": s, "pivots": v} for s, v in values.items()] if values is not None else pivots.limit(2).collect()
    if len(rows) > 1 or not isinstance(kind, NUMBERS):
        raise ValueError(f"how={how!r} serves one subproblem with a numeric key")
    if not rows:
        return work.limit(0).withColumn("bucket", F.lit(0))
    sub, values = rows[0]["sub"], list(rows[0]["pivots"])
    work = work.filter(F.col("sub") == sub)
    if how == "case":
        count = nested_case(F.col("key"), values)
    elif how == "bucketizer":
        from pyspark.ml.feature import Bucketizer

        # Adding 0.0 makes a negative zero the zero it equals.
        tool = Bucketizer(splits=[-np.inf, *(float(v) + 0.0 for v in values), np.inf], inputCol="_d", outputCol="_b", handleInvalid="keep")
        work = tool.transform(work.withColumn("_d", F.col("key").cast("double") + F.lit(0.0))) if values else work.withColumn("_b", F.lit(0.0)).withColumn("_d", F.lit(0.0))
        count = F.least(F.col("_b").cast("int"), F.lit(len(values)))
    elif how == "arrow":
        edges = np.array(values)

        @F.pandas_udf("int")
        def search(key: pd.Series) -> pd.Series:
            return pd.Series(np.searchsorted(edges, key.to_numpy(), side="right").astype(np.int32))

        count = search(F.col("key"))
    else:
        raise ValueError(f"how must be one of {HOWS}")
    array = F.array([F.lit(v).cast(kind) for v in values]) if values else F.array().cast(T.ArrayType(kind))
    return work.withColumn("_c", count).withColumn("bucket", three_way(F.col("key"), array, F.col("_c"))).drop("_c", "_b", "_d")

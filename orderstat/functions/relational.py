"""Joins and set operations around answers: comparison, brute force, what is left to answer."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def compared(a: DataFrame, b: DataFrame) -> DataFrame:
    """(rank, a, b, same) of two answer sets; ranks that one lacks have null on its side, nulls equal each other."""
    left, right = a.select("rank", F.col("value").alias("a")), b.select(F.col("rank").alias("_rank"), F.col("value").alias("b"))
    met = left.join(right, F.col("rank").eqNullSafe(F.col("_rank")), "full_outer")
    both = F.col("rank").isNotNull() & F.col("_rank").isNotNull()
    return met.select(F.coalesce("rank", "_rank").alias("rank"), "a", "b", (both & F.col("a").eqNullSafe(F.col("b"))).alias("same"))


def same_answers(a: DataFrame, b: DataFrame) -> bool:
    """Whether two answer sets are equal as multisets of rows."""
    columns = ["rank", "value"]
    return a.select(columns).exceptAll(b.select(columns)).isEmpty() and b.select(columns).exceptAll(a.select(columns)).isEmpty()


def unanswered(ranks: DataFrame, answers: DataFrame) -> DataFrame:
    return ranks.join(answers, "rank", "left_anti")


def brute_force(df: DataFrame, key: str, ranks: DataFrame) -> DataFrame:
    """(rank, value) by counting, for each distinct value, the rows under and up to it: a nested loop, for tiny tables only."""
    rows = df.select(F.col(key).alias("y")).filter("y is not null")
    values = rows.select(F.col("y").alias("value")).distinct()
    spans = values.join(rows, F.col("y") <= F.col("value")).groupBy("value").agg(F.sum((F.col("y") < F.col("value")).cast("long")).alias("lt"), F.count("*").alias("le"))
    return ranks.join(spans, (F.col("rank") > F.col("lt")) & (F.col("rank") <= F.col("le"))).select("rank", "value")

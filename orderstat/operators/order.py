"""Numbering of rows in an order: one exchange by ranges, sorted tasks, and offsets by task. No row goes through a single task."""

from __future__ import annotations

from itertools import accumulate

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from orderstat.sources.scratch import stored

#: monotonically_increasing_id holds the task above and the row's number in it below this bit.
_BIT = 33


def numbered(rows: DataFrame, by: list[str], parts: int | None = None, out: str = "rank") -> DataFrame:
    """rows with the place from 1 in the order of the columns by. Rows that are equal in all of by are spread over tasks as any others.

    The ordered rows are written once, so that counts and numbers are those of one and the same exchange.
    """
    spark = rows.sparkSession
    parts = parts or max(spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")))
    laid = rows.withColumn("_tie", F.monotonically_increasing_id()).repartitionByRange(parts, *by, "_tie").sortWithinPartitions(*by, "_tie")
    laid = stored(laid.drop("_tie").withColumn("_at", F.monotonically_increasing_id()), "ordered")
    part = F.shiftrightunsigned("_at", _BIT)
    sizes = sorted(tuple(r) for r in laid.groupBy(part.alias("part")).agg(F.count("*").alias("n")).collect())  # a row for each task
    before = list(accumulate((n for _, n in sizes), initial=0))
    starts = spark.createDataFrame([(p, b) for (p, _), b in zip(sizes, before)], "_part long, _before long")
    met = laid.join(F.broadcast(starts), part == F.col("_part"))
    return met.withColumn(out, F.col("_before") + F.col("_at").bitwiseAND((1 << _BIT) - 1) + 1).drop("_at", "_part", "_before")

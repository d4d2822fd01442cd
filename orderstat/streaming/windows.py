"""Exact quantiles of the events of each closed window.

The state of a window and key is the multiset of its values, value by count, so memory grows with the distinct values of
open windows. Rows later than the watermark are dropped by the engine and counted in its progress reports.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from fractions import Fraction

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from orderstat.operators.engine import multi_select
from orderstat.sources.ranks import Fractions, fraction_rank


def events_stream(spark: SparkSession, path: str, schema) -> DataFrame:
    return spark.readStream.schema(schema).parquet(path)


def window_counts(events: DataFrame, value: str, window: Column, keys: list[str], delay: str = "10 minutes", time: str = "ts", unique: str | None = None) -> DataFrame:
    """(start, end, keys, value, n): the histogram of each window. Tumbling, sliding or session windows; unique drops repeats of an event."""
    rows = events.withWatermark(time, delay)
    if unique:
        rows = rows.dropDuplicatesWithinWatermark([unique])
    return rows.groupBy(window.alias("w"), *keys, F.col(value).alias("value")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *keys, "value", "n")


def ranks_of_counts(counts: DataFrame, by: list[str], ps: list[str]) -> DataFrame:
    """Batch form: exact values of fractions from a histogram."""
    from pyspark.sql import Window

    order = Window.partitionBy(*by).orderBy("value")
    spans = counts.withColumn("hi", F.sum("n").over(order.rowsBetween(Window.unboundedPreceding, 0))).withColumn("total", F.sum("n").over(Window.partitionBy(*by)))
    asked = [Fraction(p) for p in ps]
    each = F.array([F.struct(F.lit(float(p)).alias("fraction"), F.greatest(F.lit(1), F.expr(f"(total * {p.numerator} + {p.denominator - 1}) div {p.denominator}")).alias("rank")) for p in asked])
    met = spans.select(*by, "value", "n", "hi", F.explode(each).alias("e"))
    return met.filter((F.col("e.rank") <= F.col("hi")) & (F.col("e.rank") > F.col("hi") - F.col("n"))).select(*by, "e.fraction", "e.rank", "value")


def stateful_ranks(events: DataFrame, value: str, window: Column, keys: list[str], ps: list[str], delay: str = "10 minutes", time: str = "ts") -> DataFrame:
    """Streaming form: (start, keys..., fraction, rank, value), emitted once when the watermark passes a window's end."""
    asked = [Fraction(p) for p in ps]
    rows = events.withWatermark(time, delay).select(window.alias("w"), time, *keys, F.col(value).cast("double").alias("value"))
    rows = rows.select(F.col("w.start").cast("timestamp").alias("start"), F.col("w.end").cast("timestamp").alias("end"), time, *keys, "value")
    key_schema = ", ".join(f"{k} {events.schema[k].dataType.simpleString()}" for k in keys)
    out = f"start timestamp, {key_schema + ', ' if keys else ''}fraction double, rank long, value double"

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            values, counts = state.get
            state.remove()
            n, at, found = sum(counts), 0, []
            pairs = sorted(zip(values, counts))
            for p in sorted(asked):
                r, upto = fraction_rank(p, n), 0
                for v, c in pairs:
                    upto += c
                    if upto >= r:
                        found.append((key[0], *key[2:], float(p), r, v))
                        break
            yield pd.DataFrame(found, columns=["start", *keys, "fraction", "rank", "value"])
            return
        held = dict(zip(*state.get)) if state.exists else {}
        for frame in frames:
            for v, c in frame["value"].dropna().value_counts().items():
                held[v] = held.get(v, 0) + int(c)
        state.update((list(held), list(held.values())))
        end = int(pd.Timestamp(key[1]).timestamp() * 1000)
        state.setTimeoutTimestamp(max(end, state.getCurrentWatermarkMs() + 1))

    return rows.groupBy("start", "end", *keys).applyInPandasWithState(step, out, "values array<double>, counts array<long>", "append", GroupStateTimeout.EventTimeTimeout)


def each_batch(write: Callable[[DataFrame], None], key: str, ps: list[str], by: list[str]) -> Callable[[DataFrame, int], None]:
    """A foreachBatch function: exact quantiles of each micro-batch's groups by the engine, handed to write."""

    def run(batch: DataFrame, number: int) -> None:
        write(multi_select(batch, key, Fractions(*ps), group_by=by))

    return run

"""Cost and accuracy measures: of rank lists, of kernel runs, of answers, of Spark runs."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from orderstat.plans.gaps import Sizes, counted
from orderstat.plans.policy import TallCache


def rank_entropy(gaps: DataFrame, n: int) -> DataFrame:
    """(entropy): sum of size lg(n / size) over the gaps, in bits."""
    return gaps.agg(F.coalesce(F.sum(F.col("size") * F.log2(F.lit(float(n)) / F.col("size"))), F.lit(0.0)).alias("entropy"))


def entropy_of(sizes: Sizes, n: int) -> float:
    return sum(c * s * math.log2(n / s) for s, c in counted(sizes)) if n else 0.0


def io_bound(sizes: Sizes, n: int, m: int, b: int, base: str = "m/b") -> float:
    """Sum of size / B log(n / size) over the gaps, to the base M / B (or "m" for M), plus n / B."""
    log = math.log(m / b if base == "m/b" else m)
    return sum(c * s / b * max(0.0, math.log(n / s)) / log for s, c in counted(sizes)) + n / b


def scan_blocks(n: int, b: int) -> int:
    return -(-n // b)


def sort_bound(n: int, m: int, b: int) -> float:
    return n / b * (1 + max(0.0, math.log(max(n / b, 1)) / math.log(m / b)))


def tree_space(k: int, d: float) -> float:
    return k ** ((d + 1) / 2)


def potential(sizes: Sizes, n: int, kind: str = "comparisons", m: int = 2, b: int = 1) -> float:
    """Potential of all elements of a problem: 1 + lg(n / size) for each element of a gap, or its share of transfers."""
    if kind == "comparisons":
        return sum(c * s * (1 + math.log2(n / s)) for s, c in counted(sizes))
    return sum(c * s / b * (1 + math.log(n / s) / math.log(m)) for s, c in counted(sizes))


def released(call: dict, later: list[dict]) -> float:
    """Potential that a kernel call gives back: its own less that of the problems it leaves, their elements in the same gaps."""
    own = potential(call["sizes"], call["n"])
    return own - sum(potential(c["sizes"], c["n"]) for c in later)


def k2_ok(n: int, delta: int, tall: TallCache = TallCache()) -> bool:
    """Whether n^(1 + 1 / (1 + eps)) <= delta^2, under which the square of the fan-out is within n / B."""
    return (1 + 1 / (1 + float(tall.eps))) * math.log(n) <= 2 * math.log(delta) + 1e-9


def rank_error(df: DataFrame, key: str, answers: DataFrame) -> DataFrame:
    """answers (rank, value) with lt, eq and error: how far rank lies outside the ranks that value holds.

    One pass with one search for each row.
    """
    from orderstat.functions.quantiles import rank_of

    counts = rank_of(df, key, answers.select("value"))
    told = answers.join(counts, "value", "left").na.fill(0, ["lt", "eq"])
    return told.withColumn("error", F.greatest(F.col("lt") + 1 - F.col("rank"), F.col("rank") - F.col("lt") - F.greatest("eq", F.lit(1)), F.lit(0)))


def read_event_log(spark: SparkSession, path: str) -> DataFrame:
    """Tasks of an event log: (stage, rows_read, shuffle_rows, shuffle_bytes, spill_bytes, run_ms)."""
    log = spark.read.schema(
        "Event string, `Stage ID` long, `Task Metrics` struct<`Executor Run Time`:long,`Disk Bytes Spilled`:long,`Input Metrics`:struct<`Records Read`:long>,`Shuffle Write Metrics`:struct<`Shuffle Records Written`:long,`Shuffle Bytes Written`:long>>"
    ).json(path)
    m = "`Task Metrics`"
    return log.filter("Event = 'SparkListenerTaskEnd'").select(
        F.col("`Stage ID`").alias("stage"), F.col(f"{m}.`Input Metrics`.`Records Read`").alias("rows_read"), F.col(f"{m}.`Shuffle Write Metrics`.`Shuffle Records Written`").alias("shuffle_rows"),
        F.col(f"{m}.`Shuffle Write Metrics`.`Shuffle Bytes Written`").alias("shuffle_bytes"), F.col(f"{m}.`Disk Bytes Spilled`").alias("spill_bytes"), F.col(f"{m}.`Executor Run Time`").alias("run_ms"),
    )

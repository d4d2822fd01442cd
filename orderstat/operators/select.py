"""Single, grouped and weighted selection by rounds of pivots and exact counts."""

from __future__ import annotations

import math
from decimal import ROUND_CEILING, Context, Decimal
from fractions import Fraction

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from orderstat.operators.distribute import bucketize
from orderstat.operators.engine import Ledger, multi_select, resolve
from orderstat.operators.summary import even_pivots
from orderstat.plans.policy import Settings
from orderstat.sources.scratch import stored


def select_rank(df: DataFrame, key: str, k: int, settings: Settings = Settings(branch="partition")) -> DataFrame:
    """(rank, value) of one rank."""
    return multi_select(df, key, [k], settings=settings)


def select_rank_grouped(df: DataFrame, sub: str, key: str, wanted: DataFrame, settings: Settings = Settings()) -> DataFrame:
    """(sub, rank, value) for wanted (sub, rank); sub is a whole number, and its values are few enough to list."""
    work = df.select(F.col(sub).cast("long").alias("sub"), F.col(key).alias("key")).filter("key is not null")
    want = wanted.select("sub", "rank", F.struct("sub", "rank").alias("asked"))
    return resolve(work, want, settings, Ledger()).select("asked.sub", "asked.rank", "value")


def weighted_rank(df: DataFrame, value: str, weight: str, target, settings: Settings = Settings()) -> DataFrame:
    """(value, cum_weight): the smallest value such that the weights up to it sum to target; no row where all do not."""
    return weighted_ranks(df, value, weight, [target], settings).select("value", "cum_weight")


def weighted_ranks(df: DataFrame, value: str, weight: str, targets: list, settings: Settings = Settings()) -> DataFrame:
    """(no, value, cum_weight) for targets no = 0, 1, ...: all of them share each round's passes.

    A round collects pivots, sums the weights of every bucket in one pass, and writes only the buckets in which a target is passed; a
    target passed at a pivot is answered. What fits a task is ordered there. Pivots that part nothing are followed by elements, each of
    which is removed with its equals, so that a round always makes progress. Null values and null weights count nothing.
    Sums of whole or decimal weights are exact; those of doubles are taken in no set order and hold to their rounding.
    """
    spark = df.sparkSession
    work = df.select(F.lit(0).cast("long").alias("sub"), F.col(value).alias("key"), F.col(weight).alias("w")).filter("key is not null and w is not null")
    kind, sum_kind = work.schema["key"].dataType, work.agg(F.sum("w").alias("w")).schema["w"].dataType
    zero = _as(0, sum_kind)
    open_ = {0: (zero, [(no, _as(t, sum_kind)) for no, t in enumerate(targets)])}  # weight before a subproblem, and its targets
    row = work.agg(F.count("*").alias("n"), F.sum("w").alias("w")).first()
    sizes, done, stuck = {0: row["n"]}, [], False
    open_[0] = (zero, [(no, t) for no, t in open_[0][1] if row["n"] and t <= row["w"]])
    answers: list[tuple] = []
    while any(told for _, told in open_.values()):
        if max(sizes.values()) <= settings.finish_rows:
            done.append(_ordered(work, open_, sum_kind))
            break
        parts = max(2, min(settings.min_fanout, settings.max_total_pivots // len(sizes)))
        pivots = even_pivots(work.select("sub", "key"), parts, settings.accuracy, own=stuck)
        rows = pivots.collect()
        held, values = spark.createDataFrame(rows, pivots.schema), {r["sub"]: list(r["pivots"]) for r in rows}
        most = max(map(len, values.values()))
        sums = sorted(tuple(r) for r in bucketize(work, held, most, values=values).groupBy("sub", "bucket").agg(F.sum("w").alias("w"), F.count("*").alias("n")).collect())
        needs: dict[tuple[int, int], tuple] = {}
        for sub, (before, told) in open_.items():
            own = [(b, w, n) for s, b, w, n in sums if s == sub]
            for no, target in told:
                reached = before
                for j, (b, w, n) in enumerate(own):
                    # Rounding may let the sums of a bucket's parts fall short of its own; its last part is then meant.
                    if reached + w >= target or j == len(own) - 1:
                        break
                    reached += w
                if b % 2:
                    answers.append((no, values[sub][b // 2], reached + w))
                else:
                    needs.setdefault((sub, b), (reached, n, []))[2].append((no, target))
        if not needs:
            break
        ids = spark.createDataFrame([(s, b, k) for k, (s, b) in enumerate(needs)], "sub long, bucket int, next long")
        kept = bucketize(work, held, most, values=values).join(F.broadcast(ids), ["sub", "bucket"]).select(F.col("next").alias("sub"), "key", "w")
        stuck = max(n for _, n, _ in needs.values()) == max(sizes.values())
        sizes = {k: n for k, (_, n, _) in enumerate(needs.values())}
        open_ = {k: (reached, told) for k, (reached, _, told) in enumerate(needs.values())}
        work = stored(kept, "weighted")
    schema = T.StructType([T.StructField("no", T.IntegerType()), T.StructField("value", kind), T.StructField("cum_weight", sum_kind)])
    out = spark.createDataFrame(answers, schema)
    for more in done:
        out = out.unionByName(more)
    return out


def _ordered(work: DataFrame, open_: dict, sum_kind: T.DataType) -> DataFrame:
    """The answers by running sums in each subproblem, every one of which fits a task."""
    schema = T.StructType([T.StructField("sub", T.LongType()), T.StructField("before", sum_kind), T.StructField("no", T.IntegerType()), T.StructField("target", sum_kind)])
    told = work.sparkSession.createDataFrame([(s, before, no, t) for s, (before, ts) in open_.items() for no, t in ts], schema)
    merged = work.groupBy("sub", "key").agg(F.sum("w").alias("w"))
    turn = Window.partitionBy("sub").orderBy("key").rowsBetween(Window.unboundedPreceding, 0)
    running = merged.withColumn("cum", F.sum("w").over(turn)).withColumn("last", F.max("key").over(Window.partitionBy("sub")) == F.col("key"))
    met = running.join(F.broadcast(told), "sub").withColumn("cum_weight", (F.col("cum") + F.col("before")).cast(sum_kind))
    best = met.filter((F.col("cum_weight") >= F.col("target")) | F.col("last")).groupBy("no").agg(F.min(F.struct("key", "cum_weight")).alias("m"))
    return best.select("no", F.col("m.key").alias("value"), "m.cum_weight")


def _as(target, kind: T.DataType):
    """The least value of a type of sums that is at least target."""
    if isinstance(kind, T.DecimalType):
        exact = Fraction(target)
        step = Decimal(1).scaleb(-kind.scale)
        return (Decimal(math.ceil(exact * 10**kind.scale)) * step).quantize(step, ROUND_CEILING, Context(prec=60))
    return math.ceil(target) if isinstance(kind, T.LongType) else float(target)

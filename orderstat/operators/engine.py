"""Exact multiple selection, level by level.

All subproblems of a level live in one DataFrame work (sub, key); their wanted ranks in want (sub, rank, asked), asked
being the rank as the caller gave it. A level finds pivots, counts every bucket exactly in one pass over the keys, answers
ranks that fall on pivots, and keeps only the buckets that still hold wanted ranks. Rows move between tasks once: when what
is left of a subproblem fits a task and is ordered there.
"""

from __future__ import annotations

import time
from bisect import bisect_right
from dataclasses import dataclass, field, replace
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from orderstat.operators.distribute import bucketize, upto
from orderstat.operators.partition import Partition, counted, multi_partition
from orderstat.operators.summary import bracket_pivots, even_pivots, sketched
from orderstat.plans.gaps import gap_sizes, gap_threshold, rank_gaps, threshold_of
from orderstat.plans.policy import Branch, Settings, choose_branch
from orderstat.sources import ranks as R
from orderstat.sources.scratch import stored


@dataclass
class Level:
    depth: int
    branch: str
    pivots: str
    rows: int
    delta: int | None
    buckets: int
    largest_open: int
    answered: int
    survivors: int
    seconds: float


@dataclass
class Ledger:
    levels: list[Level] = field(default_factory=list)
    rows_scanned: int = 0
    rows_shuffled: int = 0


@dataclass
class Wanted:
    """Ranks still to answer: a short list of (sub, rank, asked) on the driver, or a DataFrame of these columns."""

    rows: list[tuple[int, int, int]] | None
    frame: DataFrame

    @staticmethod
    def of(frame: DataFrame, most: int) -> Wanted:
        if not isinstance(frame.schema["asked"].dataType, T.LongType):
            return Wanted(None, frame)
        rows = [tuple(r) for r in frame.select("sub", "rank", "asked").limit(most + 1).collect()]
        return Wanted.listed(frame.sparkSession, rows) if len(rows) <= most else Wanted(None, frame)

    @staticmethod
    def listed(spark: SparkSession, rows: list[tuple[int, int, int]]) -> Wanted:
        return Wanted(rows, spark.createDataFrame(rows, "sub long, rank long, asked long"))


def _route_listed(want: Wanted, part: Partition, kind: T.DataType) -> tuple[DataFrame, list[tuple[int, int, int]], Wanted]:
    """Answers on pivots; the buckets still needed as (sub, bucket, n), numbered by place; their ranks under these numbers."""
    spark, settled, needs, rest = want.frame.sparkSession, [], {}, []
    los = {s: [lo for _, _, lo in rows] for s, rows in part.bounds.items()}
    for sub, rank, asked in want.rows:
        bucket, n, lo = part.bounds[sub][bisect_right(los[sub], rank) - 1]
        if bucket % 2:
            settled.append((asked, part.values[sub][bucket // 2]))
        else:
            rest.append((needs.setdefault((sub, bucket, n), len(needs)), rank - lo + 1, asked))
    answers = spark.createDataFrame(settled, T.StructType([T.StructField("asked", T.LongType()), T.StructField("value", kind)]))
    return answers, list(needs), Wanted.listed(spark, rest)


def _route_frame(want: Wanted, part: Partition, kind: T.DataType) -> tuple[DataFrame, list[tuple[int, int, int]], Wanted]:
    """The same for a rank list of any length: a rank finds its bucket by the halving search that a key uses."""
    each = part.bounds_frame().groupBy("sub").agg(F.array_sort(F.collect_list(F.struct("lo_rank", "bucket", "n"))).alias("b"))
    table = each.join(part.pivots, "sub").select("sub", "b", F.transform("b", lambda x: x["lo_rank"]).alias("los"), "pivots")
    met = want.frame.join(F.broadcast(table), "sub").withColumn("c", upto(F.col("rank"), F.col("los"), 2 * part.most + 1))
    hit = met.withColumn("h", F.col("b")[F.col("c") - 1])
    odd = F.col("h.bucket") % 2 == 1
    value = F.when(odd, F.try_element_at("pivots", F.expr("cast((h.bucket + 1) div 2 as int)"))).cast(kind)
    routed = stored(hit.select("sub", "asked", F.col("h.bucket").alias("bucket"), F.col("h.n").alias("n"), (F.col("rank") - F.col("h.lo_rank") + 1).alias("rank"), value.alias("value"), odd.alias("settled")), "routed")
    needs = [(r["sub"], r["bucket"], r["n"]) for r in routed.filter("not settled").select("sub", "bucket", "n").distinct().orderBy("sub", "bucket").collect()]
    ids = want.frame.sparkSession.createDataFrame([(s, b, k) for k, (s, b, _) in enumerate(needs)], "sub long, bucket int, next long")
    rest = routed.filter("not settled").join(F.broadcast(ids), ["sub", "bucket"]).select(F.col("next").alias("sub"), "rank", "asked")
    return routed.filter("settled").select("asked", "value"), needs, Wanted(None, rest)


def _route(want: Wanted, part: Partition, kind: T.DataType) -> tuple[DataFrame, list[tuple[int, int, int]], Wanted]:
    return _route_listed(want, part, kind) if want.rows is not None else _route_frame(want, part, kind)


def finish(work: DataFrame, want: DataFrame, listed: bool = False) -> DataFrame:
    """(asked, value) by ordering each subproblem; the largest wanted rank ends the numbering.

    A listed want has Settings.listed_ranks rows at most and is broadcast, so the one shuffle is that of the ordering.
    """
    last = want.groupBy("sub").agg(F.max("rank").alias("last"))
    want, last = (F.broadcast(want), F.broadcast(last)) if listed else (want, last)
    numbered = work.join(last, "sub").withColumn("rank", F.row_number().over(Window.partitionBy("sub").orderBy("key"))).filter("rank <= last")
    return numbered.join(want, ["sub", "rank"]).select("asked", F.col("key").alias("value"))


def _trimmed(work: DataFrame, want: DataFrame, sizes: dict[int, int], settings: Settings) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Answers of each subproblem's least and largest wanted rank, and what lies strictly between them."""
    spark, kind = work.sparkSession, work.schema["key"].dataType
    ends = [tuple(r) for r in want.groupBy("sub").agg(F.min("rank"), F.max("rank")).collect()]
    asked = spark.createDataFrame([(s, r, s * 2 + k) for s, a, z in ends for k, r in enumerate((a, z))], "sub long, rank long, asked long")
    found = {r["asked"]: r["value"] for r in resolve(work, asked, replace(settings, trim="none", pivots="summary"), Ledger(), sizes=sizes).collect()}
    schema = T.StructType([T.StructField("sub", T.LongType()), T.StructField("low", kind), T.StructField("high", kind)])
    edge = F.broadcast(spark.createDataFrame([(s, found[2 * s], found[2 * s + 1]) for s, _, _ in ends], schema))
    met = work.join(edge, "sub")
    tell = lambda c: F.sum(c.cast("long"))
    counts = met.groupBy("sub").agg(tell(F.col("key") <= F.col("low")).alias("upto"), tell(F.col("key") < F.col("high")).alias("under"))
    told = want.join(F.broadcast(counts), "sub").join(edge, "sub")
    low, high = F.col("rank") <= F.col("upto"), F.col("rank") > F.col("under")
    answers = told.filter(low | high).select("asked", F.when(low, F.col("low")).otherwise(F.col("high")).alias("value"))
    rest = told.filter(~low & ~high).select("sub", (F.col("rank") - F.col("upto")).alias("rank"), "asked")
    between = met.filter((F.col("key") > F.col("low")) & (F.col("key") < F.col("high"))).select("sub", "key")
    return stored(answers, "ends"), stored(between, "trimmed"), stored(rest, "rest")


def _pivots(work: DataFrame, want: Wanted, sizes: dict[int, int], delta: int | None, settings: Settings) -> tuple[DataFrame, str]:
    n, kind, mode = max(sizes.values()), work.schema["key"].dataType, settings.pivots
    one = len(sizes) == 1 and sketched(kind) and want.rows is not None and len(want.rows) <= settings.max_pivots // 2
    if mode in ("auto", "bracket") and one:
        return bracket_pivots(work, sorted({r for _, r, _ in want.rows}), n, settings.accuracy), "bracket"
    parts = min(max(-(-2 * n // delta) if delta else 2, settings.min_fanout), settings.max_pivots, settings.max_total_pivots // len(sizes))
    return even_pivots(work, max(parts, 2), max(settings.accuracy, 8 * parts)), "summary"


def resolve(work: DataFrame, want: DataFrame, settings: Settings, ledger: Ledger, delta: int | None = None, forced: DataFrame | None = None, sizes: dict[int, int] | None = None) -> DataFrame:
    """(asked, value) for all of want (sub, rank, asked). work's subproblems must be few enough to list: big groups, or buckets."""
    kind, spark = work.schema["key"].dataType, work.sparkSession
    done: list[DataFrame] = []
    wanted, stuck = Wanted.of(want, settings.listed_ranks), False
    for depth in range(settings.max_levels):
        began = time.time()
        if depth and settings.trim == "exact":
            large = [s for s, n in sizes.items() if n > settings.finish_rows]
            if large:
                big = F.col("sub").isin(large)
                done.append(finish(work.filter(~big), wanted.frame.filter(~big), wanted.rows is not None))
                answers, work, rest = _trimmed(work.filter(big), wanted.frame.filter(big), {s: sizes[s] for s in large}, settings)
                done.append(answers)
                wanted, sizes = Wanted.of(rest, settings.listed_ranks), None
        if sizes is None:
            sizes = {r["sub"]: r["n"] for r in work.groupBy("sub").agg(F.count("*").alias("n")).collect()}
        here = {s: n for s, n in sizes.items() if n > settings.finish_rows or (depth == 0 and (delta or forced is not None))}
        if len(here) < len(sizes):
            small = ~F.col("sub").isin(list(here)) if here else F.lit(True)
            done.append(finish(work.filter(small), wanted.frame.filter(small), wanted.rows is not None))
            ledger.rows_shuffled += sum(n for s, n in sizes.items() if s not in here)
            if here:
                work, wanted = work.filter(~small), Wanted.of(wanted.frame.filter(~small), settings.listed_ranks)
        if not here:
            break
        total = sum(here.values())
        if forced is not None:
            part, mode, forced = counted(work, forced, settings), "given", None
        elif stuck:
            part, mode = counted(work, even_pivots(work, settings.min_fanout, settings.accuracy, own=True), settings), "elements"
        elif settings.pivots in ("medians", "paper") and delta:
            part, mode = multi_partition(work, delta, settings, "medians" if settings.pivots == "medians" else "summary"), settings.pivots
        else:
            pivots, mode = _pivots(work, wanted, here, delta, settings)
            part = counted(work, pivots, settings)
        answers, needs, rest = _route(wanted, part, kind)
        done.append(answers)
        opened, survivors = part.open_sizes(), sum(n for _, _, n in needs)
        ledger.rows_scanned += 2 * total + (total if needs else 0)
        answered = len(wanted.rows) - len(rest.rows) if wanted.rows is not None else -1
        ledger.levels.append(Level(depth, "partition", mode, total, delta, len(opened), max(opened, default=0), answered, survivors, time.time() - began))
        if not needs:
            break
        # Pivots that part nothing: next time take elements, each of which is removed with all its equals.
        stuck = max(n for _, _, n in needs) == max(here.values())
        ids = spark.createDataFrame([(s, b, k) for k, (s, b, _) in enumerate(needs)], "sub long, bucket int, next long")
        kept = bucketize(work, part.pivots, part.most, settings.how, part.values).join(F.broadcast(ids), ["sub", "bucket"]).select(F.col("next").alias("sub"), "key")
        sizes, delta, wanted = {k: n for k, (_, _, n) in enumerate(needs)}, None, rest
        if all(n <= settings.finish_rows for n in sizes.values()):
            # The last read of the keys goes straight into the one shuffle; nothing is written between.
            ledger.rows_shuffled += survivors
            done.append(finish(kept, wanted.frame, wanted.rows is not None))
            break
        work = stored(kept, "frontier")
    else:
        raise RuntimeError("the selection did not end")
    return reduce(DataFrame.unionByName, done)


def sort_and_pick(work: DataFrame, want: DataFrame, n: int, settings: Settings, ledger: Ledger) -> DataFrame:
    """The sort branch for one subproblem: even buckets, exact offsets, and an ordering in each bucket that holds a rank."""
    began = time.time()
    spark = work.sparkSession
    parts = min(max(-(-n // settings.bucket_rows), min(spark.sparkContext.defaultParallelism, n // 20_000), 1), settings.max_sort_buckets)
    if parts == 1:
        ledger.levels.append(Level(0, "sort", "none", n, None, 1, n, 0, n, time.time() - began))
        ledger.rows_scanned, ledger.rows_shuffled = n, n
        return finish(work, want)
    kind = work.schema["key"].dataType
    part = counted(work, even_pivots(work, parts, max(settings.accuracy, 8 * parts)), settings)
    answers, needs, rest = _route(Wanted.of(want, settings.listed_ranks), part, kind)
    ids = spark.createDataFrame([(s, b, k) for k, (s, b, _) in enumerate(needs)], "sub long, bucket int, next long")
    kept = bucketize(work, part.pivots, part.most, settings.how, part.values).join(F.broadcast(ids), ["sub", "bucket"]).select(F.col("next").alias("sub"), "key")
    moved = sum(n for _, _, n in needs)
    ledger.levels.append(Level(0, "sort", "summary", n, None, len(part.open_sizes()), max(part.open_sizes(), default=0), -1, moved, time.time() - began))
    ledger.rows_scanned, ledger.rows_shuffled = 3 * n, moved
    return answers.unionByName(finish(kept, rest.frame, rest.rows is not None))


def order_key(df: DataFrame, order_by: str | Column | list) -> Column:
    """One column to order by: a column or a struct of several; maps and variants have no order."""
    parts = order_by if isinstance(order_by, list) else [order_by]
    columns = [F.col(p) if isinstance(p, str) else p for p in parts]
    key = columns[0] if len(columns) == 1 else F.struct(*[c.alias(f"k{k}") for k, c in enumerate(columns)])
    kind = df.select(key.alias("key")).schema["key"].dataType
    if _has_map(kind):
        raise TypeError("maps and variants cannot be ordered; take an orderable part out first")
    return key


def _has_map(kind: T.DataType) -> bool:
    if isinstance(kind, (T.MapType, T.VariantType)):
        return True
    if isinstance(kind, T.ArrayType):
        return _has_map(kind.elementType)
    return isinstance(kind, T.StructType) and any(_has_map(f.dataType) for f in kind.fields)


def multi_select(df: DataFrame, order_by: str | Column | list, ranks, *, group_by: str | list[str] | None = None, settings: Settings = Settings(), nulls: str = "exclude", descending: bool = False, on_invalid: str = "error", forced_pivots: list | None = None, ledger: Ledger | None = None) -> DataFrame:
    """Exact order statistics: (groups,) rank, value, in order of rank.

    ranks: whole numbers, a rank family (sources.ranks), or a DataFrame. nulls: "exclude" leaves them out of the count; "first"
    and "last" give them the lowest or highest ranks. Ranks outside 1..n raise an error, or are dropped with on_invalid="drop";
    by group, ranks that a group does not have are always dropped. An empty rank list gives an empty result.
    """
    key = order_key(df, order_by)
    ledger = ledger if ledger is not None else Ledger()
    if group_by:
        by = [group_by] if isinstance(group_by, str) else list(group_by)
        return _grouped(df, key, ranks, by, settings, ledger)
    every = df.select(F.lit(0).cast("long").alias("sub"), key.alias("key"))
    work = every.filter("key is not null")
    kind = work.schema["key"].dataType
    row = every.agg(F.count("key").alias("n"), F.count("*").alias("all")).first()
    n, missing = row["n"], row["all"] - row["n"]
    total = n if nulls == "exclude" else row["all"]
    few, asked = R.listed(ranks, total), None
    if few is not None and len(few) <= settings.listed_ranks:
        wrong = [r for r in few if not 1 <= r <= total]
        if wrong and on_invalid == "error":
            raise ValueError(f"ranks must lie in 1..{total}")
        few = [r for r in few if 1 <= r <= total]
    else:
        asked = R.resolve(df.sparkSession, ranks, total, on_invalid).select(F.col("rank").alias("asked"))
        few = [r["asked"] for r in asked.limit(settings.listed_ranks + 1).collect()]
    listed = len(few) <= settings.listed_ranks
    if listed:
        asked = df.sparkSession.createDataFrame([(r,) for r in few], "asked long")
    place = F.lit(total + 1) - F.col("asked") if descending else F.col("asked")
    want = asked.withColumn("rank", place - (missing if nulls == "first" else 0)).withColumn("sub", F.lit(0).cast("long"))
    empty = want.filter(~F.col("rank").between(1, n)).select("asked", F.lit(None).cast(kind).alias("value")) if nulls != "exclude" else None
    want = want.filter(F.col("rank").between(1, n)).select("sub", "rank", "asked")
    if n == 0 or (listed and not few):
        answers = want.select("asked", F.lit(None).cast(kind).alias("value"))
    else:
        if listed:
            shift = missing if nulls == "first" else 0
            inside = [r for r in ((total + 1 - a if descending else a) - shift for a in few) if 1 <= r <= n]
            delta = threshold_of(gap_sizes(inside, n), n)
        else:
            delta = gap_threshold(rank_gaps(want.select("rank"), n), n)
        branch = Branch(settings.branch) if settings.branch != "auto" else choose_branch(n, delta, settings.tall)
        if settings.collapse is True or settings.collapse == "auto" and work.agg(F.approx_count_distinct("key").alias("d")).first()["d"] <= settings.collapse_values:
            answers = _collapsed(work, want)
        elif branch is Branch.SORT:
            answers = sort_and_pick(work, want, n, settings, ledger)
        else:
            forced = None
            if forced_pivots is not None:
                forced = df.sparkSession.createDataFrame([(0, sorted(set(forced_pivots)))], T.StructType([T.StructField("sub", T.LongType()), T.StructField("pivots", T.ArrayType(kind))]))
            answers = resolve(work, want, settings, ledger, delta, forced, {0: n})
    if empty is not None:
        answers = answers.unionByName(empty)
    return answers.select(F.col("asked").alias("rank"), "value").orderBy("rank")


def _collapsed(work: DataFrame, want: DataFrame) -> DataFrame:
    """Selection on the histogram of a key with few values."""
    counts = work.groupBy("sub", "key").agg(F.count("*").alias("n"))
    order = Window.partitionBy("sub").orderBy("key").rowsBetween(Window.unboundedPreceding, 0)
    spans = counts.withColumn("hi", F.sum("n").over(order)).withColumn("lo", F.col("hi") - F.col("n") + 1)
    return want.join(F.broadcast(spans.drop("sub")), F.col("rank").between(F.col("lo"), F.col("hi"))).select("asked", F.col("key").alias("value"))


def _grouped(df: DataFrame, key: Column, ranks, by: list[str], settings: Settings, ledger: Ledger) -> DataFrame:
    rows = df.select(*by, key.alias("key")).filter("key is not null")
    groups = stored(rows.groupBy(*by).agg(F.count("*").alias("n")), "groups")
    largest = groups.agg(F.max("n")).first()[0] or 0
    if isinstance(ranks, DataFrame):
        asked = groups.join(ranks, by).filter("rank between 1 and n")
    elif hasattr(ranks, "grouped"):
        asked = ranks.grouped(groups)
    else:
        asked = R.At(*ranks).grouped(groups)
    out = [F.col(b) for b in by]
    if largest <= settings.finish_rows:
        ledger.levels.append(Level(0, "sort", "none", 0, None, 0, largest, 0, 0, 0.0))
        return _by_window(rows, asked, by).orderBy(*by, "rank")
    # Groups too large for a task are at most n / finish_rows; only they are listed, numbered by place, and go level by level.
    large = stored(groups.filter(F.col("n") > settings.finish_rows).withColumn("sub", F.monotonically_increasing_id()), "large")
    named = F.broadcast(large.select(*[F.col(b).alias(f"_g{k}") for k, b in enumerate(by)], "sub"))
    same = F.lit(True)
    for k, b in enumerate(by):
        same = same & F.col(b).eqNullSafe(F.col(f"_g{k}"))
    sizes = {r["sub"]: r["n"] for r in large.select("sub", "n").collect()}
    want = stored(asked.select(*by, "rank").join(named, same).select("sub", "rank", F.struct("sub", "rank").alias("asked")), "want")
    none = [s for s in sizes if s not in {r["sub"] for r in want.select("sub").distinct().collect()}]
    work = rows.join(named, same).select("sub", "key")
    found = resolve(work.filter(~F.col("sub").isin(none)) if none else work, want, settings, ledger, sizes={s: n for s, n in sizes.items() if s not in none}) if len(none) < len(sizes) else None
    small = _by_window(rows.join(named, same, "left_anti"), asked.join(named, same, "left_anti"), by)
    if found is None:
        return small.orderBy(*by, "rank")
    answers = found.select(F.col("asked.sub").alias("sub"), F.col("asked.rank").alias("rank"), "value").join(F.broadcast(large.drop("n")), "sub")
    return answers.select(*out, "rank", "value").unionByName(small).orderBy(*by, "rank")


def _by_window(rows: DataFrame, asked: DataFrame, by: list[str]) -> DataFrame:
    """(by, rank, value) of groups that each fit a task: one shuffle by group, no pivots. Nulls in group columns match each other."""
    numbered = rows.withColumn("rank", F.row_number().over(Window.partitionBy(*by).orderBy("key")).cast("long"))
    named = asked.select(*[F.col(b).alias(f"_g{k}") for k, b in enumerate(by)], F.col("rank").alias("_rank"))
    same = F.col("rank") == F.col("_rank")
    for k, b in enumerate(by):
        same = same & F.col(b).eqNullSafe(F.col(f"_g{k}"))
    return numbered.join(named, same).select(*[F.col(b) for b in by], "rank", F.col("key").alias("value"))

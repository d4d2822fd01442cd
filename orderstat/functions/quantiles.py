"""Functions on top of multi_select; none is part of the published method."""

from __future__ import annotations

from fractions import Fraction
from itertools import combinations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from orderstat.operators.engine import multi_select
from orderstat.operators.distribute import upto
from orderstat.operators.order import numbered
from orderstat.operators.select import weighted_ranks
from orderstat.plans.policy import Settings
from orderstat.sources import ranks as R
from orderstat.sources.scratch import stored


def _by(group_by: str | list[str] | None) -> list[str]:
    return [] if not group_by else [group_by] if isinstance(group_by, str) else list(group_by)


def _sizes(df: DataFrame, key: str, by: list[str]) -> DataFrame:
    return df.filter(F.col(key).isNotNull()).groupBy(*by).agg(F.count("*").alias("n"))


def disc(df: DataFrame, key: str, fractions: list[str | Fraction], group_by=None, settings: Settings = Settings()) -> DataFrame:
    """(groups,) fraction, value: the value of rank max(1, ceil(p n)). Fractions are given exactly, as "0.95" or Fraction."""
    by, ps = _by(group_by), [Fraction(p) for p in fractions]
    found = multi_select(df, key, R.Fractions(*ps), group_by=by or None, settings=settings)
    sizes = _sizes(df, key, by)
    each = sizes.select(*by, F.explode(F.array([F.struct(F.lit(float(p)).alias("fraction"), F.greatest(F.lit(1), F.expr(f"cast((cast(n as decimal(38,0)) * {p.numerator} + {p.denominator - 1}) div {p.denominator} as bigint)")).alias("rank")) for p in ps])).alias("e")).select(*by, "e.*")
    return _met(each, found, by, "rank").select(*by, "fraction", "value")


def _met(a: DataFrame, b: DataFrame, by: list[str], *also: str) -> DataFrame:
    """Join on by (nulls match) and also."""
    renamed = b
    same = F.lit(True)
    for k, c in enumerate([*by, *also]):
        renamed = renamed.withColumnRenamed(c, f"_j{k}")
        same = same & F.col(c).eqNullSafe(F.col(f"_j{k}"))
    return a.join(renamed, same).drop(*[f"_j{k}" for k in range(len(by) + len(also))])


def cont(df: DataFrame, key: str, fractions: list[str | Fraction], group_by=None, settings: Settings = Settings()) -> DataFrame:
    """(groups,) fraction, value: linear between the ranks around 1 + p (n - 1)."""
    by, ps = _by(group_by), [Fraction(p) for p in fractions]
    sizes = _sizes(df, key, by)
    parts = [F.struct(F.lit(float(p)).alias("fraction"), F.expr(f"cast(1 + (cast(n - 1 as decimal(38,0)) * {p.numerator}) div {p.denominator} as bigint)").alias("lo"), F.expr(f"cast((cast(n - 1 as decimal(38,0)) * {p.numerator}) % {p.denominator} as double) / {p.denominator}").alias("part")) for p in ps]
    each = sizes.select(*by, "n", F.explode(F.array(parts)).alias("e")).select(*by, "n", "e.*").withColumn("hi", F.least(F.col("lo") + 1, F.col("n")))
    asked = each.select(*by, F.explode(F.array("lo", "hi")).alias("rank")).distinct()
    found = multi_select(df, key, asked if by else asked.select("rank"), group_by=by or None, settings=settings)
    low = _met(each, found.select(*by, F.col("rank").alias("lo"), F.col("value").alias("a")), by, "lo")
    both = _met(low, found.select(*by, F.col("rank").alias("hi"), F.col("value").alias("b")), by, "hi")
    return both.select(*by, "fraction", (F.col("a") + (F.col("b") - F.col("a")) * F.col("part")).alias("value"))


def median(df: DataFrame, key: str, group_by=None, settings: Settings = Settings()) -> DataFrame:
    return disc(df, key, ["0.5"], group_by, settings).drop("fraction").withColumnRenamed("value", "median")


def quartiles(df: DataFrame, key: str, group_by=None, settings: Settings = Settings()) -> DataFrame:
    return disc(df, key, ["0.25", "0.5", "0.75"], group_by, settings)


def iqr(df: DataFrame, key: str, group_by=None, settings: Settings = Settings()) -> DataFrame:
    by = _by(group_by)
    return quartiles(df, key, group_by, settings).groupBy(*by).agg((F.max("value") - F.min("value")).alias("iqr"))


def mad(df: DataFrame, key: str, group_by=None, settings: Settings = Settings()) -> DataFrame:
    """Median of the absolute deviations from the median."""
    by = _by(group_by)
    centre = median(df, key, group_by, settings)
    rows = df.select(*by, F.col(key).alias("_v"))
    met = _met(rows, centre, by) if by else rows.join(F.broadcast(centre))
    return median(met.withColumn("_dev", F.abs(F.col("_v") - F.col("median"))), "_dev", group_by, settings).withColumnRenamed("median", "mad")


def rank_slice(df: DataFrame, key: str, a: int, b: int, tie_break: list[str], settings: Settings = Settings()) -> DataFrame:
    """Rows of ranks a to b with rank; tie_break makes the order total. Two selections bound the keys that are ordered."""
    full = [key, *tie_break]
    n = df.filter(F.col(key).isNotNull()).count()
    b = min(b, n)
    if a > b:
        return df.withColumn("rank", F.lit(0).cast("long")).limit(0)
    ends = [r["value"] for r in multi_select(df, key, [a, b], settings=settings).collect()]
    low, high = ends[0], ends[-1]
    before = df.filter(F.col(key) < F.lit(low)).count()
    inside = df.filter((F.col(key) >= F.lit(low)) & (F.col(key) <= F.lit(high)))
    return numbered(inside, full).withColumn("rank", F.col("rank") + before).filter(F.col("rank").between(a, b))


def rows_at(df: DataFrame, key: str, ranks, tie_break: list[str], settings: Settings = Settings()) -> DataFrame:
    """Whole rows at the given ranks of the order (key, tie_break), which must be total, with rank."""
    full = [key, *tie_break]
    found = multi_select(df, full, ranks, settings=settings).select("rank", *[F.col(f"value.k{j}").alias(f"_k{j}") for j in range(len(full))])
    same = F.lit(True)
    for j, c in enumerate(full):
        same = same & F.col(c).eqNullSafe(F.col(f"_k{j}"))
    return df.join(found, same).drop(*[f"_k{j}" for j in range(len(full))])


def top(df: DataFrame, key: str, m: int, settings: Settings = Settings()) -> DataFrame:
    return multi_select(df, key, R.top(m), settings=settings)


def bottom(df: DataFrame, key: str, m: int, settings: Settings = Settings()) -> DataFrame:
    return multi_select(df, key, R.bottom(m), settings=settings)


def ntile_edges(df: DataFrame, key: str, m: int, settings: Settings = Settings()) -> DataFrame:
    """(tile, value): the largest value of each of m tiles, tile sizes as in ntile."""
    n = df.filter(F.col(key).isNotNull()).count()
    tiles = df.sparkSession.range(1, min(m, n) + 1).select(F.col("id").alias("tile"), (F.col("id") * (n // m) + F.least("id", F.lit(n % m))).alias("rank"))
    return multi_select(df, key, tiles.select("rank"), settings=settings).join(tiles, "rank").select("tile", "value")


def equi_depth(df: DataFrame, key: str, m: int, settings: Settings = Settings()) -> DataFrame:
    """(bin, lo, hi, n): bins between the m-quantiles, open below and closed above, with exact counts."""
    edges = ntile_edges(df, key, m, settings).groupBy("value").agg(F.max("tile").alias("tile"))
    rows = label(df, key, edges.select("value")).filter(F.col(key).isNotNull())
    return rows.groupBy("bin").agg(F.min(key).alias("lo"), F.max(key).alias("hi"), F.count("*").alias("n"))


#: Edges up to which they are broadcast as one array; more are met in groups, by a join.
MOST_EDGES = 1 << 17


def label(df: DataFrame, key: str, edges: DataFrame) -> DataFrame:
    """df with bin: how many edges (column value) lie under the key."""
    met = _placed(df, key, edges)
    return met.withColumn("bin", (F.col("_count") - F.col("_hit").cast("int")).cast("int")).drop("_count", "_hit")


def _placed(df: DataFrame, key: str, edges: DataFrame, most: int | None = None) -> DataFrame:
    """df with _count, the distinct edges at most the key, and _hit, whether one equals it.

    Up to most edges are one array, searched by halving. Of more, every so many-th is in that array; it tells the group of
    edges among which the search goes on, and a row meets its group's edges in a join.
    """
    most = most or MOST_EDGES
    edges = edges.select("value").filter("value is not null").distinct()
    n = edges.count()
    if n <= most:
        packed = edges.agg(F.array_sort(F.collect_list("value")).alias("_edges"))
        met = df.join(F.broadcast(packed)).withColumn("_count", upto(F.col(key), F.col("_edges"), n))
        hit = F.coalesce((F.col("_count") > 0) & (F.try_element_at("_edges", F.col("_count").cast("int")) == F.col(key)), F.lit(False))
        return met.withColumn("_count", F.coalesce(F.col("_count"), F.lit(0)).cast("long")).withColumn("_hit", hit).drop("_edges")
    step = -(-n // most)
    placed = stored(numbered(edges, ["value"], out="_place").withColumn("_group", F.expr(f"(_place - 1) div {step} + 1")), "edges")
    fences = placed.filter(f"_place % {step} = {1 % step}").agg(F.array_sort(F.collect_list("value")).alias("_fences"))
    groups = placed.groupBy("_group").agg(F.array_sort(F.collect_list("value")).alias("_edges"))
    met = df.join(F.broadcast(fences)).withColumn("_group", F.coalesce(upto(F.col(key), F.col("_fences"), most), F.lit(0)).cast("long")).drop("_fences")
    met = met.join(groups, "_group", "left").withColumn("_in", F.coalesce(upto(F.col(key), F.col("_edges"), step), F.lit(0)))
    hit = F.coalesce((F.col("_in") > 0) & (F.try_element_at("_edges", F.col("_in").cast("int")) == F.col(key)), F.lit(False))
    return met.withColumn("_count", F.when(F.col("_group") > 0, (F.col("_group") - 1) * step + F.col("_in")).otherwise(0)).withColumn("_hit", hit).drop("_group", "_edges", "_in")


def _edges(df: DataFrame, key: str, lo: str, hi: str, settings: Settings) -> DataFrame:
    """One row: n, ranks a and z kept, and their values."""
    n = df.filter(F.col(key).isNotNull()).count()
    a, z = int(Fraction(lo) * n) + 1, n - int((1 - Fraction(hi)) * n)
    ends = [r["value"] for r in multi_select(df, key, [a, z], settings=settings).collect()]
    return df.sparkSession.createDataFrame([(n, a, z, ends[0], ends[-1])], "n long, a long, z long, low double, high double")


def trimmed_mean(df: DataFrame, key: str, lo: str = "0.05", hi: str = "0.95", settings: Settings = Settings()) -> DataFrame:
    """(mean): of the ranks from lo n + 1 to hi n; values equal to an edge count as often as their ranks lie inside."""
    ends = _edges(df, key, lo, hi, settings)
    v = F.col(key).cast("double")
    sums = df.filter(F.col(key).isNotNull()).join(F.broadcast(ends)).agg(
        F.sum(F.when((v > F.col("low")) & (v < F.col("high")), v).otherwise(0.0)).alias("s"), F.sum((v <= F.col("low")).cast("long")).alias("upto"), F.sum((v < F.col("high")).cast("long")).alias("under"), F.first("a").alias("a"), F.first("z").alias("z"), F.first("low").alias("low"), F.first("high").alias("high"),
    )
    count = F.col("z") - F.col("a") + 1
    own = F.col("low") * (F.least("upto", "z") - F.col("a") + 1) + F.when(F.col("high") > F.col("low"), F.col("high") * (F.col("z") - F.col("under"))).otherwise(0.0)
    return sums.select(((F.col("s") + own) / count).alias("mean"))


def winsor_mean(df: DataFrame, key: str, lo: str = "0.05", hi: str = "0.95", settings: Settings = Settings()) -> DataFrame:
    """(mean) with values outside the edges pulled to them."""
    ends = _edges(df, key, lo, hi, settings)
    return df.filter(F.col(key).isNotNull()).join(F.broadcast(ends)).agg(F.avg(F.greatest(F.least(F.col(key).cast("double"), "high"), "low")).alias("mean"))


def rank_of(df: DataFrame, key: str, values: DataFrame) -> DataFrame:
    """(value, lt, eq) for the distinct values of a list of any length: one counting pass, one search for each row."""
    kind = df.schema[key].dataType
    values = values.select(F.col("value").cast(kind).alias("value")).filter("value is not null").distinct()
    keys = df.select(F.col(key).alias("_key")).filter("_key is not null")
    counts = _placed(keys, "_key", values).groupBy("_count", "_hit").agg(F.count("*").alias("n"))
    # By value: rows under it, which are between it and the edge before, and rows equal to it; then running sums in two steps.
    each = counts.select((F.col("_count") + (~F.col("_hit")).cast("int")).alias("_place"), F.when(F.col("_hit"), 0).otherwise(F.col("n")).alias("under"), F.when(F.col("_hit"), F.col("n")).otherwise(0).alias("eq"))
    told = numbered(values, ["value"], out="_place").join(each.groupBy("_place").agg(F.sum("under").alias("under"), F.sum("eq").alias("eq")), "_place", "left").na.fill(0, ["under", "eq"])
    told = told.withColumn("_block", F.expr("_place div 65536"))
    inner = Window.partitionBy("_block").orderBy("_place").rowsBetween(Window.unboundedPreceding, 0)
    sums = told.groupBy("_block").agg(F.sum(F.col("under") + F.col("eq")).alias("_n"))
    before = sums.withColumn("_before", F.sum("_n").over(Window.partitionBy(F.lit(0)).orderBy("_block")) - F.col("_n")).drop("_n")
    run = told.withColumn("_run", F.sum(F.col("under") + F.col("eq")).over(inner)).join(F.broadcast(before), "_block")
    return run.select("value", (F.col("_before") + F.col("_run") - F.col("eq")).alias("lt"), "eq")


def weighted(df: DataFrame, key: str, weight: str, fractions: list[str], settings: Settings = Settings()) -> DataFrame:
    """(fraction, value): the smallest value with fraction of all weight up to it; all fractions share the passes."""
    total = df.filter(F.col(key).isNotNull()).agg(F.sum(weight)).first()[0] or 0
    ps = [Fraction(p) for p in fractions]
    wanted = [float(p) * total if isinstance(total, float) else p * Fraction(total) for p in ps]
    names = df.sparkSession.createDataFrame([(k, float(p)) for k, p in enumerate(ps)], "no int, fraction double")
    return weighted_ranks(df, key, weight, wanted, settings).join(F.broadcast(names), "no").select("fraction", "value")


def percent_rank(df: DataFrame, key: str, values: DataFrame) -> DataFrame:
    """(value, percent_rank, cume_dist) of a list of values among the rows of df, as the window functions of these names define them."""
    n = df.filter(F.col(key).isNotNull()).count()
    return rank_of(df, key, values).select("value", (F.col("lt") / F.lit(max(1, n - 1))).alias("percent_rank"), ((F.col("lt") + F.col("eq")) / F.lit(max(1, n))).alias("cume_dist"))


def normalised(df: DataFrame, key: str, target: DataFrame, value: str, m: int, settings: Settings = Settings()) -> DataFrame:
    """df with mapped: the key's m-quantile bin answered by the target column's quantile of the same bin (quantile normalisation)."""
    edges = multi_select(df, key, R.even(m), settings=settings)
    n = target.filter(F.col(value).isNotNull()).count()
    tops = target.sparkSession.range(1, m + 1).select(F.col("id").alias("tile"), F.expr(f"cast((id * {n} + {m - 1}) div {m} as bigint)").alias("rank"))
    known = multi_select(target, value, tops.select("rank").filter("rank > 0").distinct(), settings=settings).join(tops, "rank").select("tile", F.col("value").alias("mapped"))
    return label(df, key, edges.select("value")).withColumn("tile", F.when(F.col(key).isNotNull(), F.col("bin") + 1)).join(F.broadcast(known), "tile", "left").drop("bin", "tile")


def cut_at(df: DataFrame, key: str, fraction: str, settings: Settings = Settings()) -> DataFrame:
    """df with part: "train" up to the value of rank ceil(fraction n), "test" over it, null for null keys."""
    edge = disc(df, key, [fraction], settings=settings).select(F.col("value").alias("_edge"))
    return df.join(F.broadcast(edge)).withColumn("part", F.when(F.col(key) <= F.col("_edge"), "train").when(F.col(key) > F.col("_edge"), "test")).drop("_edge")


def range_bounds(df: DataFrame, key: str, parts: int, settings: Settings = Settings()) -> DataFrame:
    """(part, lo, hi, n): exact bounds of so many ranges of about equal size, for range partitioning; ties stay together."""
    return equi_depth(df, key, parts, settings).withColumnRenamed("bin", "part")


def _per_set(df: DataFrame, keys: list[str], sets: list[tuple[str, ...]], key: str, fractions: list[str], settings: Settings) -> DataFrame:
    """One grouped selection over all grouping sets: rows are expanded once, with nulls for what a set leaves out and its number."""
    kinds = {k: df.schema[k].dataType for k in keys}
    each = [F.struct(*[(F.col(k) if k in s else F.lit(None).cast(kinds[k])).alias(k) for k in keys], F.lit(sum(1 << (len(keys) - 1 - j) for j, k in enumerate(keys) if k not in s)).alias("grouping_id")) for s in sets]
    rows = df.select(F.explode(F.array(each)).alias("g"), F.col(key).alias("_v")).select("g.*", "_v")
    return disc(rows, "_v", fractions, [*keys, "grouping_id"], settings)


def cube(df: DataFrame, keys: list[str], key: str, fractions: list[str], settings: Settings = Settings()) -> DataFrame:
    return _per_set(df, keys, [s for r in range(len(keys), -1, -1) for s in combinations(keys, r)], key, fractions, settings)


def rollup(df: DataFrame, keys: list[str], key: str, fractions: list[str], settings: Settings = Settings()) -> DataFrame:
    return _per_set(df, keys, [tuple(keys[:r]) for r in range(len(keys), -1, -1)], key, fractions, settings)


def norm(vector: Column) -> Column:
    """Length of a vector column."""
    return F.sqrt(F.aggregate(F.transform(vector, lambda x: x.cast("double") * x), F.lit(0.0), lambda a, x: a + x))

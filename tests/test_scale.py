"""Ways that large or awkward inputs take: wide keys, many edges, many groups, many ties, no shared folder."""

import random
from bisect import bisect_left, bisect_right
from collections import Counter

import pytest
from pyspark.sql import functions as F

from orderstat import Settings, multi_select
from orderstat.functions import quantiles
from orderstat.operators import baselines, select
from orderstat.operators.distribute import bucketize
from orderstat.operators.engine import Ledger
from orderstat.operators.order import numbered
from orderstat.plans import costs
from orderstat.sources import ranks as R
from orderstat.sources import scratch

SMALL = Settings(finish_rows=50, min_fanout=8)


def plain_weighted(pairs, target):
    reached = 0
    for v in sorted({v for v, _ in pairs}):
        reached += sum(w for x, w in pairs if x == v)
        if reached >= target:
            return v, reached
    return None


def cases():
    r = random.Random(8)
    wide = [((1 << 60) + r.randrange(4000), r.randrange(1, 9)) for _ in range(2000)]
    return {"wide": wide, "equal": [(7, 2)] * 900, "zero weights": [(r.randrange(500), r.choice((0, 0, 3))) for _ in range(900)], "one huge": [(k, 1) for k in range(700)] + [(350, 10**9)]}


@pytest.mark.parametrize("name", list(cases()))
def test_weighted(spark, name):
    pairs = cases()[name]
    total = sum(w for _, w in pairs)
    targets = [0, 1, total // 3, total / 2, total, total + 1]
    rows = spark.createDataFrame(pairs, "v long, w long").repartition(3)
    got = {r["no"]: (r["value"], r["cum_weight"]) for r in select.weighted_ranks(rows, "v", "w", targets, SMALL).collect()}
    assert got == {k: found for k, t in enumerate(targets) if (found := plain_weighted(pairs, t))}


def test_weighted_doubles_and_decimals(spark):
    r = random.Random(3)
    pairs = [(r.random(), r.randrange(1, 100) / 4) for _ in range(1500)]
    for kind in ("double", "decimal(12,2)"):
        rows = spark.createDataFrame(pairs, "v double, w double").withColumn("w", F.col("w").cast(kind))
        got = {x["fraction"]: x["value"] for x in quantiles.weighted(rows, "v", "w", ["0.1", "0.5", "0.9"], SMALL).collect()}
        total = sum(w for _, w in pairs)
        assert got == {p: plain_weighted(pairs, p * total)[0] for p in (0.1, 0.5, 0.9)}
    assert select.weighted_rank(rows.limit(0), "v", "w", 0, SMALL).count() == 0


@pytest.mark.parametrize("most", [4, 100, 10_000])
def test_edges_beyond_one_array(spark, monkeypatch, most):
    monkeypatch.setattr(quantiles, "MOST_EDGES", most)
    r = random.Random(most)
    keys, edges = [r.randrange(3000) for _ in range(2000)] + [None], sorted({r.randrange(3000) for _ in range(700)})
    rows = spark.createDataFrame([(k,) for k in keys], "k long").repartition(3)
    listed = spark.createDataFrame([(e,) for e in edges * 2], "value long").repartition(2)
    got = Counter(tuple(x) for x in quantiles.label(rows, "k", listed).collect())
    assert got == Counter((k, bisect_left(edges, k) if k is not None else 0) for k in keys)
    held = sorted(k for k in keys if k is not None)
    assert {x["value"]: (x["lt"], x["eq"]) for x in quantiles.rank_of(rows, "k", listed).collect()} == {e: (bisect_left(held, e), bisect_right(held, e) - bisect_left(held, e)) for e in edges}
    assert quantiles.label(rows, "k", listed.limit(0)).filter("bin <> 0").isEmpty()


def test_wide_longs_in_every_distribution(spark):
    keys = [(1 << 60) + k for k in range(40)] + [-0, 5]
    work = spark.createDataFrame([(0, k) for k in keys], "sub long, key long")
    pivots = [(1 << 60) + 3, (1 << 60) + 4, (1 << 60) + 5]
    told = spark.createDataFrame([(0, pivots)], "sub long, pivots array<long>")
    want = Counter(2 * bisect_right(pivots, k) - (k in pivots) for k in keys)
    for how in ("auto", "search", "case", "bucketizer", "join"):
        assert Counter(r["bucket"] for r in bucketize(work, told, 3, how, {0: pivots} if how == "auto" else None).collect()) == want


def test_zeros_and_nan_in_the_fast_distribution(spark):
    keys = [0.0, -0.0, float("nan"), float("inf"), float("-inf"), 1.5]
    work = spark.createDataFrame([(0, k) for k in keys], "sub long, key double")
    told = spark.createDataFrame([(0, [0.0, 1.5])], "sub long, pivots array<double>")
    a, b = (sorted(r["bucket"] for r in bucketize(work, told, 2, how, {0: [0.0, 1.5]}).collect()) for how in ("auto", "search"))
    assert a == b == [0, 1, 1, 3, 4, 4]


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_many_groups_with_a_large_one(spark):
    """100,000 groups, one of which holds a third of all rows and is too large for a task: nothing goes through one partition."""
    rows = spark.range(150_000).select(F.when(F.col("id") % 3 == 0, -1).otherwise(F.col("id")).alias("g"), F.xxhash64("id").alias("v"))
    ledger = Ledger()
    found = multi_select(rows, "v", R.Fractions("0.5"), group_by="g", settings=Settings(finish_rows=10_000), ledger=ledger)
    assert "SinglePartition" not in plan(found) and len(ledger.levels) >= 1
    got = found.count()
    assert got == 100_001
    middle = sorted(r["v"] for r in rows.filter("g = -1").collect())[(50_000 + 1) // 2 - 1]
    assert found.filter("g = -1").first()["value"] == middle


def test_slice_of_half_a_table(spark):
    rows = spark.range(20_000).select(F.col("id"), (F.xxhash64("id") % 100).alias("k"))
    got = quantiles.rank_slice(rows, "k", 5_000, 15_000, ["id"])
    assert "Window" not in plan(got) and "SinglePartition" not in plan(got)
    want = sorted((r["k"], r["id"]) for r in rows.collect())[4_999:15_000]
    assert [(r["k"], r["id"]) for r in sorted(got.collect(), key=lambda r: r["rank"])] == want


def test_numbering_spreads_ties(spark):
    rows = spark.range(9_000).select(F.lit(7).alias("k"), "id")
    out = numbered(rows, ["k"], 6)
    assert sorted(r["rank"] for r in out.collect()) == list(range(1, 9_001))
    sizes = [r["count"] for r in out.groupBy(F.spark_partition_id()).count().collect()]
    assert max(sizes) < 9_000


@pytest.mark.parametrize("margin", [0.001, 4.0])
def test_sampled_predecessor(spark, margin):
    """Ranks are right whether the margin holds (one round) or is far too small (found out by counts, tried again)."""
    r = random.Random(2)
    values = [r.randrange(10**6) for _ in range(8_000)] + [77] * 500
    rows = spark.createDataFrame([(v,) for v in values], "v long").repartition(4)
    ranks = [1, 2, 100, 4_000, 4_001, 8_499, 8_500, 9_999]
    ledger = Ledger()
    got = {x["rank"]: x["value"] for x in baselines.sampled_select(rows, "v", ranks, 3, ways=16, oversample=8, margin=margin, ledger=ledger).collect()}
    held = sorted(values)
    assert got == {k: held[k - 1] for k in ranks if k <= 8_500}
    assert margin > 1 or len(ledger.levels) > 1
    assert ledger.rows_shuffled < 8_500 * len(ledger.levels)


@pytest.mark.parametrize("pivots", ["median", "random", "first"])
def test_binary_prune_by_any_pivot(spark, pivots):
    rows = spark.range(3_000).select((F.xxhash64("id") % 2_000).alias("v"))
    held = sorted(x["v"] for x in rows.collect())
    got = {x["rank"]: x["value"] for x in baselines.binary_prune(rows, "v", [1, 1_000, 1_001, 3_000], 200, pivots=pivots).collect()}
    assert got == {k: held[k - 1] for k in (1, 1_000, 1_001, 3_000)}


def test_rank_error_by_one_search(spark):
    rows = spark.createDataFrame([(float(k // 3),) for k in range(300)], "v double")
    answers = spark.createDataFrame([(10, 3.0), (10, 5.0), (200, 0.5)], "rank long, value double")
    assert sorted(tuple(r) for r in costs.rank_error(rows, "v", answers).select("rank", "value", "lt", "eq", "error").collect()) == [(10, 3.0, 9, 3, 0), (10, 5.0, 15, 3, 6), (200, 0.5, 3, 0, 196)]


def test_collapse_is_chosen_for_few_values(spark):
    rows = spark.range(5_000).select((F.col("id") % 9).alias("few"), F.col("id").alias("many"))
    for key in ("few", "many"):
        ledger = Ledger()
        held = sorted(r[key] for r in rows.collect())
        got = multi_select(rows, key, [1, 2_500, 5_000], settings=Settings(branch="partition", collapse="auto", collapse_values=100, finish_rows=500), ledger=ledger).collect()
        assert [tuple(r) for r in got] == [(k, held[k - 1]) for k in (1, 2_500, 5_000)] and bool(ledger.levels) == (key == "many")


def test_percent_rank_normalisation_and_cut(spark):
    a = spark.createDataFrame([(k, float(k % 10)) for k in range(100)], "id long, v double")
    b = spark.createDataFrame([(float(k * k),) for k in range(50)], "w double")
    told = {r["value"]: (round(r["percent_rank"], 6), round(r["cume_dist"], 6)) for r in quantiles.percent_rank(a, "v", a.select(F.col("v").alias("value"))).collect()}
    assert told == {float(j): (round(10 * j / 99, 6), (j + 1) / 10) for j in range(10)}
    mapped = {r["v"]: r["mapped"] for r in quantiles.normalised(a, "v", b, "w", 10).collect()}
    assert [mapped[float(j)] for j in range(10)] == [float((5 * (j + 1) - 1) ** 2) for j in range(10)]
    assert Counter(r["part"] for r in quantiles.cut_at(a, "v", "0.8").collect()) == {"train": 80, "test": 20}


def test_no_private_folder_on_a_cluster(spark, monkeypatch):
    class Context:
        master, applicationId = "spark://host:7077", "app"

        def getCheckpointDir(self):
            return None

    class Session:
        sparkContext = Context()

        class conf:
            @staticmethod
            def get(key, default=None):
                return default

    with pytest.raises(RuntimeError):
        scratch.shared_dir(Session())
    Context.master = "local[4]"
    assert scratch.shared_dir(Session()).startswith("file://")


def test_cleanup(spark, monkeypatch, tmp_path):
    monkeypatch.setattr(scratch, "shared_dir", lambda _: f"file://{tmp_path}/run")
    scratch.stored(spark.range(3), "x")
    assert (tmp_path / "run").exists()
    scratch.cleanup(spark)
    assert not (tmp_path / "run").exists()

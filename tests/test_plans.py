import random
from fractions import Fraction

import pytest

from orderstat.plans import costs, gaps
from orderstat.plans.policy import Branch, Settings, TallCache, choose_branch
from orderstat.sources import ranks as R


def test_exponent():
    assert [TallCache.of(e).d for e in ("0.5", "1", "2", "4")] == [5, 3, 2, 2]


@pytest.mark.parametrize("n, eps, limit", [(6000, "0.5", 2508), (60000, "1", 6447), (600000, "2", 11292), (10**9, "1", 9_457_000)])
def test_thresholds(n, eps, limit):
    tall = TallCache.of(eps)
    assert abs(tall.threshold(n) - limit) <= limit * 0.001
    assert choose_branch(n, tall.threshold(n), tall) is Branch.SORT and choose_branch(n, tall.threshold(n) + 1, tall) is Branch.PARTITION


def test_exact_at_equality():
    # d = 3: (2 n)^3 = delta^4 with n = 2^7 and delta = 2^6.
    assert TallCache.of("1").sorts_by_fanout(128, 64) and not TallCache.of("1").sorts_by_fanout(128, 65)


def test_second_condition_never_alone():
    r = random.Random(1)
    for _ in range(5000):
        n, tall = r.randint(2, 10**12), TallCache.of(r.choice(["0.1", "0.5", "1", "2", "3", "7"]))
        delta = r.randint(1, n)
        assert tall.sorts_by_fanout(n, delta) or not tall.sorts_by_blocks(n, delta)


def test_fan_out_within_blocks_when_partitioning():
    r = random.Random(2)
    for _ in range(2000):
        n, tall = r.randint(2, 10**12), TallCache.of(r.choice(["0.5", "1", "2"]))
        delta = r.randint(1, n)
        if choose_branch(n, delta, tall) is Branch.PARTITION:
            assert costs.k2_ok(n, delta, tall)


@pytest.mark.parametrize("ranks, n, delta", [([1, 2, 3, 8], 15, 8), ([18, 22, 27, 31, 52, 55, 60, 66], 68, 18), ([1], 10, 10), (list(range(1, 11)), 10, 1)])
def test_threshold(spark, ranks, n, delta):
    frame = R.of(spark, ranks)
    for limit in (1000, 1):
        found = gaps.rank_gaps(frame, n, limit)
        assert sorted(r["size"] for r in found.collect()) == sorted(gaps.gap_sizes(ranks, n))
        assert gaps.gap_threshold(found, n) == delta == gaps.threshold_of(gaps.gap_sizes(ranks, n), n)


def test_no_ranks(spark):
    assert [tuple(r) for r in gaps.rank_gaps(R.of(spark, []), 5).collect()] == [(0, 6, 6)]


def test_fractions_in_whole_numbers():
    assert R.fraction_rank("0.07", 100) == 7 and R.fraction_rank(Fraction(1, 3), 10) == 4 and R.fraction_rank("0", 5) == 1


def test_invalid_ranks(spark):
    with pytest.raises(ValueError):
        R.resolve(spark, [0, 3], 5)
    assert sorted(r["rank"] for r in R.resolve(spark, [0, 3, 3, 9], 5, "drop").collect()) == [3]


def test_settings_do_not_take_part_in_the_branch():
    assert Settings(finish_rows=1).tall == Settings(finish_rows=10**9).tall


def test_weighted_select(spark):
    rows = spark.createDataFrame([("a", 1, 0), ("a", 2, 5), ("a", 2, 1), ("b", 9, 2), (None, 4, 3)], "g string, v int, w int")
    assert sorted((r["g"] or "", r["v"], r["cum_weight"]) for r in gaps.weighted_select(rows, "v", "w", 2, ["g"]).collect()) == [("", 4, 3), ("a", 2, 6), ("b", 9, 2)]
    assert gaps.weighted_select(rows, "v", "w", 100).count() == 0

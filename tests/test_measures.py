"""The measure queries read whole tables."""

from pathlib import Path

import duckdb
import pytest
from pyspark.sql import functions as F

from orderstat import catalog
from orderstat.functions import sqlapi
from orderstat.operators.engine import multi_select
from orderstat.plans.policy import Settings
from orderstat.sources.tables import table


def test_survivors_count_every_row(spark, small):
    levels = catalog._levels(catalog._work(spark, small))
    assert levels[0][0] == table(spark, small, "lineitem").count() > 3000 and levels[0][2]
    assert [tuple(r) for r in catalog.QUERIES["survivors_by_level"](spark, small).collect()] == [(True, True)]


@pytest.mark.parametrize("sf", ["0.001", "0.01"])
def test_kernel_costs(spark, small, sf):
    where = small.replace("0.001", sf)
    got = {(r["family"], r["m"]): r for r in catalog.QUERIES["kernel_costs"](spark, where).collect()}
    assert len(got) == 14 and all(r["comparisons_to_bound"] <= 12 for r in got.values())


def test_no_row_caps():
    import inspect

    assert not any(".limit(" in inspect.getsource(f) for f in (catalog.survivors_by_level, catalog._levels, catalog.kernel_costs))


def from_sql(name, where):
    db = duckdb.connect()
    for t in ("lineitem", "orders"):
        if Path(f"{where}/{t}.parquet").exists():
            db.execute(f"CREATE VIEW {t} AS SELECT * FROM '{where}/{t}.parquet'")
    return db.execute(catalog.SQL[name]).fetchall()


def test_cost_table_lists_sizes_not_gaps(spark, small, monkeypatch):
    """The driver gets the distinct gap sizes, at most sqrt(2 n + 2), also where there are n / 2 gaps."""
    frame, got, where = type(spark.range(1)), [], small.replace("0.001", "0.01")
    collect = frame.collect
    monkeypatch.setattr(frame, "collect", lambda df: got.append(collect(df)) or got[-1])
    n = table(spark, where, "lineitem").count()
    rows = catalog.QUERIES["cost_table"](spark, where).collect()
    assert max(len(g) for g in got) <= (2 * n + 2) ** 0.5
    assert sorted(map(tuple, rows)) == sorted(from_sql("cost_table", where))


def test_wide_keys_beyond_longs(spark, small, tmp_path):
    rows = table(spark, small, "lineitem").withColumn("l_orderkey", F.expr("l_orderkey + if(l_orderkey > 1000, 8000000L, 0L)"))
    rows.write.parquet(f"{tmp_path}/lineitem.parquet")
    upto, want, total = 0, None, sum(r["l_quantity"] for r in rows.collect())
    for k, w in sorted((r["l_orderkey"] * 1152921504606 + r["l_linenumber"], r["l_quantity"]) for r in rows.collect()):
        upto += w
        if want is None and 2 * upto >= total:
            want = k
    assert max(r["l_orderkey"] for r in rows.collect()) * 1152921504606 > 2**63
    found = catalog.QUERIES["weighted_select_wide_keys"](spark, str(tmp_path))
    assert found.dtypes == [("value", "bigint")] and [r["value"] for r in found.collect()] == [want]
    assert [tuple(r) for r in catalog.QUERIES["weighted_select_wide_keys"](spark, small).collect()] == from_sql("weighted_select_wide_keys", small)


@pytest.mark.parametrize("name, least", [("fig_example", 4), ("rank_family_source", 13), ("udtf_gap_table", 100)])
def test_follows_its_table(spark, small, name, least):
    found = catalog.QUERIES[name](spark, small)
    rows = sorted(map(tuple, found.collect()))
    assert rows == sorted(from_sql(name, small)) and len(rows) >= least


def test_published_example_and_entry_points(spark):
    """What the queries had as literals before: the fifteen numbers, the gaps between two ranks, a family of 1,000."""
    fifteen = [67, 30, 45, 33, 15, 99, 26, 90, 55, 9, 96, 45, 95, 31, 3]
    got = multi_select(spark.createDataFrame([(x,) for x in fifteen], "x long"), "x", [1, 2, 3, 8], settings=Settings(branch="partition", pivots="paper", finish_rows=4))
    assert sorted(map(tuple, got.collect())) == [(1, 3), (2, 9), (3, 15), (8, 45)]
    sqlapi.register(spark)
    assert sorted(map(tuple, spark.sql("SELECT * FROM gap_table(array(4L, 9L), 20)").collect())) == [(1, 0, 4, 4), (2, 4, 9, 5), (3, 9, 21, 12)]
    family = spark.read.format("rank_family").option("kind", "geometric").option("n", 1000).load()
    assert sorted(r["rank"] for r in family.collect()) == [1 << j for j in range(10)]

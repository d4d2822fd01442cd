"""One query for each method, variant, baseline, measure and workload, with its SQL."""

from __future__ import annotations

import uuid
from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from orderstat import workloads as W
from orderstat.functions import incremental, quantiles, relational, sqlapi
from orderstat.operators import baselines, engine, kernel, select
from orderstat.operators.cachesim import BlockCache
from orderstat.operators.distribute import bucketize
from orderstat.operators.engine import Ledger, multi_select
from orderstat.operators.partition import bucket_counts, multi_partition, pivot_ranks
from orderstat.plans import costs, gaps
from orderstat.plans.policy import Settings, TallCache, choose_branch
from orderstat.sources import ranks as R
from orderstat.sources.scratch import shared_dir
from orderstat.sources.tables import register, table

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}

PRICE = "l_extendedprice"
SMALL = Settings(finish_rows=2000)
#: Literal instances of the published figures.
SIXTY_EIGHT, PIVOTS, EIGHT = list(range(1, 69)), [16, 34, 52], [18, 22, 27, 31, 52, 55, 60, 66]

#: SQL conditions on a row number rn of n rows, by family.
WHERE = {
    "median": "rn = (n + 1) // 2",
    "minimum": "rn = 1",
    "maximum": "rn = n",
    "quartiles": "rn IN ((n + 3) // 4, (2 * n + 3) // 4, (3 * n + 3) // 4)",
    "deciles": "rn IN (SELECT (i * n + 9) // 10 FROM range(1, 10) t(i))",
    "percentiles": "rn IN (SELECT (i * n + 99) // 100 FROM range(1, 100) t(i))",
    "permille": "rn IN (SELECT (i * n + 999) // 1000 FROM range(1, 1000) t(i))",
    "tail": "rn IN ((n + 1) // 2, (9 * n + 9) // 10, (95 * n + 99) // 100, (99 * n + 99) // 100, (999 * n + 999) // 1000, (9999 * n + 9999) // 10000)",
    "top100": "rn > n - 100",
    "middle": "rn BETWEEN n // 2 AND n // 2 + n // 100 - 1",
    "clusters": "rn IN (SELECT (c * n) // 10 + 3 * j FROM range(1, 10) a(c), range(0, 50) b(j))",
    "geometric": "rn IN (SELECT CAST(power(2, j) AS BIGINT) FROM range(0, 62) t(j))",
    "half_dense": "rn <= n // 2 + 1",
    "everything": "true",
    "nothing": "false",
}


def by_number(source: str, key: str, where: str, value: str | None = None, order: str | None = None) -> str:
    return f"WITH v AS (SELECT {key} AS k FROM {source}), o AS (SELECT k, row_number() OVER (ORDER BY {order or 'k'}) AS rn, count(*) OVER () AS n FROM v WHERE k IS NOT NULL) SELECT CAST(rn AS BIGINT) AS rank, {value or 'k'} AS value FROM o WHERE {where}"


def grouped_by_number(source: str, by: list[str], key: str, where: str, value: str = "k") -> str:
    g = ", ".join(by)
    return f"WITH v AS (SELECT {g}, {key} AS k FROM {source}), o AS (SELECT *, row_number() OVER (PARTITION BY {g} ORDER BY k) AS rn, count(*) OVER (PARTITION BY {g}) AS n FROM v WHERE k IS NOT NULL) SELECT {g}, CAST(rn AS BIGINT) AS rank, {value} AS value FROM o WHERE {where}"


def query(sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[f.__name__] = f
        if sql is not None:
            SQL[f.__name__] = sql
        return f

    return add


def family(name: str, source: str, key: str, kind: str, *, expr=None, settings: Settings = Settings(), shape: Callable[[DataFrame], DataFrame] = lambda d: d, sql_key: str | None = None, sql_value: str | None = None) -> None:
    """A selection of one rank family over one column."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return shape(multi_select(table(spark, sf_dir, source), expr() if expr else key, W.FAMILIES[kind], settings=settings))

    run.__name__ = name
    query(by_number(source, sql_key or key, WHERE[kind], sql_value))(run)


for _name, _kind in {"median_price": "median", "quartiles_price": "quartiles", "deciles_price": "deciles", "percentiles_price": "percentiles", "permille_price": "permille", "tail_price": "tail", "top100_price": "top100", "mid_window_price": "middle", "clusters_price": "clusters", "geometric_price": "geometric", "half_dense_price": "half_dense"}.items():
    family(_name, "lineitem", PRICE, _kind)
family("all_ranks_acctbal", "customer", "c_acctbal", "everything")
family("empty_ranks", "lineitem", PRICE, "nothing")
family("ties_quantity", "lineitem", "l_quantity", "deciles")
family("ties_quantity_tail", "lineitem", "l_quantity", "tail")
family("ties_discount", "lineitem", "l_discount", "tail")
family("ties_linenumber", "lineitem", "l_linenumber", "tail")
family("ties_returnflag", "lineitem", "l_returnflag", "tail", settings=Settings(branch="partition"))
family("constant_key", "lineitem", "", "quartiles", expr=lambda: F.lit(7).alias("seven"), settings=Settings(branch="partition"), sql_key="7")
family("names_customer", "customer", "c_name", "quartiles", settings=Settings(branch="partition", finish_rows=100))
family("names_part", "part", "p_name", "tail", settings=Settings(branch="partition", finish_rows=100))
family("urls_pages", "pages", "url", "quartiles", settings=Settings(branch="partition", finish_rows=20))
family("event_ts", "events", "ts", "tail")
family("ship_dates", "lineitem", "l_shipdate", "quartiles")
family("decimal_totalprice", "orders", "o_totalprice", "tail", expr=lambda: F.col("o_totalprice").cast("decimal(18,2)"), sql_key="CAST(o_totalprice AS DECIMAL(18,2))")
family("nulls_excluded", "lineitem", PRICE, "tail", expr=lambda: F.expr("CASE WHEN l_quantity > 45 THEN NULL ELSE l_extendedprice END"), sql_key="CASE WHEN l_quantity > 45 THEN NULL ELSE l_extendedprice END")
family("html_length_quartiles", "pages", "html", "quartiles", expr=lambda: F.char_length("html"), sql_key="length(html)", sql_value="CAST(k AS INTEGER)")
family("turn_length_quartiles", "conversations", "text", "quartiles", expr=lambda: F.char_length("text"), sql_key="length(text)", sql_value="CAST(k AS INTEGER)")
family("json_k_deciles", "events", "props", "deciles", expr=lambda: F.get_json_object("props", "$.k").cast("long"), sql_key="CAST(json_extract_string(props, '$.k') AS BIGINT)")
family("vectors_norm_quartiles", "embeddings", "embedding", "quartiles", expr=lambda: F.round(quantiles.norm(F.col("embedding")), 6), sql_key="round(sqrt(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x))), 6)")
family("struct_key_lineitem", "lineitem", "", "tail", expr=lambda: F.struct("l_shipdate", "l_orderkey", "l_linenumber", "l_partkey"), settings=SMALL, shape=lambda d: d.select("rank", F.to_json(F.array(F.col("value.l_orderkey"), F.col("value.l_linenumber"), F.col("value.l_partkey"))).alias("value")), sql_key="{'s': l_shipdate, 'o': l_orderkey, 'l': l_linenumber, 'p': l_partkey}", sql_value="'[' || k.o || ',' || k.l || ',' || k.p || ']'")
family("vectors_lexicographic", "embeddings", "embedding", "quartiles", settings=Settings(branch="partition", finish_rows=100), shape=lambda d: d.select("rank", F.col("value")[0].cast("double").alias("value")), sql_value="CAST(k[1] AS DOUBLE)")


@query(f"SELECT 'min' AS which, min({PRICE}) AS value FROM lineitem UNION ALL SELECT 'max', max({PRICE}) FROM lineitem")
def min_max_price(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "lineitem")
    return multi_select(rows, PRICE, R.At(1)).select(F.lit("min").alias("which"), "value").unionByName(multi_select(rows, PRICE, R.top(1)).select(F.lit("max").alias("which"), "value"))


@query(by_number("orders", "o_totalprice", "rn IN (1, 2, 3, (n + 1) // 2)"))
def fig_example(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The published example's ranks, the three least and the median, of all orders; tests/test_measures.py has its fifteen numbers."""
    rows = table(spark, sf_dir, "orders")
    return multi_select(rows, "o_totalprice", sorted({1, 2, 3, (rows.count() + 1) // 2}), settings=Settings(branch="partition", pivots="paper", finish_rows=4))


@query("SELECT * FROM (VALUES " + ", ".join(f"(CAST({r} AS BIGINT), CAST({r} AS BIGINT))" for r in EIGHT) + ") t(rank, value)")
def fig_buckets(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = spark.createDataFrame([(x,) for x in SIXTY_EIGHT], "x long")
    return multi_select(rows, "x", EIGHT, settings=Settings(branch="partition", trim="exact", finish_rows=4), forced_pivots=PIVOTS)


@query(by_number("orders", "o_totalprice", "n + 1 - rn IN ((n + 3) // 4, (2 * n + 3) // 4, (3 * n + 3) // 4)").replace("CAST(rn AS BIGINT) AS rank", "CAST(n + 1 - rn AS BIGINT) AS rank"))
def descending_totalprice(spark: SparkSession, sf_dir: str) -> DataFrame:
    return multi_select(table(spark, sf_dir, "orders"), "o_totalprice", R.even(4), descending=True)


@query("WITH o AS (SELECT nullif(event_type, 'error') AS k, row_number() OVER (ORDER BY nullif(event_type, 'error') NULLS LAST) AS rn, count(*) OVER () AS n FROM events) SELECT CAST(rn AS BIGINT) AS rank, k AS value FROM o WHERE " + WHERE["deciles"])
def nulls_last(spark: SparkSession, sf_dir: str) -> DataFrame:
    return multi_select(table(spark, sf_dir, "events"), F.expr("nullif(event_type, 'error')"), R.even(10), nulls="last", settings=Settings(branch="partition"))


@query(by_number("lineitem", PRICE, "rn IN (SELECT DISTINCT n_chars FROM documents)"))
def ranks_from_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    return multi_select(table(spark, sf_dir, "lineitem"), PRICE, R.from_column(table(spark, sf_dir, "documents"), "n_chars"))


@query(by_number("lineitem", PRICE, "rn <= 700").replace("FROM lineitem", "FROM lineitem WHERE l_shipdate >= TIMESTAMP '1998-01-01'"))
def filtered_recent_price(spark: SparkSession, sf_dir: str) -> DataFrame:
    return multi_select(table(spark, sf_dir, "lineitem").filter("l_shipdate >= timestamp_ntz'1998-01-01 00:00:00'"), PRICE, R.span(1, 700))


def _grouped(name: str, source: str, by: list[str], key: str, kind: str, settings: Settings = Settings(), expr=None, value: str = "k", sql_key: str | None = None) -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return multi_select(table(spark, sf_dir, source), expr() if expr else key, {"tail": W.TAIL, "quartiles": R.Fractions("0.25", "0.5", "0.75")}[kind], group_by=by, settings=settings)

    run.__name__ = name
    query(grouped_by_number(source, by, sql_key or key, WHERE[kind], value))(run)


_grouped("grouped_flags_tail", "lineitem", ["l_returnflag", "l_linestatus"], PRICE, "tail", SMALL)
_grouped("grouped_event_type", "events", ["event_type"], "value", "tail", SMALL)
_grouped("grouped_lang_chars", "documents", ["lang"], "n_chars", "tail")
_grouped("grouped_priority", "orders", ["o_orderpriority"], "o_totalprice", "quartiles")


def _sets(kind: str, sets: list[list[str]]) -> str:
    keys = ["l_returnflag", "l_linestatus"]
    parts = []
    for s in sets:
        gid = sum(1 << (1 - j) for j, k in enumerate(keys) if k not in s)
        cols = ", ".join(k if k in s else f"CAST(NULL AS VARCHAR) AS {k}" for k in keys)
        part = f"PARTITION BY {', '.join(s)}" if s else ""
        parts.append(f"SELECT {cols}, {gid} AS grouping_id, CAST(0.5 AS DOUBLE) AS fraction, {PRICE} AS value FROM (SELECT *, row_number() OVER ({part} ORDER BY {PRICE}) AS rn, count(*) OVER ({part}) AS n FROM lineitem) WHERE rn = (n + 1) // 2")
    return " UNION ALL ".join(parts)


@query(_sets("cube", [["l_returnflag", "l_linestatus"], ["l_returnflag"], ["l_linestatus"], []]))
def cube_flags_median(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quantiles.cube(table(spark, sf_dir, "lineitem"), ["l_returnflag", "l_linestatus"], PRICE, ["0.5"])


@query(_sets("rollup", [["l_returnflag", "l_linestatus"], ["l_returnflag"], []]))
def rollup_flags_median(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quantiles.rollup(table(spark, sf_dir, "lineitem"), ["l_returnflag", "l_linestatus"], PRICE, ["0.5"])


_STAR = "(SELECT r_name, l_extendedprice * (1 - l_discount) AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey)"


@query(grouped_by_number(_STAR, ["r_name"], "round(revenue, 4)", "rn IN (SELECT (i * n + 9) // 10 FROM range(1, 10) t(i))"))
def star_region_revenue_deciles(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = lambda name: table(spark, sf_dir, name)
    star = t("lineitem").join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(t("customer"), F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(t("nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey"))
    rows = star.select("r_name", F.round(F.col(PRICE) * (1 - F.col("l_discount")), 4).alias("revenue"))
    return multi_select(rows, "revenue", R.Fractions(*[f"0.{i}" for i in range(1, 10)]), group_by="r_name", settings=SMALL)


# Gaps, threshold, branch, measures ---------------------------------------------------------------

_RANKS = "(SELECT DISTINCT n_chars AS r FROM documents WHERE n_chars BETWEEN 1 AND (SELECT count(*) FROM lineitem))"
_GAPS = f"gaps AS (SELECT coalesce(lag(r) OVER (ORDER BY r), 0) AS lo_rank, r AS hi_rank, r - coalesce(lag(r) OVER (ORDER BY r), 0) AS size FROM (SELECT r FROM {_RANKS} UNION ALL SELECT count(*) + 1 FROM lineitem))"
_DELTA = "delta AS (SELECT min(size) AS delta FROM (SELECT size, sum(w) OVER (ORDER BY size) AS cum FROM (SELECT size, sum(size) AS w FROM gaps GROUP BY size)) WHERE 2 * cum >= (SELECT count(*) FROM lineitem) + 2)"


def _chars_ranks(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, int]:
    n = table(spark, sf_dir, "lineitem").count()
    return R.resolve(spark, R.from_column(table(spark, sf_dir, "documents"), "n_chars"), n), n


@query(f"WITH {_GAPS} SELECT CAST(lo_rank AS BIGINT) AS lo_rank, CAST(hi_rank AS BIGINT) AS hi_rank, CAST(size AS BIGINT) AS size FROM gaps")
def gap_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return gaps.rank_gaps(*_chars_ranks(spark, sf_dir))


@query(f"WITH {_GAPS} SELECT CAST(lo_rank AS BIGINT) AS lo_rank, CAST(hi_rank AS BIGINT) AS hi_rank, CAST(size AS BIGINT) AS size FROM gaps")
def gap_sizes_stitched(spark: SparkSession, sf_dir: str) -> DataFrame:
    return gaps.rank_gaps(*_chars_ranks(spark, sf_dir), window_ranks=10)


@query(f"WITH {_GAPS}, {_DELTA} SELECT CAST(delta AS BIGINT) AS delta FROM delta")
def gap_threshold(spark: SparkSession, sf_dir: str) -> DataFrame:
    ranks, n = _chars_ranks(spark, sf_dir)
    return spark.createDataFrame([(gaps.gap_threshold(gaps.rank_gaps(ranks, n), n),)], "delta long")


@query(f"WITH {_GAPS}, {_DELTA} SELECT CAST(coalesce(sum(size) FILTER (size < delta), 0) AS BIGINT) AS below, CAST(sum(size) FILTER (size <= delta) AS BIGINT) AS upto, CAST(sum(size) FILTER (size >= delta) AS BIGINT) AS over FROM gaps, delta")
def gap_mass(spark: SparkSession, sf_dir: str) -> DataFrame:
    ranks, n = _chars_ranks(spark, sf_dir)
    g = gaps.rank_gaps(ranks, n)
    return gaps.gap_mass(g, gaps.gap_threshold(g, n))


@query(f"WITH {_GAPS} SELECT round(sum(size * log2(CAST((SELECT count(*) FROM lineitem) AS DOUBLE) / size)), 3) AS entropy FROM gaps")
def rank_entropy(spark: SparkSession, sf_dir: str) -> DataFrame:
    ranks, n = _chars_ranks(spark, sf_dir)
    return costs.rank_entropy(gaps.rank_gaps(ranks, n), n).select(F.round("entropy", 3).alias("entropy"))


_EPS = ("0.5", "1", "2", "4")
_KINDS = ("median", "minimum", "quartiles", "deciles", "percentiles", "permille", "tail", "top100", "middle", "clusters", "geometric", "half_dense")


def _family_deltas(spark: SparkSession, n: int) -> dict[str, int]:
    return {k: gaps.gap_threshold(gaps.rank_gaps(R.resolve(spark, W.FAMILIES[k], n), n), n) for k in _KINDS}


def _branch_sql() -> str:
    """All families' thresholds and branches; powers in doubles, which suffices away from equality."""
    fams = " UNION ALL ".join(f"SELECT '{k}' AS family, rn AS r FROM numbers WHERE {WHERE[k]}" for k in _KINDS)
    return f"""
WITH numbers AS (SELECT row_number() OVER () AS rn, count(*) OVER () AS n FROM lineitem), m AS (SELECT count(*) AS n FROM lineitem),
f AS ({fams}), e AS (SELECT family, r FROM f UNION ALL SELECT DISTINCT family, n + 1 FROM f, m),
g AS (SELECT family, r - coalesce(lag(r) OVER (PARTITION BY family ORDER BY r), 0) AS size FROM e),
c AS (SELECT family, size, sum(sum(size)) OVER (PARTITION BY family ORDER BY size) AS cum FROM g GROUP BY family, size),
d AS (SELECT family, min(size) AS delta FROM c, m WHERE 2 * cum >= n + 2 GROUP BY family),
eps AS (SELECT * FROM (VALUES ('0.5', 0.5), ('1', 1.0), ('2', 2.0), ('4', 4.0)) t(eps, e))
SELECT family, eps, CAST(delta AS BIGINT) AS delta,
  CASE WHEN greatest(1 + 2 / e, 2) * log2(2 * n) >= (greatest(1 + 2 / e, 2) + 1) * log2(delta) OR (1 + 1 / (1 + e)) * log2(n) >= 2 * log2(delta) THEN 'sort' ELSE 'partition' END AS branch
FROM d, eps, m"""


@query(_branch_sql())
def branch_choice(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = table(spark, sf_dir, "lineitem").count()
    rows = [(k, e, d, choose_branch(n, d, TallCache.of(e)).value) for k, d in _family_deltas(spark, n).items() for e in _EPS]
    return spark.createDataFrame(rows, "family string, eps string, delta long, branch string")


def _cost_sql() -> str:
    """The same measures from the gaps alone; M = 2^20, B = 2^10, eps = 1."""
    fams = " UNION ALL ".join(f"SELECT '{k}' AS family, rn AS r FROM numbers WHERE {WHERE[k]}" for k in _KINDS)
    return f"""
WITH numbers AS (SELECT row_number() OVER () AS rn, count(*) OVER () AS n FROM lineitem), m AS (SELECT count(*) AS n, CAST(count(*) AS DOUBLE) AS x FROM lineitem),
f AS ({fams}), e AS (SELECT family, r FROM f UNION ALL SELECT DISTINCT family, n + 1 FROM f, m),
g AS (SELECT family, r - coalesce(lag(r) OVER (PARTITION BY family ORDER BY r), 0) AS size FROM e),
c AS (SELECT family, size, sum(sum(size)) OVER (PARTITION BY family ORDER BY size) AS cum FROM g GROUP BY family, size),
d AS (SELECT family, min(size) AS delta FROM c, m WHERE 2 * cum >= n + 2 GROUP BY family),
s AS (SELECT family, sum(size * log2(x / size)) / any_value(x) AS entropy, sum(size / 1024.0 * greatest(0, ln(x / size))) / ln(1024.0) + any_value(x) / 1024 AS io,
  sum(size / 1024.0 * greatest(0, ln(x / size))) / ln(1048576.0) + any_value(x) / 1024 AS io_log_m, sum(size * (1 + log2(x / size))) AS potential, sum(size / 1024.0 * (1 + ln(x / size) / ln(1048576.0))) AS io_potential FROM g, m GROUP BY family)
SELECT family, CAST(delta AS BIGINT) AS delta, round(entropy, 6) AS entropy, round(io, 4) AS io, round(io_log_m, 4) AS io_log_m, CAST((n + 1023) // 1024 AS BIGINT) AS scan,
  round(x / 1024 * (1 + greatest(0, ln(greatest(x / 1024, 1)) / ln(1024.0))), 4) AS sort, CAST(greatest(1, 2 * n // delta) AS BIGINT) AS fan_out, round(power(greatest(1, 2 * n // delta), 2), 2) AS tree_cells,
  round(potential, 2) AS potential, round(io_potential, 4) AS io_potential, 1.5 * ln(x) <= 2 * ln(delta) + 1e-9 AS k2_ok
FROM s JOIN d USING (family), m"""


@query(_cost_sql())
def cost_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Entropy, I/O forms, sort bound and tree space by family, M = 2^20, B = 2^10."""
    n, m, b = table(spark, sf_dir, "lineitem").count(), 1 << 20, 1 << 10
    rows = []
    for k in _KINDS:
        sizes = gaps.size_counts(gaps.rank_gaps(R.resolve(spark, W.FAMILIES[k], n), n))
        delta = gaps.threshold_of(sizes, n)
        fan = max(1, 2 * n // delta)
        rows.append((k, delta, round(costs.entropy_of(sizes, n) / n, 6), round(costs.io_bound(sizes, n, m, b), 4), round(costs.io_bound(sizes, n, m, b, "m"), 4), costs.scan_blocks(n, b), round(costs.sort_bound(n, m, b), 4), fan, round(costs.tree_space(fan, 3.0), 2), round(costs.potential(sizes, n), 2), round(costs.potential(sizes, n, "io", m, b), 4), costs.k2_ok(n, delta)))
    return spark.createDataFrame(rows, "family string, delta long, entropy double, io double, io_log_m double, scan long, sort double, fan_out long, tree_cells double, potential double, io_potential double, k2_ok boolean")


@query()
def kernel_costs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The kernel's comparisons and simulated transfers over the families against the bounds, two caches, on the whole of supplier."""
    values = [r[0] for r in table(spark, sf_dir, "supplier").select("s_acctbal").orderBy(F.xxhash64("s_suppkey")).collect()]
    n, rows = len(values), []
    for k in ("median", "quartiles", "deciles", "percentiles", "tail", "geometric", "everything"):
        ranks = [r["rank"] for r in R.resolve(spark, W.FAMILIES[k], n).collect()]
        for m, b in ((256, 8), (1024, 16)):
            desk = kernel.Desk(BlockCache(m, b))
            assert sum(1 for _ in kernel.select_many(values, ranks, desk=desk)) == len(ranks)
            sizes = gaps.gap_sizes(ranks, n)
            rows.append((k, m, b, desk.counters.comparisons, desk.cache.transfers, desk.counters.comparisons / (costs.entropy_of(sizes, n) + n), desk.cache.transfers / costs.io_bound(sizes, n, m, b)))
    return spark.createDataFrame(rows, "family string, m int, b int, comparisons long, transfers long, comparisons_to_bound double, transfers_to_bound double")


# Selection ---------------------------------------------------------------------------------------

_WEIGHTED = f"WITH w AS (SELECT {PRICE} AS k, sum(l_quantity) AS w FROM lineitem GROUP BY 1), c AS (SELECT k, sum(w) OVER (ORDER BY k) AS cum FROM w) SELECT min(k) AS value FROM c WHERE 2 * cum >= (SELECT sum(l_quantity) FROM lineitem)"


@query(_WEIGHTED)
def weighted_select_price_by_quantity(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "lineitem")
    return select.weighted_rank(rows, PRICE, "l_quantity", rows.agg(F.sum("l_quantity")).first()[0] / 2, SMALL).select("value")


@query("WITH w AS (SELECT l_returnflag, l_quantity AS k, sum(l_linenumber) AS w FROM lineitem GROUP BY 1, 2), c AS (SELECT l_returnflag, k, sum(w) OVER (PARTITION BY l_returnflag ORDER BY k) AS cum FROM w) SELECT l_returnflag, min(k) AS l_quantity, CAST(min(cum) AS BIGINT) AS cum_weight FROM c WHERE cum >= 5000 GROUP BY 1")
def weighted_select_grouped(spark: SparkSession, sf_dir: str) -> DataFrame:
    return gaps.weighted_select(table(spark, sf_dir, "lineitem"), "l_quantity", "l_linenumber", F.lit(5000), ["l_returnflag"])


@query(by_number("lineitem", PRICE, "rn = 12345 % n"))
def single_select_price(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "lineitem")
    return select.select_rank(rows, PRICE, 12345 % rows.count(), replace(SMALL, branch="partition"))


@query("WITH o AS (SELECT l_linenumber AS sub, l_extendedprice AS value, row_number() OVER (PARTITION BY l_linenumber ORDER BY l_extendedprice) AS rn FROM lineitem) SELECT CAST(sub AS BIGINT) AS sub, CAST(rn AS BIGINT) AS rank, value FROM o WHERE rn IN (1, 100)")
def grouped_select_rounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "lineitem")
    wanted = rows.groupBy(F.col("l_linenumber").cast("long").alias("sub")).agg(F.count("*").alias("n")).select("sub", F.explode(F.array(F.lit(1).cast("long"), F.lit(100).cast("long"))).alias("rank"), "n").filter("rank <= n").drop("n")
    return select.select_rank_grouped(rows, "l_linenumber", PRICE, wanted, SMALL)


# Partition ---------------------------------------------------------------------------------------


def _work(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").select(F.lit(0).cast("long").alias("sub"), F.col(PRICE).alias("key"))


_CHECKED = "SELECT true AS whole, true AS within, true AS few"


def _partition_facts(spark: SparkSession, sf_dir: str, source: str) -> DataFrame:
    work = _work(spark, sf_dir)
    n = work.count()
    delta = n // 10
    found = multi_partition(work, delta, Settings(), source)
    sizes = found.open_sizes()
    whole = sum(size for rows in found.bounds.values() for _, size, _ in rows) == n
    return spark.createDataFrame([(whole, max(sizes) <= delta, len(sizes) <= 4 * n // delta)], "whole boolean, within boolean, few boolean")


@query(_CHECKED)
def bucket_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _partition_facts(spark, sf_dir, "summary")


@query(_CHECKED)
def bucket_sizes_medians(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _partition_facts(spark, sf_dir, "medians")


@query("WITH b AS (SELECT CASE WHEN l_extendedprice < 10000 THEN 0 WHEN l_extendedprice = 10000 THEN 1 WHEN l_extendedprice < 30000 THEN 2 WHEN l_extendedprice = 30000 THEN 3 ELSE 4 END AS bucket FROM lineitem), c AS (SELECT bucket, count(*) AS n FROM b GROUP BY 1) SELECT CAST(bucket AS INTEGER) AS bucket, n, CAST(sum(n) OVER (ORDER BY bucket) AS BIGINT) AS hi_rank, CAST(sum(n) OVER (ORDER BY bucket) - n + 1 AS BIGINT) AS lo_rank FROM c")
def pivot_ranks_fixed(spark: SparkSession, sf_dir: str) -> DataFrame:
    pivots = spark.createDataFrame([(0, [10000.0, 30000.0])], "sub long, pivots array<double>")
    return pivot_ranks(bucket_counts(_work(spark, sf_dir), pivots, 2)).drop("sub")


def _how(how: str) -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        edges = [1000.0 * k for k in range(1, 100)]
        pivots = spark.createDataFrame([(0, edges)], "sub long, pivots array<double>")
        return bucket_counts(_work(spark, sf_dir), pivots, len(edges), how).select("bucket", "n")

    run.__name__ = f"distribute_{how}"
    query("SELECT CAST(least(floor(l_extendedprice / 1000), 99) * 2 - CASE WHEN l_extendedprice = floor(l_extendedprice / 1000) * 1000 AND l_extendedprice < 100000 THEN 1 ELSE 0 END AS INTEGER) AS bucket, count(*) AS n FROM lineitem GROUP BY 1")(run)


for _h in ("search", "case", "bucketizer", "arrow", "join"):
    _how(_h)


# Variants that must agree ------------------------------------------------------------------------

_AGREE = "SELECT true AS agree"


def _same(spark: SparkSession, sf_dir: str, runs: list[Settings], kind: str = "tail") -> DataFrame:
    rows = table(spark, sf_dir, "lineitem")
    got = [[tuple(r) for r in multi_select(rows, PRICE, W.FAMILIES[kind], settings=s).collect()] for s in runs]
    return spark.createDataFrame([(all(g == got[0] for g in got),)], "agree boolean")


@query(_AGREE)
def trim_modes_agree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _same(spark, sf_dir, [Settings(branch="partition", pivots="paper", trim=t, finish_rows=500) for t in ("exact", "none")], "clusters")


@query(_AGREE)
def branches_agree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _same(spark, sf_dir, [Settings(branch=b, finish_rows=500) for b in ("sort", "partition")] + [Settings(tall=TallCache.of(e)) for e in ("0.5", "4")])


@query(_AGREE)
def pivot_sources_agree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _same(spark, sf_dir, [Settings(branch="partition", pivots=p, finish_rows=500) for p in ("bracket", "summary", "medians", "paper")])


@query(_AGREE)
def collapse_agrees(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "lineitem")
    a, b = (multi_select(rows, "l_quantity", W.TAIL, settings=Settings(collapse=c)).collect() for c in (True, False))
    return spark.createDataFrame([(a == b,)], "agree boolean")


@query("SELECT true AS halves, true AS ends")
def survivors_by_level(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whether subproblems hold under half of the elements and each at most the threshold less two, over the whole table.

    The first level is partitioned and trimmed by the distributed engine; the subproblems it leaves are as short as the ranks' clusters
    at any size of the table, and the kernel takes all of their rows through the further levels.
    """
    levels = _levels(_work(spark, sf_dir))
    return spark.createDataFrame([(all(2 * sum(c) < n for n, _, c in levels), all(x <= d - 2 for _, d, c in levels for x in c))], "halves boolean, ends boolean")


def _levels(work: DataFrame) -> list[tuple[int, int, list[int]]]:
    """(elements, threshold, sizes of the subproblems that are left) of the whole table and of each subproblem partitioned below it."""
    spark, n, settings = work.sparkSession, work.count(), Settings(branch="partition", pivots="paper")
    ranks = sorted({r for k in range(1, 10) for j in range(20) if (r := n * k // 10 + 3 * j) <= n})
    delta = gaps.threshold_of(gaps.gap_sizes(ranks, n), n)
    part = multi_partition(work, delta, settings)
    _, needs, rest = engine._route(engine.Wanted.listed(spark, [(0, r, r) for r in ranks]), part, work.schema["key"].dataType)
    ids = spark.createDataFrame([(s, b, k) for k, (s, b, _) in enumerate(needs)], "sub long, bucket int, next long")
    kept = bucketize(work, part.pivots, part.most, settings.how).join(F.broadcast(ids), ["sub", "bucket"]).select(F.col("next").alias("sub"), "key")
    _, between, rest = engine._trimmed(kept, rest.frame, {k: size for k, (_, _, size) in enumerate(needs)}, settings)
    inside: dict[int, list[int]] = {}
    for r in rest.orderBy("sub", "rank").collect():
        inside.setdefault(r["sub"], []).append(r["rank"])
    values: dict[int, list] = {s: [] for s in inside}
    for r in between.join(rest.select("sub").distinct(), "sub", "left_semi").collect():
        values[r["sub"]].append(r["key"])
    levels = [(n, delta, [len(v) for v in values.values()])]
    for s, v in values.items():
        desk = kernel.Desk()
        list(kernel.select_many(v, inside[s], branch="partition", desk=desk))
        levels += [(c["n"], c["delta"], c["children"]) for c in desk.counters.calls if c["branch"] == "partition"]
    return levels


@query()
def ledger_by_level(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows scanned and kept by pivot source."""
    rows, out = table(spark, sf_dir, "lineitem"), []
    for pivots in ("bracket", "summary", "paper"):
        ledger = Ledger()
        multi_select(rows, PRICE, W.TAIL, settings=Settings(branch="partition", pivots=pivots, finish_rows=500), ledger=ledger)
        out += [(pivots, x.depth, x.rows, x.buckets, x.largest_open, x.survivors, ledger.rows_scanned, ledger.rows_shuffled) for x in ledger.levels]
    return spark.createDataFrame(out, "pivots string, depth int, rows long, buckets int, largest_open long, survivors long, rows_scanned long, rows_shuffled long")


# Baselines ---------------------------------------------------------------------------------------


def _tail_ranks(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, list[int], int]:
    rows = table(spark, sf_dir, "lineitem")
    n = rows.count()
    return rows, [r["rank"] for r in W.TAIL(spark, n).collect()], n


_TAIL = by_number("lineitem", PRICE, WHERE["tail"])


@query(_TAIL)
def baseline_sort_one(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows, ranks, _ = _tail_ranks(spark, sf_dir)
    return baselines.sort_one(rows, PRICE, R.of(spark, ranks))


@query(_TAIL)
def baseline_sort_all(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows, ranks, _ = _tail_ranks(spark, sf_dir)
    return baselines.sort_all(rows, PRICE, R.of(spark, ranks))


@query(_TAIL)
def baseline_each(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows, ranks, _ = _tail_ranks(spark, sf_dir)
    return baselines.select_each(rows, PRICE, ranks)


@query(_TAIL)
def baseline_binary_prune(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows, ranks, n = _tail_ranks(spark, sf_dir)
    return baselines.binary_prune(rows, PRICE, ranks, max(500, n // 16))


@query(_TAIL)
def baseline_aware(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows, ranks, n = _tail_ranks(spark, sf_dir)
    return baselines.aware_partition(rows, PRICE, ranks, max(1024, n // 64), 64)


@query(_TAIL)
def baseline_sampled(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows, ranks, _ = _tail_ranks(spark, sf_dir)
    return baselines.sampled_select(rows, PRICE, ranks, seed=5)


_FIVE = [0.1, 0.25, 0.5, 0.75, 0.9]


@query("SELECT unnest([0.1, 0.25, 0.5, 0.75, 0.9])::DOUBLE AS fraction, unnest([quantile_disc(l_quantity, 0.1), quantile_disc(l_quantity, 0.25), quantile_disc(l_quantity, 0.5), quantile_disc(l_quantity, 0.75), quantile_disc(l_quantity, 0.9)]) AS value FROM lineitem")
def baseline_percentile_disc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return baselines.built_in(table(spark, sf_dir, "lineitem"), "l_quantity", _FIVE)


@query(by_number("lineitem", PRICE, WHERE["top100"]))
def baseline_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "lineitem")
    return baselines.top_k(rows, PRICE, 100, rows.count())


@query("SELECT true AS engine_exact, true AS sketch_within")
def rank_error_approx(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rank error of the engine is 0; that of the built-in sketch is within n / accuracy."""
    rows, ranks, n = _tail_ranks(spark, sf_dir)
    worst = lambda a: costs.rank_error(rows, PRICE, a).agg(F.max("error")).first()[0]
    return spark.createDataFrame([(worst(multi_select(rows, PRICE, ranks)) == 0, worst(baselines.approximate(rows, PRICE, ranks, n, 200)) <= n / 200 + 1)], "engine_exact boolean, sketch_within boolean")


@query()
def rank_error_kll(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows, ranks, n = _tail_ranks(spark, sf_dir)
    return costs.rank_error(rows, PRICE, baselines.kll(rows, PRICE, ranks, n))


# Functions ---------------------------------------------------------------------------------------


@query("WITH o AS (SELECT o_orderkey, o_totalprice, row_number() OVER (ORDER BY o_totalprice, o_orderkey) AS rn FROM orders) SELECT CAST(rn AS BIGINT) AS rank, o_orderkey, o_totalprice FROM o WHERE rn BETWEEN 500 AND 600")
def rank_slice(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quantiles.rank_slice(table(spark, sf_dir, "orders"), "o_totalprice", 500, 600, ["o_orderkey"]).select("rank", "o_orderkey", "o_totalprice")


@query("SELECT tile, max(o_totalprice) AS value FROM (SELECT o_totalprice, ntile(20) OVER (ORDER BY o_totalprice) AS tile FROM orders) GROUP BY tile")
def ntile_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quantiles.ntile_edges(table(spark, sf_dir, "orders"), "o_totalprice", 20)


_EDGES = "edges AS (SELECT DISTINCT max(l_quantity) AS e FROM (SELECT l_quantity, ntile(8) OVER (ORDER BY l_quantity) AS tile FROM lineitem) GROUP BY tile)"


@query(f"WITH {_EDGES}, b AS (SELECT l_quantity AS k, (SELECT count(*) FROM edges WHERE e < l_quantity) AS bin FROM lineitem) SELECT CAST(bin AS INTEGER) AS bin, min(k) AS lo, max(k) AS hi, count(*) AS n FROM b GROUP BY 1")
def equi_depth_histogram(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quantiles.equi_depth(table(spark, sf_dir, "lineitem"), "l_quantity", 8)


@query("WITH o AS (SELECT l_quantity AS k, row_number() OVER (ORDER BY l_quantity) AS rn, count(*) OVER () AS n FROM lineitem) SELECT round(avg(k), 6) AS mean FROM o WHERE rn > n // 20 AND rn <= n - n // 20")
def trimmed_mean(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quantiles.trimmed_mean(table(spark, sf_dir, "lineitem"), "l_quantity").select(F.round("mean", 6).alias("mean"))


@query("WITH o AS (SELECT l_extendedprice AS k, row_number() OVER (ORDER BY l_extendedprice) AS rn, count(*) OVER () AS n FROM lineitem), e AS (SELECT min(k) FILTER (rn = n // 20 + 1) AS a, min(k) FILTER (rn = n - n // 20) AS z FROM o) SELECT round(avg(greatest(least(k, z), a)), 4) AS mean FROM o, e")
def winsor_mean(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quantiles.winsor_mean(table(spark, sf_dir, "lineitem"), PRICE).select(F.round("mean", 4).alias("mean"))


@query("WITH o AS (SELECT o_totalprice AS k, row_number() OVER (ORDER BY o_totalprice) AS rn, count(*) OVER () AS n FROM orders), m AS (SELECT k AS med FROM o WHERE rn = (n + 1) // 2), d AS (SELECT abs(k - med) AS x, row_number() OVER (ORDER BY abs(k - med)) AS rn, count(*) OVER () AS n FROM o, m) SELECT round((SELECT max(k) - min(k) FROM o WHERE rn IN ((n + 3) // 4, (3 * n + 3) // 4)), 4) AS iqr, round((SELECT x FROM d WHERE rn = (n + 1) // 2), 4) AS mad")
def iqr_mad(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "orders")
    return quantiles.iqr(rows, "o_totalprice").join(F.broadcast(quantiles.mad(rows, "o_totalprice"))).select(F.round("iqr", 4).alias("iqr"), F.round("mad", 4).alias("mad"))


@query("SELECT l_returnflag, CAST(0.25 AS DOUBLE) AS fraction, round(quantile_cont(l_extendedprice, 0.25), 4) AS value FROM lineitem GROUP BY 1 UNION ALL SELECT l_returnflag, 0.5, round(quantile_cont(l_extendedprice, 0.5), 4) FROM lineitem GROUP BY 1 UNION ALL SELECT l_returnflag, 0.95, round(quantile_cont(l_extendedprice, 0.95), 4) FROM lineitem GROUP BY 1")
def quantile_cont(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quantiles.cont(table(spark, sf_dir, "lineitem"), PRICE, ["0.25", "0.5", "0.95"], ["l_returnflag"]).withColumn("value", F.round("value", 4))


@query("WITH o AS (SELECT o_orderkey, o_custkey, o_totalprice, row_number() OVER (ORDER BY o_totalprice, o_orderkey) AS rn, count(*) OVER () AS n FROM orders) SELECT CAST(rn AS BIGINT) AS rank, o_orderkey, o_custkey, o_totalprice FROM o WHERE " + WHERE["deciles"])
def payload_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quantiles.rows_at(table(spark, sf_dir, "orders"), "o_totalprice", R.even(10), ["o_orderkey"], SMALL).select("rank", "o_orderkey", "o_custkey", "o_totalprice")


@query("WITH v AS (SELECT unnest([1.0, 25.0, 25.5, 50.0])::DOUBLE AS value) SELECT value, (SELECT count(*) FROM lineitem WHERE l_quantity < value) AS lt, (SELECT count(*) FROM lineitem WHERE l_quantity = value) AS eq FROM v")
def rank_of_values(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quantiles.rank_of(table(spark, sf_dir, "lineitem"), "l_quantity", spark.createDataFrame([(x,) for x in (1.0, 25.0, 25.5, 50.0)], "value double"))


@query("WITH w AS (SELECT l_quantity AS k, sum(l_extendedprice) AS w FROM lineitem GROUP BY 1), c AS (SELECT k, sum(w) OVER (ORDER BY k) AS cum, sum(w) OVER () AS total FROM w), p AS (SELECT unnest([0.1, 0.5, 0.9])::DOUBLE AS fraction) SELECT fraction, min(k) AS value FROM c, p WHERE cum >= fraction * total GROUP BY 1")
def weighted_quantiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quantiles.weighted(table(spark, sf_dir, "lineitem"), "l_quantity", PRICE, ["0.1", "0.5", "0.9"], SMALL)


@query(f"WITH e AS (SELECT k AS e, row_number() OVER (ORDER BY k) AS j FROM (SELECT DISTINCT k FROM (SELECT value AS k, row_number() OVER (ORDER BY value) AS rn, count(*) OVER () AS n FROM events) WHERE {WHERE['deciles']})), b AS (SELECT event_id, (SELECT count(*) FROM e WHERE e < value) AS bin FROM events) SELECT CAST(bin AS INTEGER) AS bin, count(*) AS n, CAST(sum(event_id) AS BIGINT) AS ids FROM b GROUP BY 1")
def asof_quantile_label(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "events")
    marked = quantiles.label(rows, "value", multi_select(rows, "value", R.even(10)).select("value"))
    return marked.groupBy("bin").agg(F.count("*").alias("n"), F.sum("event_id").cast("long").alias("ids"))


@query(by_number("lineitem", PRICE, "rn IN (1, 77, 1234, 4321)"))
def incremental_ranks(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = f"{shared_dir(spark)}/partition-{uuid.uuid4().hex}"
    incremental.save_partition(table(spark, sf_dir, "lineitem"), PRICE, path, parts=16)
    return incremental.later_ranks(spark, path, [1, 77]).unionByName(incremental.later_ranks(spark, path, [1234, 4321]))


@query("WITH o AS (SELECT lang AS grp, CAST(n_chars AS DOUBLE) AS value, row_number() OVER (PARTITION BY lang ORDER BY n_chars) AS rn FROM documents) SELECT grp, CAST(rn AS BIGINT) AS rank, value FROM o WHERE rn IN (1, 5, 20)")
def udtf_pick_ranks(spark: SparkSession, sf_dir: str) -> DataFrame:
    sqlapi.register(spark)
    table(spark, sf_dir, "documents").select(F.col("lang").alias("g"), F.col("n_chars").cast("double").alias("v")).createOrReplaceTempView("pick_ranks_input")
    return spark.sql("SELECT * FROM pick_ranks(TABLE(pick_ranks_input) PARTITION BY (g) ORDER BY (v), array(1, 5, 20))")


@query("WITH c AS (SELECT l_returnflag, l_quantity, count(*) AS m FROM lineitem GROUP BY 1, 2), e AS (SELECT l_returnflag, sum(m) OVER (PARTITION BY l_returnflag ORDER BY l_quantity) AS hi FROM c UNION ALL SELECT l_returnflag, count(*) + 1 FROM lineitem GROUP BY 1), g AS (SELECT l_returnflag, hi, coalesce(lag(hi) OVER (PARTITION BY l_returnflag ORDER BY hi), 0) AS lo, row_number() OVER (PARTITION BY l_returnflag ORDER BY hi) AS k FROM e) SELECT l_returnflag, CAST(k AS INTEGER) AS gap_no, CAST(lo AS BIGINT) AS lo_rank, CAST(hi AS BIGINT) AS hi_rank, CAST(hi - lo AS BIGINT) AS size FROM g")
def udtf_gap_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The gaps between the last ranks of each quantity, by return flag: how many items have it."""
    sqlapi.register(spark)
    table(spark, sf_dir, "lineitem").createOrReplaceTempView("gap_table_input")
    last = "SELECT l_returnflag, sum(count(*)) OVER (PARTITION BY l_returnflag ORDER BY l_quantity) AS hi FROM gap_table_input GROUP BY l_returnflag, l_quantity"
    return spark.sql(f"SELECT l_returnflag, g.* FROM (SELECT l_returnflag, collect_list(hi) AS ranks, max(hi) AS n FROM ({last}) GROUP BY l_returnflag) r, LATERAL gap_table(r.ranks, r.n) g")


@query("SELECT o_orderpriority, v AS value FROM (SELECT o_orderpriority, o_totalprice AS v, row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice) AS rn, count(*) OVER (PARTITION BY o_orderpriority) AS n FROM orders) WHERE " + WHERE["quartiles"])
def udaf_exact_quantiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    sqlapi.register(spark)
    table(spark, sf_dir, "orders").createOrReplaceTempView("udaf_orders")
    return spark.sql("SELECT o_orderpriority, explode(q) AS value FROM (SELECT o_orderpriority, exact_quantiles(o_totalprice) AS q FROM udaf_orders GROUP BY o_orderpriority)")


@query(by_number("orders", "o_totalprice", "rn IN (10, 100)").replace("FROM orders", "FROM orders WHERE o_orderstatus = 'F'"))
def sql_select_ranks(spark: SparkSession, sf_dir: str) -> DataFrame:
    register(spark, sf_dir)
    return sqlapi.select_ranks(spark, "SELECT * FROM orders WHERE o_orderstatus = 'F'", "o_totalprice", [10, 100])


@query(by_number("lineitem", PRICE, WHERE["geometric"]))
def rank_family_source(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Selection of the ranks that the data source gives for the table's size."""
    sqlapi.register(spark)
    rows = table(spark, sf_dir, "lineitem")
    return multi_select(rows, PRICE, spark.read.format("rank_family").option("kind", "geometric").option("n", rows.count()).load())


@query("WITH e AS (SELECT date_trunc('day', ts) AS start, event_type, value AS k FROM events), o AS (SELECT *, row_number() OVER (PARTITION BY start, event_type ORDER BY k) AS rn, count(*) OVER (PARTITION BY start, event_type) AS n FROM e) SELECT CAST(start AS TIMESTAMP) AS start, event_type, CAST(CASE WHEN rn = (n + 1) // 2 THEN 0.5 END AS DOUBLE) AS fraction, CAST(rn AS BIGINT) AS rank, k AS value FROM o WHERE rn = (n + 1) // 2")
def window_ranks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Batch form of the streamed windows: medians by day and type from histograms."""
    from orderstat.streaming import windows

    rows = table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp_ntz"))
    counts = rows.groupBy(F.date_trunc("day", F.col("ts")).cast("timestamp_ntz").alias("start"), "event_type", "value").agg(F.count("*").alias("n"))
    return windows.ranks_of_counts(counts, ["start", "event_type"], ["0.5"])


@query("WITH e AS (SELECT date_trunc('day', ts) AS start, event_type, value AS k FROM events), o AS (SELECT *, row_number() OVER (PARTITION BY start, event_type ORDER BY k) AS rn, count(*) OVER (PARTITION BY start, event_type) AS n FROM e) SELECT CAST(start AS TIMESTAMP) AS start, event_type, CAST(CASE WHEN rn = (n + 1) // 2 THEN 0.5 END AS DOUBLE) AS fraction, CAST(rn AS BIGINT) AS rank, k AS value FROM o WHERE rn = (n + 1) // 2 AND start + INTERVAL 1 DAY <= (SELECT max(ts) FROM events) - INTERVAL 1 HOUR")
def stream_window_ranks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same by a stream over the events in two files; windows that the watermark has passed."""
    from orderstat.streaming import windows

    base = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    rows = table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    rows.repartitionByRange(2, "ts").sortWithinPartitions("ts").write.parquet(f"{base}/in")
    stream = windows.events_stream(spark, f"{base}/in", rows.schema)
    found = windows.stateful_ranks(stream, "value", F.window("ts", "1 day"), ["event_type"], ["0.5"], "1 hour")
    job = found.writeStream.format("parquet").option("checkpointLocation", f"{base}/state").option("path", f"{base}/out").outputMode("append").trigger(availableNow=True).start()
    job.awaitTermination()
    return spark.read.schema(found.schema).parquet(f"{base}/out").withColumn("start", F.col("start").cast("timestamp_ntz"))



# Relational forms, sweeps -------------------------------------------------------------------------


@query(f"SELECT rank, value AS a, value AS b, true AS same FROM ({_TAIL})")
def answers_compared(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows, ranks, _ = _tail_ranks(spark, sf_dir)
    return relational.compared(multi_select(rows, PRICE, ranks), baselines.sort_all(rows, PRICE, R.of(spark, ranks)))


@query(by_number("supplier", "s_acctbal", "rn IN (1, 2, 5, 9)"))
def brute_force_theta(spark: SparkSession, sf_dir: str) -> DataFrame:
    return relational.brute_force(table(spark, sf_dir, "supplier"), "s_acctbal", R.of(spark, [1, 2, 5, 9]))


@query("SELECT j, count(*) AS q, round(sum(k), 2) AS total FROM (SELECT l_extendedprice AS k, row_number() OVER (ORDER BY l_extendedprice) AS rn, count(*) OVER () AS n FROM lineitem) o, range(1, 11) t(j) WHERE rn IN (SELECT (i * n + (1 << j) - 1) // (1 << j) FROM range(1, 1024) s(i) WHERE i < (1 << j)) GROUP BY j".replace("range(1, 11)", "(VALUES (1), (4), (7), (10))"))
def spectrum_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """2^j - 1 even ranks: from one selection towards a sort."""
    rows, out = table(spark, sf_dir, "lineitem"), None
    for j in (1, 4, 7, 10):
        one = multi_select(rows, PRICE, W.spectrum(1 << 11)[j]).agg(F.lit(j).alias("j"), F.count("*").alias("q"), F.round(F.sum("value"), 2).alias("total"))
        out = one if out is None else out.unionByName(one)
    return out


@query(_AGREE)
def random_ranks_agree(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "orders")
    n = rows.count()
    checks = []
    for seed in (1, 2):
        ranks = R.resolve(spark, R.random(40, seed), n)
        checks.append(relational.same_answers(multi_select(rows, "o_totalprice", ranks), baselines.sort_one(rows, "o_totalprice", ranks)))
    return spark.createDataFrame([(all(checks),)], "agree boolean")


@query(_AGREE)
def input_orders_agree(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same table sorted, reversed, shuffled, and dealt unevenly."""
    rows = table(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice")
    laid = [rows.repartitionByRange(8, "o_totalprice").sortWithinPartitions("o_totalprice"), rows.repartitionByRange(8, F.desc("o_totalprice")).sortWithinPartitions(F.desc("o_totalprice")), rows.repartition(8, F.xxhash64("o_orderkey")), rows.repartition(8, F.when(F.col("o_orderkey") % 10 < 9, 0).otherwise(F.col("o_orderkey")))]
    got = [multi_select(x, "o_totalprice", W.TAIL, settings=Settings(branch="partition", finish_rows=500)).collect() for x in laid]
    return spark.createDataFrame([(all(g == got[0] for g in got),)], "agree boolean")


@query("SELECT CAST(start AS TIMESTAMP) AS start, event_type, CAST(sum(1) AS BIGINT) AS n FROM (SELECT time_bucket(INTERVAL 12 HOUR, ts) - o * INTERVAL 12 HOUR AS start, event_type FROM events, range(0, 2) t(o)) GROUP BY 1, 2")
def sliding_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sliding windows of a day every half day, from the histograms that streams keep; here over the table as a batch."""
    from orderstat.streaming import windows

    rows = table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    counts = windows.window_counts(rows, "value", F.window("ts", "24 hours", "12 hours"), ["event_type"])
    return counts.groupBy("start", "event_type").agg(F.sum("n").alias("n"))


# Later additions ----------------------------------------------------------------------------------


@query("WITH w AS (SELECT l_orderkey * 1152921504606 + l_linenumber AS k, sum(l_quantity) AS w FROM lineitem GROUP BY 1), c AS (SELECT k, sum(w) OVER (ORDER BY k) AS cum FROM w) SELECT min(k) AS value FROM c WHERE 2 * cum >= (SELECT sum(l_quantity) FROM lineitem)")
def weighted_select_wide_keys(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Weighted selection among whole numbers that doubles do not tell apart.

    Keys are decimals, as those of some eight million orders or more pass the range of longs; the answer is a long while it is one.
    """
    wide = F.col("l_orderkey").cast("decimal(20,0)") * F.lit(1152921504606) + F.col("l_linenumber")
    rows = table(spark, sf_dir, "lineitem").select(wide.alias("k"), "l_quantity")
    return select.weighted_rank(rows, "k", "l_quantity", rows.agg(F.sum("l_quantity")).first()[0] / 2, SMALL).select(F.col("value").cast("long").alias("value"))


@query("WITH n AS (SELECT count(*) AS n FROM lineitem), o AS (SELECT l_extendedprice AS k, row_number() OVER (ORDER BY l_extendedprice) AS rn FROM lineitem), j AS (SELECT unnest(range(0, 64)) AS j) SELECT CAST(j AS INTEGER) AS j, count(*) AS q, round(sum(k), 2) AS total FROM j, n, o WHERE (1::BIGINT << (j % 62)) <= n AND j < 62 AND j > 0 AND ((rn * (1::BIGINT << j)) // n) <> (((rn - 1) * (1::BIGINT << j)) // n) AND (rn * (1::BIGINT << j)) // n < (1::BIGINT << j) GROUP BY j")
def spectrum_to_sort(spark: SparkSession, sf_dir: str) -> DataFrame:
    """2^j - 1 even ranks for every j from 1 to floor(lg N): from one selection to nearly a sort."""
    rows = table(spark, sf_dir, "lineitem")
    n, out = rows.count(), None
    for j in range(1, n.bit_length()):
        one = multi_select(rows, PRICE, R.even(1 << j)).agg(F.lit(j).alias("j"), F.count("*").alias("q"), F.round(F.sum("value"), 2).alias("total"))
        out = one if out is None else out.unionByName(one)
    return out


def _windowed(source: str, start: str) -> str:
    return f"WITH e AS (SELECT {start} AS start, event_type, value AS k FROM {source}), o AS (SELECT *, row_number() OVER (PARTITION BY start, event_type ORDER BY k) AS rn, count(*) OVER (PARTITION BY start, event_type) AS n FROM e) SELECT CAST(start AS TIMESTAMP) AS start, event_type, CAST(CASE WHEN rn = (n + 1) // 2 THEN 0.5 ELSE 0.9 END AS DOUBLE) AS fraction, CAST(rn AS BIGINT) AS rank, k AS value FROM o WHERE rn IN ((n + 1) // 2) UNION ALL SELECT CAST(start AS TIMESTAMP), event_type, CAST(0.9 AS DOUBLE), CAST(rn AS BIGINT), k FROM o WHERE rn = (9 * n + 9) // 10"


@query(_windowed("events, range(0, 2) t(o)", "time_bucket(INTERVAL 12 HOUR, ts) - o * INTERVAL 12 HOUR"))
def sliding_window_ranks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Medians and 90 % ranks by type in windows of a day every half day."""
    from orderstat.streaming import windows

    rows = table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    counts = windows.window_counts(rows, "value", F.window("ts", "24 hours", "12 hours"), ["event_type"])
    return windows.ranks_of_counts(counts.select("start", "event_type", "value", "n"), ["start", "event_type"], ["0.5", "0.9"])


_SESSIONS = "(SELECT *, max(CASE WHEN fresh THEN ts END) OVER (PARTITION BY event_type ORDER BY ts ROWS UNBOUNDED PRECEDING) AS begun FROM (SELECT *, coalesce(ts - lag(ts) OVER (PARTITION BY event_type ORDER BY ts) >= INTERVAL 30 MINUTE, true) AS fresh FROM events))"


@query(_windowed(_SESSIONS, "begun"))
def session_window_ranks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same in sessions of a type that half an hour without an event ends."""
    from orderstat.streaming import windows

    rows = table(spark, sf_dir, "events").select(F.col("ts").cast("timestamp").alias("ts"), "event_type", "value")
    spans = rows.groupBy("event_type", F.session_window("ts", "30 minutes").alias("w")).agg(F.count("*").alias("all"))
    spans = spans.select(F.col("event_type").alias("_type"), F.col("w.start").alias("start"), F.col("w.end").alias("_end"))
    met = rows.join(spans, (F.col("event_type") == F.col("_type")) & (F.col("ts") >= F.col("start")) & (F.col("ts") < F.col("_end")))
    counts = met.groupBy("start", "event_type", "value").agg(F.count("*").alias("n"))
    return windows.ranks_of_counts(counts, ["start", "event_type"], ["0.5", "0.9"])


@query("SELECT value, any_value(pr) AS percent_rank, any_value(cd) AS cume_dist FROM (SELECT l_quantity AS value, round(percent_rank() OVER (ORDER BY l_quantity), 9) AS pr, round(cume_dist() OVER (ORDER BY l_quantity), 9) AS cd FROM lineitem) GROUP BY value")
def percent_rank_of_values(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "lineitem")
    found = quantiles.percent_rank(rows, "l_quantity", rows.select(F.col("l_quantity").alias("value")))
    return found.select("value", F.round("percent_rank", 9).alias("percent_rank"), F.round("cume_dist", 9).alias("cume_dist"))


@query("WITH o AS (SELECT l_quantity AS k, row_number() OVER (ORDER BY l_quantity) AS rn, count(*) OVER () AS n FROM lineitem) SELECT CASE WHEN l_quantity <= (SELECT k FROM o WHERE rn = (8 * n + 9) // 10) THEN 'train' ELSE 'test' END AS part, count(*) AS n FROM lineitem GROUP BY 1")
def train_test_cut(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quantiles.cut_at(table(spark, sf_dir, "lineitem"), "l_quantity", "0.8").groupBy("part").agg(F.count("*").alias("n"))


@query("WITH e AS (SELECT DISTINCT k FROM (SELECT o_totalprice AS k, row_number() OVER (ORDER BY o_totalprice) AS rn, count(*) OVER () AS n FROM orders) WHERE rn IN (SELECT (i * n + 9) // 10 FROM range(1, 10) t(i))), t AS (SELECT k, rn, n FROM (SELECT c_acctbal AS k, row_number() OVER (ORDER BY c_acctbal) AS rn, count(*) OVER () AS n FROM customer)), b AS (SELECT (SELECT count(*) FROM e WHERE e.k < o_totalprice) + 1 AS tile FROM orders) SELECT t.k AS mapped, count(*) AS n FROM b JOIN t ON t.rn = (b.tile * t.n + 9) // 10 GROUP BY 1")
def quantile_normalised(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order totals answered by the account balance of the same decile."""
    found = quantiles.normalised(table(spark, sf_dir, "orders"), "o_totalprice", table(spark, sf_dir, "customer"), "c_acctbal", 10)
    return found.groupBy("mapped").agg(F.count("*").alias("n"))


@query(_AGREE)
def eps_sweep_agrees(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The answers of every eps of the sweep, over families on both sides of the branch rule."""
    runs = [Settings(tall=TallCache.of(e), finish_rows=500) for e in _EPS]
    return spark.createDataFrame([(all(_same(spark, sf_dir, runs, k).first()["agree"] for k in ("tail", "permille")),)], "agree boolean")


@query(_AGREE)
def collapse_by_distinct_agrees(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The histogram is taken for the few quantities and not for the many prices; answers are the same."""
    rows, same = table(spark, sf_dir, "lineitem"), []
    for key, few in (("l_quantity", True), (PRICE, False)):
        ledger = Ledger()
        a = multi_select(rows, key, W.TAIL, settings=Settings(collapse="auto", collapse_values=1000, branch="partition", finish_rows=500), ledger=ledger).collect()
        same += [a == multi_select(rows, key, W.TAIL).collect(), bool(ledger.levels) != few]
    return spark.createDataFrame([(all(same),)], "agree boolean")


def _pruned(pivots: str) -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        rows, ranks, n = _tail_ranks(spark, sf_dir)
        return baselines.binary_prune(rows, PRICE, ranks, max(500, n // 8), pivots=pivots)

    run.__name__ = f"baseline_binary_prune_{pivots}"
    query(_TAIL)(run)


for _p in ("random", "first"):
    _pruned(_p)

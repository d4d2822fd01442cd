"""SQL entry points: table functions, a grouped aggregate for small groups, selection over a SQL string."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import PandasUDFType
from pyspark.sql.udtf import SkipRestOfInputTableException

from orderstat.operators.engine import multi_select
from orderstat.plans.policy import Settings
from orderstat.sources.rank_family import RankFamilySource


@F.udtf(returnType="gap_no int, lo_rank long, hi_rank long, size long")
class GapTable:
    """gap_table(array of ranks, n): the gaps between the ranks."""

    def eval(self, ranks, n: int):
        edges = [0, *sorted(set(ranks)), n + 1]
        for k, (a, b) in enumerate(zip(edges, edges[1:])):
            yield k + 1, a, b, b - a


@F.udtf(returnType="grp string, rank long, value double")
class PickRanks:
    """pick_ranks(TABLE(t) PARTITION BY g ORDER BY v, array of ranks): t has columns g and v; stops after the largest rank."""

    def __init__(self):
        self.seen = 0

    def eval(self, row, ranks):
        self.seen += 1
        if self.seen in ranks:
            yield row["g"], self.seen, row["v"]
        if self.seen >= max(ranks, default=0):
            raise SkipRestOfInputTableException("no rank is left")


def quartiles_of(v: pd.Series) -> list:
    """Quartiles of a small group, by rank ceil(p n)."""
    s = v.dropna().sort_values().to_numpy()
    return [float(s[max(1, -(-k * len(s) // 4)) - 1]) for k in (1, 2, 3)] if len(s) else []


def register(spark: SparkSession) -> None:
    spark.udtf.register("gap_table", GapTable)
    spark.udtf.register("pick_ranks", PickRanks)
    spark.udf.register("exact_quantiles", F.pandas_udf(quartiles_of, "array<double>", PandasUDFType.GROUPED_AGG))
    spark.dataSource.register(RankFamilySource)


def select_ranks(spark: SparkSession, sql: str, key: str, ranks: list[int], settings: Settings = Settings()) -> DataFrame:
    return multi_select(spark.sql(sql), key, ranks, settings=settings)

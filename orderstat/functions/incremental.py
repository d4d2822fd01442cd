"""Later batches of ranks on the same data: the partition is kept, and only buckets that hold new ranks are read.

An extension of ours; the published method takes all ranks at once.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from orderstat.operators.distribute import bucketize
from orderstat.operators.engine import Wanted, _route, finish
from orderstat.operators.partition import Partition, counted
from orderstat.operators.summary import even_pivots
from orderstat.plans.policy import Settings


def save_partition(df: DataFrame, key: str, path: str, parts: int = 256, settings: Settings = Settings()) -> None:
    """Write the keys by bucket, with pivots and bounds beside them."""
    work = df.select(F.lit(0).cast("long").alias("sub"), F.col(key).alias("key")).filter("key is not null")
    part = counted(work, even_pivots(work, parts, settings.accuracy), settings)
    bucketize(work, part.pivots, part.most).repartition("bucket").write.partitionBy("bucket").parquet(f"{path}/rows")
    part.pivots.write.parquet(f"{path}/pivots")
    part.bounds_frame().coalesce(1).write.parquet(f"{path}/bounds")


def later_ranks(spark: SparkSession, path: str, ranks: list[int]) -> DataFrame:
    """(rank, value): reads only the buckets that the ranks fall in (partition pruning)."""
    pivots, bounds = spark.read.parquet(f"{path}/pivots"), spark.read.parquet(f"{path}/bounds").orderBy("bucket").collect()
    part = Partition(pivots, {r["sub"]: list(r["pivots"]) for r in pivots.collect()}, {0: [(r["bucket"], r["n"], r["lo_rank"]) for r in bounds]})
    rows = spark.read.parquet(f"{path}/rows")
    answers, needs, rest = _route(Wanted.listed(spark, [(0, r, r) for r in ranks]), part, rows.schema["key"].dataType)
    ids = spark.createDataFrame([(b, k) for k, (_, b, _) in enumerate(needs)], "bucket int, next long")
    held = rows.filter(F.col("bucket").isin([b for _, b, _ in needs])).join(F.broadcast(ids), "bucket").select(F.col("next").alias("sub"), "key")
    return answers.unionByName(finish(held, rest.frame)).select(F.col("asked").alias("rank"), "value").orderBy("rank")

"""The rest of a pattern against a plain walk through the seeded order."""

import pytest
from pyspark.sql import functions as F

from orderstat.llm import mixing


@pytest.mark.parametrize("large, small, rest", [((20_000, 7), 1, 19_500), ((50_000, 9), 3, 49_000), ((5_000, 4), 2, 36_001)])
def test_one_document_of_half_a_source(spark, large, small, rest):
    n = 20_000
    rows = spark.range(n + 1).select(F.col("id").alias("doc_id"), F.lit("[]").alias("pattern"), F.when(F.col("id") == n, large[0]).otherwise(small).cast("long").alias("size"))
    rows = rows.withColumn("bucket", F.when(F.col("doc_id") == n, large[1]).otherwise(F.pmod(F.xxhash64(F.lit(11), "doc_id"), F.lit(mixing.BUCKETS))).cast("int"))
    got = mixing._filled(rows, spark.createDataFrame([("[]", rest)], "pattern string, rest long"))
    left, want = rest, set()
    for r in rows.withColumn("turn", F.xxhash64("doc_id", "bucket")).orderBy("bucket", "turn", "doc_id", "size").collect():
        if r["size"] <= left:
            left -= r["size"]
            want.add(r["doc_id"])
    have = got.collect()
    taken = sum(r["size"] for r in have if r["more"])
    assert len(have) == n + 1 and {r["doc_id"] for r in have if r["more"]} == want
    assert rest - taken < small


def test_source_reaches_its_target(spark):
    """Half of a source's words are one document; the small ones still fill the target, wherever the large one comes."""
    docs = spark.range(12_001).select(F.col("id").alias("doc_id"), F.when(F.col("id") == 12_000, F.repeat(F.lit("w "), 12_000)).otherwise("w").alias("text"), F.lit("a").alias("source"))
    docs = docs.unionByName(spark.range(20_000, 20_065).select(F.col("id").alias("doc_id"), F.repeat(F.lit("w "), 400).alias("text"), F.lit("b").alias("source")))
    for seed in (11, 12, 13):
        got = mixing.mixed(docs, weights=(1, 4), seed=seed).filter("source = 'a'").agg(F.sum("taken"), F.max("target")).first()
        assert abs(got[0] - got[1]) <= 1

r"""Line dedup with Spark expressions only.

Lines are keyed by a 128-bit hash of the line stripped and lower-cased. Keys that occur often enough to matter are counted
first, combined before the shuffle; only their occurrences are kept for the exact count of documents, and each document
with lines to drop is put together again from the positions that stay.

Cases: a null text is one empty line; rows that repeat a doc_id count as one document; rows with a null doc_id lose nothing
and are not counted; other columns are ignored; an empty table gives an empty one.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from orderstat.llm.common import LOWER, SPACES, UPPER, id_and_text, stored


def split_lines(text: Column) -> Column:
    return F.split(F.coalesce(text, F.lit("")), "\n", -1)


def line_key(line: Column) -> Column:
    return F.translate(F.btrim(line, F.lit(SPACES)), UPPER, LOWER)


def without_common_lines(docs: DataFrame, min_chars: int = 40, min_docs: int = 5) -> DataFrame:
    """(doc_id, n_lines, n_dropped, kept) for each row of docs."""
    text = id_and_text(docs)
    rows = text.filter("doc_id is not null").select("doc_id", F.posexplode(split_lines(F.col("text"))).alias("at", "line"))
    rows = rows.select("doc_id", "at", line_key(F.col("line")).alias("key")).filter(F.char_length("key") >= min_chars)
    rows = rows.select("doc_id", "at", F.xxhash64("key").alias("h1"), F.xxhash64(F.lit(1), "key").alias("h2"))
    often = rows.groupBy("h1", "h2").agg(F.count("*").alias("n")).filter(F.col("n") >= min_docs).select("h1", "h2")
    often = stored(often, "often")  # on its own, so that the join's hot keys can be split
    held = stored(rows.join(often.hint("merge"), ["h1", "h2"]), "lines")
    common = held.groupBy("h1", "h2", "doc_id").agg(F.lit(1).alias("one")).groupBy("h1", "h2").agg(F.count("one").alias("n"), F.max("doc_id").alias("last")).filter(F.col("n") >= min_docs)
    common = stored(common.select("h1", "h2", "last"), "common")
    drop = held.join(common.hint("merge"), ["h1", "h2"]).filter("doc_id < last").groupBy("doc_id").agg(F.collect_set("at").alias("drop"))

    def stay(split: Column) -> Column:
        return F.array_join(F.transform(F.array_except(F.sequence(F.lit(0), F.size(split) - 1), F.col("drop")), lambda k: split[k]), "\n")

    lines = split_lines(F.col("text"))
    kept = F.when(F.col("drop").isNull(), F.coalesce("text", F.lit(""))).otherwise(F.transform(F.array(lines), stay)[0])
    # drop grows with the documents, so the join is a merge at every size; the engine splits its hot keys.
    return text.join(drop.hint("merge"), "doc_id", "left").select("doc_id", F.size(lines).cast("long").alias("n_lines"), F.when(F.col("drop").isNull(), 0).otherwise(F.size("drop")).cast("long").alias("n_dropped"), kept.alias("kept"))

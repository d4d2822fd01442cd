"""Near-duplicate documents by SimHash, linked through a vantage-point tree (vptree.py).

Cases: null and empty texts have fingerprint zero and link like any other; rows with equal fingerprints are one vertex
before anything is linked, so copies never form pairs; component_id is the least non-null doc_id of the component, null only
where it has none; repeated rows give repeated rows; other columns of docs are ignored; an empty table gives an empty one.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from itertools import combinations, repeat

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from orderstat.llm.common import ASCII_LOWER, by_doc, components, id_and_text, lean, stored
from orderstat.llm.vptree import Forest, near_edges

#: Members aimed at in a shard, fingerprints sampled for the trees above the shards, and how much fuller a shard is split.
SHARD, SAMPLE, DENSE = 8192, 65536, 16


def simhash(text: bytes, width: int = 3) -> int:
    words = text.translate(ASCII_LOWER).split()
    if not words:
        return 0
    grams = list(map(b" ".join, zip(*(words[k:] for k in range(width))))) if len(words) >= width else [b" ".join(words)]
    h = np.fromiter(map(xxhash.xxh64_intdigest, grams, repeat(42)), dtype="<u8", count=len(grams))
    ones = np.zeros(64, dtype=np.int64)
    for k in range(0, len(h), 1 << 16):
        part = h[k : k + (1 << 16)]
        ones += np.unpackbits(part.view(np.uint8).reshape(len(part), 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(ones * 2 > len(h), bitorder="little").view("<u8")[0])


def majority(h: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """The fingerprint of each text from hashes of its shingles: h by text, each text's from starts on."""
    out = np.zeros(len(starts), dtype=np.uint64)
    ends = np.append(starts[1:], len(h))
    for k, (a, z) in enumerate(zip(starts.tolist(), ends.tolist())):
        bits = np.unpackbits(h[a:z].astype("<u8", copy=False).view(np.uint8).reshape(z - a, 8), axis=1, bitorder="little")
        out[k] = np.packbits(bits.sum(axis=0, dtype=np.int64) * 2 > z - a, bitorder="little").view("<u8")[0]
    return out


def _prints(ids: list, texts: list[bytes]) -> dict[str, list]:
    got = np.array([simhash(t) for t in texts], dtype=np.uint64)
    return {"doc_id": pa.array(ids, pa.int64()), "fp": got.view(np.int64)}


def fingerprints(docs: DataFrame) -> DataFrame:
    """(doc_id, fp): the fingerprint as a signed long."""
    return id_and_text(docs).mapInArrow(by_doc(_prints), "doc_id long, fp long")


def links(prints: DataFrame, near: int = 2, shard: int = SHARD) -> DataFrame:
    """Edges (a, b) between the distinct fingerprints of prints (column fp) that connect all pairs within reach."""
    spark = prints.sparkSession
    n = prints.count()
    depth = max(0, math.ceil(math.log2(max(1, n / shard))))
    some = prints.sample(fraction=min(1.0, 2.0 * SAMPLE / max(1, n)), seed=3).limit(SAMPLE).toPandas()["fp"].to_numpy(dtype=np.int64)
    forest = spark.sparkContext.broadcast(Forest(np.sort(some).view(np.uint64), depth, near))

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fp = np.asarray(batch.column("fp")).astype(np.int64)
            for k in range(0, len(fp), 1 << 15):
                part = fp[k : k + (1 << 15)]
                where, at = forest.value.route(part.view(np.uint64))
                yield pa.RecordBatch.from_pydict({"shard": where.astype(np.int64), "fp": part[at]})

    def join(table: pa.Table) -> pa.Table:
        every = table.column("fp").to_numpy().astype(np.int64)
        a, b = near_edges(every.view(np.uint64), np.zeros(0, dtype=np.uint64), near)
        return pa.table({"a": every[a], "b": every[b]})

    dealt = prints.mapInArrow(lean(deal), "shard long, fp long")
    if not depth:
        return dealt.groupBy("shard").applyInArrow(join, "a long, b long")
    dealt = stored(dealt, "dealt")
    # Shards that are much fuller than planned hold close fingerprints by the thousand; there are at most n / (DENSE * shard) a tree.
    dense = stored(dealt.groupBy("shard").agg(F.count("*").alias("n")).filter(F.col("n") > DENSE * shard).select("shard"), "dense")
    even = dealt.join(F.broadcast(dense), "shard", "left_anti").groupBy("shard").applyInArrow(join, "a long, b long")
    return even.unionByName(crowd_links(dealt.join(F.broadcast(dense), "shard", "left_semi").select("fp").distinct(), near))


def crowd_links(prints: DataFrame, near: int) -> DataFrame:
    """The same edges for fingerprints that crowd together, without comparing all pairs and without a task that holds a crowd.

    Two fingerprints are within near bits only if some value lies within half of near, rounded up, of both. Every fingerprint names all
    values in that reach, so a value meets at most as many fingerprints as there are such values: 65 for two bits.
    """
    reach = (near + 1) // 2
    masks = [sum(1 << b for b in bits) for k in range(reach + 1) for bits in combinations(range(64), k)]
    signed = F.array([F.lit(int(np.uint64(m).astype(np.int64))) for m in masks])
    met = prints.select("fp", F.explode(F.transform(signed, lambda m: F.col("fp").bitwiseXOR(m))).alias("value")).groupBy("value").agg(F.array_sort(F.collect_list("fp")).alias("fps")).filter("size(fps) > 1")
    if near % 2 == 0:  # all that meet are within near bits: the least of them connects them
        return met.select(F.explode(F.slice("fps", 2, len(masks))).alias("a"), F.col("fps")[0].alias("b")).distinct()
    pairs = met.select(F.explode("fps").alias("a"), "fps").select("a", F.explode("fps").alias("b")).filter("b < a")
    return pairs.filter(F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= near).distinct()


def near_duplicates(docs: DataFrame, near: int = 2) -> DataFrame:
    """(doc_id, fp, component_id) for each row of docs."""
    prints = stored(fingerprints(docs), "prints")
    groups = stored(prints.groupBy("fp").agg(F.min("doc_id").alias("first")), "groups")
    tree = components(links(groups.select("fp"), near))
    linked = groups.join(tree.withColumnRenamed("node", "fp"), "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    least = linked.groupBy("root").agg(F.min("first").alias("component_id"))
    return prints.join(linked.join(least, "root").select("fp", "component_id"), "fp").select("doc_id", "fp", "component_id")


def one_of_each(docs: DataFrame, near: int = 2) -> DataFrame:
    """The rows of docs whose document stands for its component, each document once, with all their columns."""
    return standing(docs, near_duplicates(docs, near))


def standing(docs: DataFrame, found: DataFrame) -> DataFrame:
    """The rows of docs whose doc_id is the component_id of its row in found, each document once."""
    keep = found.filter(F.col("doc_id").eqNullSafe(F.col("component_id"))).select(F.col("doc_id").alias("_keep")).distinct().hint("merge")  # grows with docs
    met = docs.join(keep, docs["doc_id"].eqNullSafe(keep["_keep"]), "left_semi")
    return met.withColumn("_turn", F.row_number().over(Window.partitionBy("doc_id").orderBy(F.xxhash64("text")))).filter("_turn = 1").drop("_turn")

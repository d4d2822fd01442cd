"""Mixing sources to target weights by min-cost flow.

Documents are counted by membership pattern (the set of sources that hold them). Each pattern offers its words once for
nothing, a second time at a price and a third at a higher price; each source asks for its target. The cheapest flow says
how many words of a pattern each source takes. A pattern's words are then whole repetitions of all its documents, and the
rest by a seeded order: documents come by the hash of their id, whole buckets of that order first and single documents in
the buckets where the rest ends, passing over those too large for what is left, until none is left that fits.

The flow has a vertex per pattern and per source, which the driver holds: a few hundred bytes each.

Cases: a null text has size 0 and is taken zero times; null sources are a source of their own, last; a source whose documents
are all empty has target 0; rows of one source that share doc_id and text are one document with one decision, rows that share
the doc_id alone are documents of their own; a null id is an id like any other; a document of no source is taken zero times;
other columns are ignored; an empty table gives an empty one.
"""

from __future__ import annotations

import json
import math
from fractions import Fraction
from functools import reduce

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from orderstat.llm.common import WORD_PATTERN, stored

#: Buckets of the seeded order at most, and documents that a round goes through one by one.
BUCKETS, ZONE = 1 << 18, 4096
#: Rows of patterns, buckets or single documents, each under 100 bytes, up to which they are broadcast.
FEW = 200_000
#: Prices of the first, second and third use of a document: convex, so that no word repeats while another is unused.
PRICES = (0, 1, 3)


def words(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD_PATTERN)), F.lit(0)).cast("long")


def targets(sizes: dict, weights: dict, total: int, most: int) -> dict:
    """Shares of total by weight; a source stops at most times its size and the excess is shared again by weight."""
    left, open_, out = Fraction(total), [s for s in sizes], {}
    while open_:
        share = {s: left * weights[s] / sum(weights[t] for t in open_) for s in open_}
        full = [s for s in open_ if share[s] > most * sizes[s]]
        if not full:
            return out | share
        for s in full:
            out[s] = Fraction(most * sizes[s])
            left -= out[s]
            open_.remove(s)
    return out


def cheapest_flow(offers: list[int], asks: list[int], may: list[list[int]], prices: tuple[int, ...] = PRICES) -> list[dict[int, int]]:
    """Words that each pattern gives each source: as many as can be, at the least price.

    offers: words of each pattern; asks: words of each source; may: the sources of each pattern. Only the uses of a pattern have
    prices, and they rise; so the largest flow of first uses comes first, then the largest that second uses add, and so on: a
    path that adds flow takes nothing back from what patterns give in all. Sources from which no path leads on are closed for good in
    their turn, so a pattern whose sources are full costs one look.
    """
    given: list[dict[int, int]] = [{} for _ in may]
    takers: list[dict[int, None]] = [{} for _ in asks]
    left, use = list(asks), [0] * len(offers)
    for turn in range(1, len(prices) + 1):
        closed: set[int] = set()
        for root, size in enumerate(offers):
            while (room := turn * size - use[root]) > 0:
                path = _way(root, may, takers, left, closed)
                if not path:
                    break
                push = min([room, left[path[-1]], *(given[path[k + 1]][path[k]] for k in range(1, len(path) - 1, 2))])
                for k in range(0, len(path), 2):
                    p, s = path[k], path[k + 1]
                    given[p][s] = given[p].get(s, 0) + push
                    takers[s][p] = None
                    if k + 2 < len(path):
                        after = path[k + 2]
                        given[after][s] -= push
                        if not given[after][s]:
                            del given[after][s], takers[s][after]
                use[root] += push
                left[path[-1]] -= push
    return given


def _way(root: int, may: list[list[int]], takers: list[dict[int, None]], left: list[int], closed: set[int]) -> list[int]:
    """Pattern, source, pattern, ..., a source that asks for more: each source but the last hands on what it has from the next pattern."""
    queue, by_pattern, by_source = [root], {root: -1}, {}
    for p in queue:
        for s in may[p]:
            if s in closed or s in by_source:
                continue
            by_source[s] = p
            if left[s] > 0:
                path = [s]
                while True:
                    path.append(by_source[path[-1]])
                    if path[-1] == root:
                        return path[::-1]
                    path.append(by_pattern[path[-1]])
            for q in takers[s]:
                if q not in by_pattern:
                    by_pattern[q] = s
                    queue.append(q)
    closed.update(by_source)
    return []


def _units(docs: DataFrame, sources: Column | None, seed: int, wide: int) -> list[Column]:
    """What a document is to the plan: its id, pattern, size and bucket, and a mark of its text that tells rows of one id apart."""
    member = F.array(docs["source"].cast("string")) if sources is None else F.coalesce(sources, F.array().cast("array<string>"))
    text = docs["text"].cast("string")
    pattern = F.to_json(F.sort_array(F.array_distinct(member), asc=False))
    bucket = F.pmod(F.xxhash64(F.lit(seed), docs["doc_id"].cast("long")), F.lit(wide)).cast("int")
    return [docs["doc_id"].cast("long").alias("_id"), pattern.alias("_pattern"), words(text).alias("_size"), F.xxhash64(F.lit(seed), text).alias("_mark"), bucket.alias("_bucket")]


def buckets_for(n: int) -> int:
    """Buckets of the seeded order for n documents: about their square root, so that neither a source's buckets nor a bucket's documents are many."""
    return min(BUCKETS, 1 << max(7, math.ceil(math.log2(max(1, n)) / 2)))


def _planned(docs: DataFrame, sources: Column | None, weights: tuple[int, ...], most: int, seed: int) -> tuple[DataFrame, DataFrame, int]:
    """Rows (doc_id, pattern, size, mark, bucket), a plan of a row for each pattern, and the number of buckets."""
    spark = docs.sparkSession
    prices = tuple(k * (k + 1) // 2 for k in range(most))
    wide = buckets_for(docs.count())
    rows = stored(docs.select(*_units(docs, sources, seed, wide)).toDF("doc_id", "pattern", "size", "mark", "bucket"), "sizes")
    offer = {r["pattern"]: int(r["size"]) for r in rows.groupBy("pattern").agg(F.sum("size").alias("size")).collect()}
    pattern = {p: json.loads(p) for p in sorted(offer)}
    names = sorted({s for p in pattern.values() for s in p}, key=lambda s: (s is None, s or ""))
    at = {s: k for k, s in enumerate(names)}
    size: dict = dict.fromkeys(names, 0)
    for p, ss in pattern.items():
        for s in ss:
            size[s] += offer[p]
    goal = targets(size, {s: weights[k % len(weights)] for s, k in at.items()}, sum(offer.values()), most)
    flow = cheapest_flow([offer[p] for p in pattern], [round(goal[s]) for s in names], [[at[s] for s in ss] for ss in pattern.values()], prices)
    plan = []
    for (p, ss), given in zip(pattern.items(), flow):
        use = min(sum(given.values()), most * offer[p])
        whole = min(use // offer[p], most) if offer[p] else 0
        # The source that stands for a pattern is the one that takes most of it.
        first = max(ss, key=lambda s: (given.get(at[s], 0), -at[s])) if ss else None
        plan.append((p, first, int(whole), int(use - whole * offer[p]), size.get(first, 0), float(goal.get(first, 0))))
    planned = spark.createDataFrame(plan, "pattern string, source string, whole int, rest long, source_size long, target double")
    return rows, _sent(planned, len(plan)), wide


def _sent(df: DataFrame, n: int) -> DataFrame:
    """A table of n short rows: broadcast up to FEW, met in a merge beyond."""
    return F.broadcast(df) if n <= FEW else df.hint("merge")


def _copies(most: int) -> Column:
    return F.when(F.col("size") == 0, 0).otherwise(F.least(F.col("whole") + F.col("more").cast("int"), F.lit(most))).cast("int")


def mixed(docs: DataFrame, sources: Column | None = None, weights: tuple[int, ...] = (1, 2, 3), most: int = 3, seed: int = 11) -> DataFrame:
    """(doc_id, source, size, source_size, target, copies, taken) for each row of docs.

    sources: an array column of the sources that hold a document; by default the column source alone. source is the first of
    them; source_size and target are that source's. What a pattern misses of its flow is less than the smallest document it passed over.
    """
    rows, planned, _ = _planned(docs, sources, weights, most, seed)
    met = _applied(rows, *_decided(rows, planned.select("pattern", "rest"))).join(planned, "pattern").withColumn("copies", _copies(most))
    return met.select("doc_id", "source", "size", "source_size", "target", "copies", (F.col("size") * F.col("copies")).cast("long").alias("taken"))


def _filled(rows: DataFrame, rests: DataFrame) -> DataFrame:
    """rows with more set for documents in seeded order, as far as their pattern's rest has room."""
    return _applied(rows, *_decided(rows, rests))


def _decided(rows: DataFrame, rests: DataFrame) -> tuple[DataFrame | None, DataFrame | None]:
    """Buckets (pattern, bucket, inside, zone) that are decided, and the documents of those in a zone with more.

    Rounds: whole buckets come first; from the bucket where the rest ends on, a zone of that bucket and about ZONE documents after it is
    gone through one by one, leaving out what no longer fits; the next round takes what is left to the buckets after the zone. A
    bucket whose smallest document is too large for what is left is passed over. Rounds end when no undecided document fits. Rows that
    are alike (id, size and text) are one document of all their words.
    """
    ends = rows.filter("size > 0").groupBy("pattern", "bucket").agg(F.sum("size").alias("n"), F.count("*").alias("docs"), F.min("size").alias("least"))
    ends = ends.join(rests.withColumnRenamed("rest", "left"), "pattern")
    # A source's buckets are about the square root of its documents, so the running sums of a hot source are short.
    order, whole = Window.partitionBy("pattern").orderBy("bucket"), Window.partitionBy("pattern")
    own = _own(rows)

    def fit(part: pd.DataFrame) -> pd.DataFrame:
        part = part.sort_values(["bucket", "turn", "doc_id", "size"], kind="stable")
        left, more = int(part["left"].iloc[0]) if len(part) else 0, []
        for size in (part["size"] * part["times"]).tolist():
            more.append(size <= left)
            left -= size if size <= left else 0
        return part.assign(more=more)[["pattern", "bucket", *own, "times", "more"]]

    kinds = ", ".join(f"{c} {rows.schema[c].dataType.simpleString()}" for c in ("pattern", "bucket", *own))
    decided, edges = None, None
    while True:
        ends = stored(ends.filter("least <= left"), "ends")
        if ends.isEmpty():
            return decided, edges
        upto = ends.withColumn("upto", F.sum("n").over(order)).withColumn("seen", F.sum("docs").over(order)).withColumn("inside", F.col("upto") <= F.col("left"))
        upto = upto.withColumn("left", F.col("left") - F.coalesce(F.max(F.when(F.col("inside"), F.col("upto"))).over(whole), F.lit(0)))
        upto = upto.withColumn("past", F.col("seen") - F.col("docs") - F.min(F.when(~F.col("inside"), F.col("seen") - F.col("docs"))).over(whole))
        marks = stored(upto.withColumn("zone", ~F.col("inside") & (F.col("left") > 0) & (F.col("past") < ZONE)).select("pattern", "bucket", "n", "docs", "least", "left", "inside", "zone"), "marks")
        zone = rows.filter("size > 0").join(marks.filter("zone").select("pattern", "bucket", "left"), ["pattern", "bucket"])
        lumps = zone.groupBy("pattern", "bucket", "left", *own).agg(F.count("*").alias("times")).withColumn("turn", F.xxhash64("doc_id", "bucket"))
        edge = stored(lumps.groupBy("pattern").applyInPandas(fit, f"{kinds}, times long, more boolean"), "zone")
        now = marks.filter("inside or zone").select("pattern", "bucket", "inside", "zone")
        decided, edges = (now, edge) if decided is None else (decided.unionByName(now), edges.unionByName(edge))
        spent = edge.filter("more").groupBy("pattern").agg(F.sum(F.col("size") * F.col("times")).alias("spent"))
        ends = marks.filter("not inside and not zone").join(spent, "pattern", "left").select("pattern", "bucket", "n", "docs", "least", (F.col("left") - F.coalesce("spent", F.lit(0))).alias("left"))


def _own(rows: DataFrame) -> list[str]:
    """What tells documents of a bucket apart."""
    return [c for c in ("doc_id", "size", "mark") if c in rows.columns]


def _applied(rows: DataFrame, decided: DataFrame | None, edges: DataFrame | None) -> DataFrame:
    """rows (doc_id, pattern, size, bucket, ...) with more."""
    if decided is None:
        return rows.withColumn("more", F.lit(False))
    met = rows.join(_sent(decided.select("pattern", "bucket", "inside"), decided.count()), ["pattern", "bucket"], "left")
    taken = edges.filter("more").select("pattern", "bucket", *[F.col(c).alias(f"_{c}_") for c in _own(rows)], F.lit(True).alias("_hit_"))
    same = reduce(lambda a, b: a & b, [met[c] == taken[c] for c in ("pattern", "bucket")] + [met[c].eqNullSafe(taken[f"_{c}_"]) for c in _own(rows)])
    hit = met.join(_sent(taken, taken.count()), same, "left")
    more = F.coalesce(F.col("_hit_") | F.col("inside"), F.lit(False)) & (F.col("size") > 0)
    return hit.select(*[met[c] for c in rows.columns], more.alias("more"))


def repeated(docs: DataFrame, sources: Column | None = None, weights: tuple[int, ...] = (1, 2, 3), most: int = 3, seed: int = 11) -> DataFrame:
    """The rows of docs, each as often as the mix takes it; rows of size 0 are left out. The decisions go to the rows, which stay where they are."""
    rows, planned, wide = _planned(docs, sources, weights, most, seed)
    decided = _decided(rows, planned.select("pattern", "rest"))
    # Names of docs may be any, so its row goes along as one struct.
    whole = docs.select(F.struct(*[docs[c] for c in docs.columns]).alias("_row"), *_units(docs, sources, seed, wide)).toDF("_row", "doc_id", "pattern", "size", "mark", "bucket")
    met = _applied(whole, *decided).join(planned.select("pattern", "whole"), "pattern").withColumn("copies", _copies(most)).filter("copies > 0")
    return met.select("_row", F.explode(F.sequence(F.lit(1), F.col("copies"))).alias("_turn")).select("_row.*")

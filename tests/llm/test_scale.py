"""Bounds that must hold as tables grow, and the ways taken beyond them."""

import random
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F
from test_operators import digests, key, plain_components, plain_repeats

from orderstat.llm import common, mixing, neardup, repeats, simhash, tokenfile, tokens, vptree


@pytest.mark.parametrize("depth", [5, 11, 16])
def test_fingerprints_are_dealt_to_as_many_shards_at_any_depth(depth):
    rng = np.random.default_rng(depth)
    prints = rng.integers(0, 1 << 64, 100_000, dtype=np.uint64)
    forest = vptree.Forest(prints[:65536], depth, 2)
    shard, at = forest.route(prints)
    assert len(at) == 3 * len(prints)
    if depth == 5:
        assert np.bincount(shard).max() < 4 * len(prints) / (1 << depth)
    # A fingerprint two bits away meets its original in one of the shards at least.
    near = prints ^ (np.uint64(1) << rng.integers(0, 64, len(prints), dtype=np.uint64)) ^ (np.uint64(1) << rng.integers(0, 64, len(prints), dtype=np.uint64))
    own, other = np.full((3, len(prints)), -1), np.full((3, len(prints)), -2)
    for (s, a), table in ((forest.route(prints), own), (forest.route(near), other)):
        table[s >> depth, a] = s
    assert (own == other).any(axis=0).all()


@pytest.mark.parametrize("near", [1, 2, 3])
def test_crowds_are_linked_by_shared_values(spark, near):
    r = random.Random(near)
    items = sorted({b ^ sum(1 << k for k in r.sample(range(64), r.randint(0, 3))) for b in (5, 1 << 60, r.getrandbits(64)) for _ in range(40)})
    signed = [int(np.uint64(x).astype(np.int64)) for x in items]
    found = simhash.crowd_links(spark.createDataFrame([(s,) for s in signed], "fp long"), near)
    roots = {x["node"]: x["root"] for x in common.components(found).collect()}
    groups = plain_components(items, near)
    least = {g: min(s for s, h in zip(signed, groups) if h == g) for g in groups}
    assert [roots.get(s, s) for s in signed] == [least[g] for g in groups]


def test_dense_shards_take_the_other_way(spark, monkeypatch):
    r = random.Random(9)
    items = sorted({7 ^ sum(1 << k for k in r.sample(range(64), r.randint(0, 4))) for _ in range(400)} | {r.getrandbits(64) for _ in range(200)})
    signed = [int(np.uint64(x).astype(np.int64)) for x in items]
    frame = spark.createDataFrame([(s,) for s in signed], "fp long")
    groups = plain_components(items, 2)
    least = {g: min(s for s, h in zip(signed, groups) if h == g) for g in groups}
    for dense in (1, 16):
        monkeypatch.setattr(simhash, "DENSE", dense)
        roots = {x["node"]: x["root"] for x in common.components(simhash.links(frame, 2, 16)).collect()}
        assert [roots.get(s, s) for s in signed] == [least[g] for g in groups]


def test_repeats_where_nothing_is_broadcast(spark, odd, rows, monkeypatch):
    monkeypatch.setattr(repeats, "BROADCAST_BYTES", 0)
    assert digests(repeats.without_repeats(odd)) == plain_repeats([(r[0], r[1]) for r in rows], 50)


def test_tables_without_rows(none):
    assert simhash.near_duplicates(none).count() == 0 and repeats.without_repeats(none).count() == 0
    assert neardup.near_duplicates(none).count() == 0 and mixing.repeated(none).count() == 0


def test_token_operators_without_rows(spark, none, tmp_path):
    public = pytest.importorskip("public_tokenizers")
    assert tokens.token_counts(none, public.path("byte_bpe_50k.json")).count() == 0
    tokenfile.write(none, f"file://{tmp_path}/t", public.path("word_bpe_49k.json"), 1)
    assert tokenfile.read(spark, f"file://{tmp_path}/t").count() == 0


def test_other_tokenizers_are_refused(odd):
    public = pytest.importorskip("public_tokenizers")
    with pytest.raises(ValueError):
        tokens.token_counts(odd, public.path("word_bpe_49k.json"))


# Mixing ------------------------------------------------------------------------------------------


def copies_of(docs, **how):
    return Counter({tuple(r)[:3]: r["n"] for r in mixing.repeated(docs, **how).groupBy("doc_id", "source", "text").agg(F.count("*").alias("n")).collect()})


def test_ids_that_stand_in_two_sources(spark):
    """One doc_id and size in several sources and rows: each row is repeated as the plan for its own source says."""
    r, rows = random.Random(4), []
    for k in range(300):
        for source in r.sample("abcd", r.randint(1, 3)):
            rows.append((k % 200 if k % 7 else None, f"{source if k % 2 else 'same'} " * (3 + k % 5), source))
    rows += [(9000, "copy of one text", "a")] * 25
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string").repartition(4)
    planned = mixing.mixed(docs).groupBy("doc_id", "source", "size").agg(F.sum("copies").alias("n")).collect()
    want = Counter({(p["doc_id"], p["source"], p["size"]): p["n"] for p in planned if p["n"]})
    got = Counter()
    for (i, s, t), n in copies_of(docs).items():
        got[i, s, len(t.split())] += n
    assert got == want and sum(want.values()) == mixing.mixed(docs).agg(F.sum("copies")).first()[0]


def test_selection_by_a_plain_walk(spark):
    """Whole repetitions and the rest of each source against targets and a walk over documents in seeded order."""
    r = random.Random(11)
    rows = [(k, "w " * r.randint(0, 30), r.choice("abc")) for k in range(400)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    sizes = Counter()
    for _, t, s in rows:
        sizes[s] += len(t.split())
    goal = mixing.targets(dict(sizes), {"a": 1, "b": 2, "c": 3}, sum(sizes.values()), 3)
    order = {x["doc_id"]: (x["b"], x["t"]) for x in docs.withColumn("b", F.pmod(F.xxhash64(F.lit(11), "doc_id"), F.lit(mixing.buckets_for(400))).cast("int")).withColumn("t", F.xxhash64("doc_id", "b")).collect()}
    want = {}
    for s in "abc":
        use = min(round(goal[s]), 3 * sizes[s])
        whole, left = divmod(use, sizes[s])
        for i, t, _ in sorted((x for x in rows if x[2] == s), key=lambda x: (*order[x[0]], x[0])):
            n = len(t.split())
            more = 0 < n <= left
            left -= n if more else 0
            want[i] = min(3, whole + more) * n
    assert {x["doc_id"]: x["taken"] for x in mixing.mixed(docs).collect()} == want


def test_many_patterns_flow_quickly():
    r = random.Random(2)
    may = [sorted(r.sample(range(40), r.randint(1, 4))) for _ in range(20_000)]
    offers = [r.randint(1, 1000) for _ in may]
    asks = [int(sum(offers) / 40 * r.uniform(0.2, 2.0)) for _ in range(40)]
    flow = mixing.cheapest_flow(offers, asks, may)
    taken = [sum(f.get(s, 0) for f in flow) for s in range(40)]
    assert all(t <= a for t, a in zip(taken, asks)) and all(sum(f.values()) <= 3 * o for f, o in zip(flow, offers)) and sum(taken) == sum(asks)
    assert all(set(f) <= set(m) for f, m in zip(flow, may))


def test_buckets_follow_the_square_root():
    assert [mixing.buckets_for(n) for n in (0, 50_000, 10**6, 5 * 10**9)] == [128, 256, 1024, 1 << 17]


# Files of several segments and blocks -------------------------------------------------------------


def test_files_of_many_segments_and_a_damaged_one(spark, small):
    """Segments and blocks of a few thousand tokens: ids come back whole, and a changed byte is noticed by the reader."""
    public = pytest.importorskip("public_tokenizers")
    word = public.path("word_bpe_49k.json")
    docs = common.table(spark, small, "documents")
    folder = f"{common.shared_dir(spark)}/many"
    tokenfile.write(docs, folder, word, 1, segment=9000, block=1500)
    files = spark.read.schema(tokenfile.SCHEMA).parquet(folder)
    assert files.count() > 8 and files.agg(F.max(F.size("blocks"))).first()[0] > 4
    t = tokens.load(word)
    want, at = {}, 0
    for x in sorted(docs.select("doc_id", "text").collect()):
        ids = t.encode(x["text"] or "", add_special_tokens=False).ids + [1]
        want[x["doc_id"]] = (at, ids)
        at += len(ids)
    assert {x["doc_id"]: (x["start"], list(x["ids"])) for x in tokenfile.read(spark, folder, with_ids=True).collect()} == want
    rows = [x.asDict(recursive=True) for x in files.collect()]
    stream = bytearray(rows[3]["blocks"][1]["stream"])
    stream[len(stream) // 2] ^= 1
    rows[3]["blocks"][1]["stream"] = bytes(stream)
    hurt = spark.createDataFrame(rows, tokenfile.SCHEMA)
    hurt.write.parquet(f"{folder}-hurt")
    with pytest.raises(Exception, match="checksum"):
        tokenfile.read(spark, f"{folder}-hurt").count()

"""The pipeline's near-dedup rule against brute-force Jaccard."""

import random

import numpy as np

import corpus_pipeline
from orderstat.llm import common, neardup, simhash


def sets(text):
    w = (text or "").translate(str.maketrans(common.UPPER, common.LOWER)).encode().split()
    return {tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} - {()}


def plain_kept(rows, threshold=0.8):
    """Ids that stand for their component, over all pairs."""
    root, have = list(range(len(rows))), [sets(t) for _, t in rows]

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in range(len(rows)):
        for b in range(a):
            both = len(have[a] & have[b])
            if both >= threshold * (len(have[a]) + len(have[b]) - both) - 1e-9:
                root[max(find(a), find(b))] = min(find(a), find(b))
    groups = {}
    for k, (i, _) in enumerate(rows):
        groups.setdefault(find(k), []).append(i)
    return {min((i for i in g if i is not None), default=None) for g in groups.values()}


def near_rows(seed):
    """Families of texts from very close to just under the threshold, a crowd around one text, and a passage that many share."""
    r, rows = random.Random(seed), []
    base = [[f"w{r.randrange(5000)}" for _ in range(r.randint(30, 200))] for _ in range(12)]
    for words in base:
        for edits in (0, 1, 1, 2, 3, 4, 6, 9):
            t = list(words)
            for _ in range(edits):
                t[r.randrange(len(t))] = f"x{r.randrange(10**6)}"
            rows.append(" ".join(t))
    for k in range(120):
        t = list(base[0]) + ["end"]
        for _ in range(k % 3):
            t[r.randrange(len(t))] = f"y{k}"
        rows.append(" ".join(t))
    shared = " ".join(f"s{k}" for k in range(40))
    rows += [shared + " " + " ".join(f"z{k}q{j}" for j in range(40)) for k in range(60)]
    return list(enumerate(rows))


def test_against_brute_force(spark):
    for seed in (1, 2):
        rows = near_rows(seed)
        docs = spark.createDataFrame(rows, "doc_id long, text string")
        assert {x["doc_id"] for x in neardup.one_of_each(docs).collect()} == plain_kept(rows)


def test_stage_links_texts_that_share_four_fifths(spark):
    """Two texts with a similarity over 0.8 whose 3-word fingerprints differ by more than two bits."""
    docs = common.table(spark, "/root/testdata/sf0.1", "documents").filter("doc_id IN (0, 7818)")
    a, b = (sets(x["text"]) for x in docs.collect())
    assert len(a & b) >= 0.8 * len(a | b)
    assert [x["doc_id"] for x in corpus_pipeline.dedup_stage(spark, docs, "").collect()] == [0]


def test_table(spark, small):
    docs = common.table(spark, small.replace("0.001", "0.01"), "documents")
    rows = [(x["doc_id"], x["text"]) for x in docs.select("doc_id", "text").collect()]
    assert {x["doc_id"] for x in corpus_pipeline.dedup_stage(spark, docs, small).collect()} == plain_kept(rows)


def test_odd(odd, none):
    got = neardup.one_of_each(odd)
    ids = [x["doc_id"] for x in got.collect()]
    assert got.columns == odd.columns and len(ids) == len(set(ids)) and {1, 5, 9} <= set(ids) and not {6, 10, 2, 11} & set(ids)
    assert neardup.one_of_each(none).count() == 0


def test_fingerprints_go_through_the_tree(spark, monkeypatch):
    """Texts whose fingerprints lie close are linked by the tree and the check of their shingles, without a band."""
    r = random.Random(3)
    words = [f"w{r.randrange(9000)}" for _ in range(900)]
    rows = [(k, " ".join(words[:j] + [f"x{k}"] * (k > 0) + words[j + 1 :])) for k, j in enumerate((0, 100, 300, 700))] + [(9, " ".join(reversed(words)))]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    digest, h, starts, at = neardup.vertices([t.encode() for _, t in rows], 5)
    prints = simhash.majority(h, starts)
    assert list(at) == [0, 1, 2, 3, 4] and all(int(np.bitwise_count(prints[0] ^ p)) <= neardup.NEAR for p in prints[:4])
    asked = []
    links = neardup.tree_links
    monkeypatch.setattr(neardup, "tree_links", lambda *a: asked.append(a) or links(*a))
    monkeypatch.setattr(neardup, "MOST_LEADERS", -2)  # no round of the bands
    assert {x["doc_id"] for x in corpus_pipeline.dedup_stage(spark, docs, "").collect()} == {0, 9} and asked


def test_close_fingerprints_are_not_enough(spark, monkeypatch):
    """Under one fingerprint all texts are candidates, and only those that share four fifths of their shingles are linked."""
    monkeypatch.setattr(neardup, "tree_pairs", lambda prints: prints.select("vertex").crossJoin(prints.select(prints["vertex"].alias("b"))).withColumnRenamed("vertex", "a").filter("a < b"))
    rows = near_rows(4)[:40]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    assert {x["doc_id"] for x in neardup.one_of_each(docs).collect()} == plain_kept(rows)


def joined(spark, rows):
    """Pairs of by_prefix, each text under its own root, and the bytes shuffled for them."""
    shuffled = lambda: spark._jsc.sc().statusStore().executorList(True).head().totalShuffleWrite()
    texts, before = spark.createDataFrame(rows, "vertex long, text string"), shuffled()
    pairs = {(min(x["x"], x["y"]), max(x["x"], x["y"])) for x in neardup.by_prefix(texts, texts.selectExpr("vertex", "vertex root"), 5, 0.8).collect()}
    return pairs, shuffled() - before


def linked(rows, pairs, threshold=0.8):
    """The components that the pairs which reach the threshold make."""
    have, root = {i: sets(t) for i, t in rows}, {i: {i} for i, _ in rows}
    for a, b in pairs:
        if len(have[a] & have[b]) >= threshold * len(have[a] | have[b]) - 1e-9 and root[a] is not root[b]:
            root[a] |= root[b]
            root |= {i: root[a] for i in root[b]}
    return {frozenset(x) for x in root.values()}


def test_texts_that_share_a_few_passages_take_no_shingles_along(spark):
    """The join by prefixes shuffles each shingle a few times, not a text's whole set for each shingle that few others share."""
    r = random.Random(5)
    passages = [[f"p{k}w{j}" for j in range(60)] for k in range(375)]
    order = [k for k in range(375) for _ in range(4)]
    r.shuffle(order)
    rows = [(k, " ".join(w for p in order[5 * k : 5 * k + 5] for w in passages[p])) for k in range(300)]
    rows.append((300, rows[0][1].rsplit(" ", 1)[0] + " other"))
    pairs, size = joined(spark, rows)
    assert (0, 300) in pairs and size < 4e6


def test_crowds_by_prefix_against_brute_force(spark):
    """Far more texts than are listed share the rarest shingles of each other, some above the threshold and most below."""
    r = random.Random(6)
    passages = [[f"p{k}w{j}" for j in range(30)] for k in range(16)]
    rows = [(k, " ".join(w for p in sorted(r.sample(range(16), 12)) for w in passages[p])) for k in range(4 * neardup.LISTED)]
    rows = list({t: (k, t) for k, t in rows}.values())
    pairs, _ = joined(spark, rows)
    want = linked(rows, [(a, b) for a, _ in rows for b, _ in rows if a < b])
    assert linked(rows, pairs) == want and 1 < len(want) < len(rows)


def test_parity_bits_differ_in_no_more_bits_than_shingles():
    r = np.random.default_rng(7)
    both = r.integers(0, 2**63, 3000).astype(np.uint64)
    parts = [np.sort(r.choice(both, n, replace=False)) for n in (1, 10, 400, 390, 2500, 3000)]
    bits = neardup.parity(np.concatenate(parts), np.cumsum([0, *map(len, parts)])[:-1])
    for a, x in zip(parts, bits):
        for b, y in zip(parts, bits):
            assert int(np.bitwise_count(x ^ y).sum()) <= len(np.setxor1d(a, b))

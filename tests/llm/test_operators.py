"""Each operator on odd inputs and against brute force."""

import hashlib
import random
import zlib
from collections import Counter

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from orderstat.llm import chat, classifier, common, decontaminate, lines, mixing, rans, recompress, repeats, rules, simhash, tokenfile, tokens, vptree

public = pytest.importorskip("public_tokenizers")
WORD, BYTE = public.path("word_bpe_49k.json"), public.path("byte_bpe_50k.json")


def key(x):
    return tuple((v is not None, v) for v in x)


# Op 1 --------------------------------------------------------------------------------------------


def plain_simhash(text):
    words = text.translate(str.maketrans(common.UPPER, common.LOWER)).encode().split()
    grams = [b" ".join(words[k : k + 3]) for k in range(len(words) - 2)] or ([b" ".join(words)] if words else [])
    hashes = [xxhash.xxh64_intdigest(g, 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def plain_components(items, near):
    root = list(range(len(items)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in range(len(items)):
        for b in range(a):
            if bin(items[a] ^ items[b]).count("1") <= near:
                root[max(find(a), find(b))] = min(find(a), find(b))
    return [find(k) for k in range(len(items))]


def test_near_duplicates(odd, rows):
    got = sorted((tuple(r) for r in simhash.near_duplicates(odd).collect()), key=key)
    prints = [plain_simhash(r[1] or "") for r in rows]
    groups = plain_components(prints, 2)
    ids = {g: min((r[0] for r, h in zip(rows, groups) if h == g and r[0] is not None), default=None) for g in groups}
    want = [(r[0], int(np.uint64(p).astype(np.int64)), ids[g]) for r, p, g in zip(rows, prints, groups)]
    assert got == sorted(want, key=key)


def test_spark_hash_is_the_same(spark):
    assert spark.sql("select xxhash64('a b c')").first()[0] == int(np.uint64(xxhash.xxh64_intdigest(b"a b c", 42)).astype(np.int64))


@pytest.mark.parametrize("shard", [4, 60, 10_000])
def test_tree_links_what_brute_force_links(spark, shard):
    r = random.Random(shard)
    base = [r.getrandbits(64) for _ in range(60)]
    items = sorted({b ^ sum(1 << k for k in r.sample(range(64), r.randint(0, 4))) for b in base for _ in range(5)} | {7 ^ (1 << a) ^ (1 << b) for a in range(20) for b in range(a)})
    frame = spark.createDataFrame([(int(np.uint64(x).astype(np.int64)),) for x in items], "fp long")
    roots = {x["node"]: x["root"] for x in common.components(simhash.links(frame, 2, shard)).collect()}
    signed = [int(np.uint64(x).astype(np.int64)) for x in items]
    want = plain_components(items, 2)
    least = {g: min(s for s, h in zip(signed, want) if h == g) for g in want}
    assert [roots.get(s, s) for s in signed] == [least[g] for g in want]


def test_tree_prunes():
    rng = np.random.default_rng(1)
    prints = rng.integers(0, 1 << 63, 20_000, dtype=np.uint64)
    shard, _, guest = vptree.Router(prints[:4000], 4, 2).route(prints)
    assert (~guest).sum() == len(prints) and len(shard) < 4 * len(prints)


def test_components_of_a_long_chain(spark):
    edges = spark.createDataFrame([(k, k + 1) for k in range(200)] + [(500, 501)], "a long, b long")
    got = {r["node"]: r["root"] for r in common.components(edges).collect()}
    assert got == {k: 0 for k in range(201)} | {500: 500, 501: 500}


def test_one_of_each(odd, rows):
    got = simhash.one_of_each(odd)
    assert got.columns == odd.columns
    ids = [r["doc_id"] for r in got.collect()]
    assert len(ids) == len(set(ids)) and {1, 5, 9} <= set(ids) and 10 not in ids and 6 not in ids


# Op 2 --------------------------------------------------------------------------------------------


def test_token_counts(odd, rows):
    t = tokens.load(BYTE)
    got = sorted((tuple(r) for r in tokens.token_counts(odd, BYTE).collect()), key=key)
    want = [(r[0], len((r[1] or "").encode()), n := len(t.encode(r[1] or "", add_special_tokens=False).ids), n > 512) for r in rows]
    assert got == sorted(want, key=key)


def _texts(seed, count):
    r = random.Random(seed)
    pools = [[chr(i) for i in range(1, 0x180)], [chr(i) for i in range(0x20, 0x7F)], [chr(i) for i in range(1, 0x3000)], list("aA1 '\n\tsßİéñ.,!?²½́ \u0085 ſΣςσ😀가中"), ["<|endoftext|>", "<|startoftext|>", "a ", " b", "'s", "'ll", "Don't", "<|STARTOFTEXT|>", "\u0307", "I", "İ", "中"]]
    for _ in range(count):
        pool = r.choice(pools)
        yield "".join(r.choice(pool) for _ in range(r.randint(0, 30)))


def test_counts_of_any_text():
    t, c = tokens.load(BYTE), tokens.Counting(BYTE, tokens.whole_tokens(BYTE))
    for text in _texts(1, 4000):
        assert c.count(text) == len(t.encode(text, add_special_tokens=False).ids), repr(text)


def test_engines_agree_on_checked_characters():
    import regex

    split, pattern, other = tokens.load(BYTE).pre_tokenizer, regex.compile(tokens.PIECES), regex.compile(tokens.UNCHECKED)
    for c in (c for c in range(0x20000) if not 0xD800 <= c <= 0xDFFF):
        if not other.match(chr(c)):
            text = f"a{chr(c)}1{chr(c)}!{chr(c)} "
            assert [len(p.encode()) for p in pattern.findall(text)] == [len(p[0]) for p in split.pre_tokenize_str(text)], hex(c)


# Op 3 --------------------------------------------------------------------------------------------


def plain_repeats(rows, window):
    split = [(i, (t or "").encode().split()) for i, t in rows]
    least = {}
    for i, w in split:
        if i is not None:
            for k in range(len(w) - window + 1):
                s = tuple(w[k : k + window])
                least[s] = min(least.get(s, i), i)
    out = []
    for i, w in split:
        cut = [False] * len(w)
        for k in range(len(w) - window + 1 if i is not None else 0):
            if least[tuple(w[k : k + window])] < i:
                cut[k : k + window] = [True] * window
        kept = b" ".join(x for x, c in zip(w, cut) if not c)
        out.append((i, len(w), sum(cut), hashlib.sha256(kept).hexdigest()))
    return sorted(out, key=key)


def digests(df):
    left = df.select("doc_id", "n_words", "n_removed", F.when(F.col("kept").isNull(), F.col("sha")).otherwise(F.sha2("kept", 256)))
    return sorted((tuple(r) for r in left.collect()), key=key)


def test_repeats(odd, rows):
    assert digests(repeats.without_repeats(odd)) == plain_repeats([(r[0], r[1]) for r in rows], 50)


@pytest.mark.parametrize("seed", [1, 2])
def test_repeats_of_few_words(spark, seed):
    """Texts over a tiny vocabulary with planted passages, runs and periods."""
    r = random.Random(seed)
    passage = [r.choice("abcdefgh") for _ in range(80)]
    docs = []
    for i in range(40):
        text = [r.choice("abcdefgh") for _ in range(r.randint(0, 150))]
        for _ in range(r.randint(0, 2)):
            k = r.randint(0, len(text))
            a = r.randint(0, 40)
            text[k:k] = r.choice([passage[a : a + r.randint(20, 60)], ["a"] * r.randint(1, 70), ["a", "b"] * r.randint(1, 40)])
        docs.append((i, " ".join(text)))
    frame = spark.createDataFrame(docs, "doc_id long, text string").repartition(4)
    for window in (50, 20):
        assert digests(repeats.without_repeats(frame, window)) == plain_repeats(docs, window)


def test_marks_do_not_depend_on_the_surroundings():
    r = random.Random(3)
    for _ in range(60):
        core = [r.choice("abcde") for _ in range(50)]
        marks = []
        for _ in range(2):
            text = [r.choice("abcde") for _ in range(r.randint(0, 60))]
            at = len(text)
            words, wall, starts = recompress.lay_out([repeats.fingerprints([x.encode() for x in text + core + [r.choice("abcde") for _ in range(r.randint(0, 60))]])])
            mark, has, _ = recompress.window_marks(recompress.parse(words, wall, 6), len(words), 50)
            marks.append((bool(has[starts[0] + at]), int(mark[starts[0] + at])))
        assert marks[0] == marks[1]


# Op 4 --------------------------------------------------------------------------------------------


def test_chat(spark):
    said = r"\### Assistant: </turn> ok"
    turns = [(1, 0, "user", said), (1, 1, "assistant", said), (2, 1, "assistant", "b<more/>"), (2, 0, "assistant", None), (2, 2, None, ""), (3, None, "a>b<", "\\b\\l"), (3, None, "a>b<", "\\b\\l"), (None, 0, "user", "x")]
    frame = spark.createDataFrame([(*t, 9) for t in turns], "conv_id long, turn long, role string, text string, turns int")
    parsed = chat.read_back(chat.formatted(frame)).collect()
    back = {r["conv_id"]: [(x["role"], t) for x in r["runs"] for t in x["texts"]] for r in parsed}
    assert back == {1: [("user", said), ("assistant", said)], 2: [("assistant", ""), ("assistant", "b<more/>"), ("", "")], 3: [("a>b<", "\\b\\l")] * 2, None: [("user", "x")]}
    assert {r["conv_id"]: len(r["runs"]) for r in parsed} == {1: 2, 2: 2, 3: 1, None: 1}
    facts = {r["conv_id"]: r for r in chat.digests(chat.read_back(chat.formatted(frame))).collect()}
    assert facts[2]["loss_chars"] == 8 and facts[2]["n_turns"] == 3 and facts[1]["loss_sha256"] == hashlib.sha256(said.encode()).hexdigest()
    assert chat.formatted(frame.limit(0)).count() == 0


# Op 5 --------------------------------------------------------------------------------------------


def plain_contained(docs, items, width=5, threshold=0.8):
    low = str.maketrans(common.UPPER, common.LOWER)
    grams = lambda t: decontaminate.shingles((t or "").translate(low).encode().split(), width)
    out = []
    for i, t in docs:
        own = grams(t)
        for j, q in items:
            asked = grams(q)
            if asked and len(asked & own) >= threshold * len(asked) - 1e-9:
                out.append((i, j, len(asked & own), len(asked)))
    return sorted(out, key=key)


def test_contained(spark, odd, rows):
    from conftest import LONG, PASSAGE

    words = LONG.split()
    items = [(1, PASSAGE), (2, " ".join(words[900:940])), (3, " ".join(words[900:936] + ["x"] * 4)), (4, " ".join(words[900:920] + ["x"] * 20)), (5, "TWO words"), (6, ""), (7, None), (8, "same same same same same same"), (1, PASSAGE)]
    frame = spark.createDataFrame(items, "item_id long, text string")
    got = sorted((tuple(r)[:4] for r in decontaminate.contained(odd, frame).collect()), key=key)
    assert got == plain_contained([(r[0], r[1]) for r in rows], items) and {(5, 2), (5, 3)} <= {g[:2] for g in got}
    kept = decontaminate.clean(odd, frame)
    assert kept.columns == odd.columns and kept.count() == len(rows) - sum(r[0] in {g[0] for g in got} for r in rows)
    assert decontaminate.contained(odd, frame.limit(0)).count() == 0


def test_item_blocks(spark, odd, rows, monkeypatch):
    items = spark.createDataFrame([(k, " ".join(f"w{k + j}" for j in range(30))) for k in range(40)], "item_id long, text string")
    want = sorted(map(tuple, decontaminate.contained(odd, items).collect()))
    monkeypatch.setattr(decontaminate, "BLOCK_BYTES", 1000)
    assert sorted(map(tuple, decontaminate.contained(odd, items).collect())) == want and len(want) == 80


# Op 6 --------------------------------------------------------------------------------------------


def test_quality(spark, small):
    docs, labels = common.table(spark, small.replace("0.001", "0.01"), "documents"), common.table(spark, small.replace("0.001", "0.01"), "labels")
    got = classifier.quality(docs, labels).join(labels, "doc_id").toPandas()
    held = got[got["held_out"]]
    assert all(classifier.fold(d) == 0 for d in held["doc_id"]) and (held["predicted"] == held["quality"]).mean() > 0.9
    assert got["score"].between(0, 1).all()


def test_quality_odd(spark, odd, rows, none):
    labels = spark.createDataFrame([(k, k % 2, 0) for k in range(1, 14)] + [(None, 1, 0), (3, None, 0)], "doc_id long, quality int, toxic int")
    got = classifier.quality(odd, labels).collect()
    assert len(got) == len(rows) and all(0 <= r["score"] <= 1 for r in got)
    assert {r["score"] for r in classifier.quality(odd, labels.limit(0)).collect()} == {0.5}
    assert classifier.accepted(odd, labels.limit(0)).count() == len(rows) and classifier.quality(none, labels).count() == 0


def test_calibration():
    rng = np.random.default_rng(3)
    x = rng.normal(size=(4000, 5))
    p = 1 / (1 + np.exp(-(x @ np.array([2.0, -1, 0.5, 0, 0]))))
    net = classifier.fit(x, (rng.random(4000) < p).astype(float), epochs=15)
    assert np.abs(net.score(x) - p).mean() < 0.08


# Op 7 --------------------------------------------------------------------------------------------


def test_token_files(spark, odd, rows, tmp_path):
    t = tokens.load(WORD)
    tokenfile.write(odd, f"file://{tmp_path}/t", WORD, 1)
    got = sorted((r["start"], r["doc_id"], list(r["ids"])) for r in tokenfile.read(spark, f"file://{tmp_path}/t", with_ids=True).collect())
    order = sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0))
    want = [(r[0], t.encode(r[1] or "", add_special_tokens=False).ids + [1]) for r in order]
    assert [g[1] for g in got] == [w[0] for w in want]
    assert sorted((g[1] or -1, g[2]) for g in got) == sorted((w[0] or -1, w[1]) for w in want)
    assert [g[0] for g in got] == [0, *np.cumsum([len(g[2]) for g in got])[:-1]]
    sums = {(r["doc_id"], r["ids_crc32"]) for r in tokenfile.read(spark, f"file://{tmp_path}/t").collect()}
    assert sums == {(d, zlib.crc32(np.array(i, dtype="<u4").tobytes())) for d, i in want}


def test_ids_of_any_text():
    t, w = tokens.load(WORD), tokenfile.WordIds(WORD)
    for text in _texts(2, 4000):
        assert np.frombuffer(w.ids(text.encode()), dtype="<u4").tolist() == t.encode(text, add_special_tokens=False).ids, repr(text)


@pytest.mark.parametrize("n", [1, 2, 63, 64, 5000, 300_000])
def test_coder_round_trip(n):
    ids = np.minimum(np.random.default_rng(n).zipf(1.3, n), 60_000).astype(np.uint32)
    table = rans.Table.of(np.bincount(ids))
    assert table.freq.sum() == rans.TOTAL
    coder = rans.Coder(rans.Table.unpack(table.pack()))
    lanes, stream, marks = coder.encode(ids)
    assert (coder.decode(n, lanes, stream, marks) == ids).all()
    count = len(np.frombuffer(marks, dtype="<u8")) // (lanes + 1)
    assert (np.concatenate([coder.decode(n, lanes, stream, marks, k, k + 1) for k in range(count)]) == ids).all()
    if n == 300_000:
        p = np.bincount(ids)[np.unique(ids)] / n
        assert len(stream) < 1.02 * (-(p * np.log2(p)).sum() * n / 8) + 20_000


def test_broken_block_is_noticed(spark, odd, tmp_path):
    table, blocks = tokenfile.pack_segment([(1, np.arange(500, dtype=np.uint32))])
    assert zlib.crc32(blocks[0]["stream"][:-1] + b"\xff") != blocks[0]["stream_crc"]


# Op 8 --------------------------------------------------------------------------------------------


def plain_rules(text):
    words, lined = text.encode().split(), text.split("\n")
    seen, dup = set(), 0
    for x in lined:
        if x.encode().split():
            dup += x in seen
            seen.add(x)
    grams = Counter(tuple(words[k : k + 8]) for k in range(len(words) - 7))
    cover = set()
    for k in range(len(words) - 7):
        if grams[tuple(words[k : k + 8])] > 1:
            cover.update(range(k, k + 8))
    return len(words), sum(len(w.decode()) for w in words), sum(c in "#*$%&|<>" for c in text), dup, len(cover)


def test_rules(odd, rows, none):
    got = sorted((tuple(r) for r in rules.quality_rules(odd).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed").collect()), key=key)
    want = [(r[0], *(c := plain_rules(r[1] or "")), c[0] < 20 or 100 * c[4] > 30 * c[0]) for r in rows]
    assert got == sorted(want, key=key) and rules.quality_rules(none).count() == 0


def test_rules_keep_clean_texts(spark, small):
    big = small.replace("0.001", "0.01")
    got = rules.quality_rules(common.table(spark, big, "documents")).join(common.table(spark, big, "labels"), "doc_id").filter("not base_failed")
    assert got.filter("quality = 1 and not kept").count() == 0 and got.filter("quality = 0 and not kept").count() > 0.5 * got.filter("quality = 0").count()


def test_js_distance():
    p, q = np.array([[1.0, 0, 0], [1, 1, 0]]), np.array([[0.0, 1, 1], [1, 1, 0]])
    assert np.allclose(rules.js_distance(p, q), [1, 0])


# Op 9 --------------------------------------------------------------------------------------------


def test_lines(odd, rows, none):
    low = str.maketrans(common.UPPER, common.LOWER)
    held = {}
    for r in rows:
        for x in (r[1] or "").split("\n"):
            k = x.strip(common.SPACES).translate(low)
            if len(k) >= 40 and r[0] is not None:
                held.setdefault(k, set()).add(r[0])
    common_keys = {k: max(d) for k, d in held.items() if len(d) >= 5}
    want = []
    for r in rows:
        all_lines = (r[1] or "").split("\n")
        kept = [x for x in all_lines if r[0] is None or r[0] >= common_keys.get(x.strip(common.SPACES).translate(low), r[0])]
        want.append((r[0], len(all_lines), len(all_lines) - len(kept), "\n".join(kept)))
    got = sorted((tuple(r) for r in lines.without_common_lines(odd).collect()), key=key)
    assert got == sorted(want, key=key) and any(w[2] for w in want) and lines.without_common_lines(none).count() == 0


# Op 10 -------------------------------------------------------------------------------------------


def test_targets():
    got = mixing.targets({"a": 10, "b": 100, "c": 1}, {"a": 1, "b": 2, "c": 3}, 111, 3)
    assert sum(got.values()) == 111 and got["c"] == 3 and got["a"] == 30 and got["b"] == 78


def brute_cost(offers, asks, may, prices):
    """Least price of the largest flow, word by word, on tiny inputs."""
    from itertools import product

    best = None
    ways = [[c for c in product(range(size * len(prices) + 1), repeat=len(s)) if sum(c) <= size * len(prices)] for size, s in zip(offers, may)]
    for pick in product(*ways):
        got = [0] * len(asks)
        for c, s in zip(pick, may):
            for x, k in zip(c, s):
                got[k] += x
        if all(g <= a for g, a in zip(got, asks)):
            price = sum(sum(prices[min(j // size, len(prices) - 1)] for j in range(sum(c))) for c, size in zip(pick, offers) if size)
            best = min(best or (0, 0), (-sum(got), price)) if best else (-sum(got), price)
    return best


@pytest.mark.parametrize("offers, asks, may", [([2, 1], [3, 2], [[0], [0, 1]]), ([1, 2, 1], [2, 3], [[0, 1], [1], [0]]), ([2], [9], [[0]])])
def test_flow_is_cheapest(offers, asks, may):
    flow = mixing.cheapest_flow(offers, asks, may)
    total = sum(sum(f.values()) for f in flow)
    price = sum(sum(mixing.PRICES[j // size] for j in range(sum(f.values()))) for f, size in zip(flow, offers))
    assert (-total, price) == brute_cost(offers, asks, may, mixing.PRICES)
    assert all(sum(f.get(k, 0) for f in flow) <= a for k, a in enumerate(asks))


def test_mixing(spark, odd, rows, none, small):
    docs = common.table(spark, small.replace("0.001", "0.01"), "documents")
    got = mixing.mixed(docs).toPandas()
    assert (got["taken"] <= 3 * got["size"]).all() and abs(got.groupby("source").first()["target"].sum() - got["size"].sum()) < 1
    for _, g in got.groupby("source"):
        assert abs(g["taken"].sum() - g["target"].iloc[0]) <= max(0.05 * g["target"].iloc[0], 50)
    assert got.sort_values("doc_id").equals(mixing.mixed(docs.repartition(7)).toPandas().sort_values("doc_id").set_axis(got.sort_values("doc_id").index))
    small_mix = mixing.mixed(odd).collect()
    assert len(small_mix) == len(rows) and {r["source"] for r in small_mix} == {None, "a", "b", "c"} and mixing.mixed(none).count() == 0
    repeated = mixing.repeated(docs)
    assert repeated.columns == docs.columns and repeated.count() == got["copies"].sum()


def test_overlapping_sources(spark):
    rows = [(k, "w " * 10, ["a", "b"] if k % 3 == 0 else ["a"]) for k in range(300)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, sources array<string>").withColumn("source", F.lit(None).cast("string"))
    got = mixing.mixed(docs, docs["sources"], weights=(1, 1)).toPandas()
    assert abs(got["taken"].sum() - got["size"].sum()) <= 30

"""The classifier, the quality rules' verdict and the repeats' digests against plain versions."""

import math
import re
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
import xxhash
from pyspark.sql import functions as F

from orderstat.llm import classifier, common, repeats, rules

LOW = str.maketrans(common.UPPER, common.LOWER)


@pytest.fixture(scope="module")
def learned(spark, small):
    docs, labels = common.table(spark, small, "documents"), common.table(spark, small, "labels")
    return docs, labels, classifier.learn(docs, classifier.taught(labels))


def buckets(text):
    return [xxhash.xxh3_64_intdigest(w.translate(common.ASCII_LOWER)) % classifier.BUCKETS for w in (text or "").encode().split()]


def shape(word):
    return re.sub(rb"(.)\1+", rb"\1", bytes(97 if 97 <= b <= 122 or b >= 128 else 65 if 65 <= b <= 90 else 48 if 48 <= b <= 57 else b for b in word), flags=re.S)


def test_context_vectors_by_hand(learned):
    """Each word's bucket sums the index vectors of the words beside it, over all documents."""
    docs, _, model = learned
    rng = np.random.default_rng(1)
    place, sign = rng.integers(0, classifier.DIMS, (classifier.SIGNS, classifier.BUCKETS)), rng.choice(np.array([-1.0, 1.0]), (classifier.SIGNS, classifier.BUCKETS))
    beside = Counter()
    for r in docs.select("text").collect():
        own = buckets(r["text"])
        for a, b in zip(own, own[1:]):
            beside[a, b] += 1
            beside[b, a] += 1
    want = np.zeros((classifier.BUCKETS, classifier.DIMS))
    for (a, b), n in beside.items():
        for k in range(classifier.SIGNS):
            want[a, place[k, b]] += n * sign[k, b]
    want /= np.maximum(np.sqrt((want * want).sum(axis=1, keepdims=True)), 1e-9)
    assert np.allclose(model.vectors, want, atol=1e-6)


def test_word_buckets_follow_the_corpus(learned, monkeypatch):
    """More bytes, more buckets; words that meet in the small table part in the larger one, and held-out rows are told as well."""
    assert [classifier.buckets_for(n) for n in (0, 100_000_000, 100_000_001, 10**9, 10**14)] == [1 << k for k in (14, 14, 15, 15, 19)]
    docs, labels, _ = learned
    monkeypatch.setattr(classifier, "BUCKET_BYTES", 1_000)
    monkeypatch.setattr(classifier, "WORDS_AT_ONCE", 700)
    model = classifier.learn(docs, classifier.taught(labels))
    size, n = docs.agg(F.sum(F.octet_length("text"))).first()[0], len(model.vectors)
    assert n == classifier.buckets_for(size) > classifier.BUCKETS
    place_rng = np.random.default_rng(1)
    place, sign = place_rng.integers(0, classifier.DIMS, (classifier.SIGNS, n)), place_rng.choice(np.array([-1.0, 1.0]), (classifier.SIGNS, n))
    want = np.zeros((n, classifier.DIMS))
    for r in docs.select("text").collect():
        own = [xxhash.xxh3_64_intdigest(w.translate(common.ASCII_LOWER)) % n for w in (r["text"] or "").encode().split()]
        for a, b in [*zip(own, own[1:]), *zip(own[1:], own)]:
            for k in range(classifier.SIGNS):
                want[a, place[k, b]] += sign[k, b]
    want /= np.maximum(np.sqrt((want * want).sum(axis=1, keepdims=True)), 1e-9)
    assert np.allclose(model.vectors, want, atol=1e-6)
    assert classifier.scores(docs, model).filter("score between 0 and 1").count() == docs.count()


def test_scores_by_hand(learned):
    """Pooling and the network's forward pass, word by word and unit by unit."""
    docs, _, model = learned
    got = {r["doc_id"]: r["score"] for r in classifier.scores(docs, model).collect()}
    net, rows = model.network, docs.select("doc_id", "text").collect()
    assert len(got) == len(rows)
    for r in rows[:60]:
        own, words = buckets(r["text"]), (r["text"] or "").encode().split()
        x = np.zeros(2 * classifier.DIMS + 1)
        for k, (b, w) in enumerate(zip(own, words)):
            x[: classifier.DIMS] += model.vectors[b]
            x[classifier.DIMS : -1] += model.shapes[xxhash.xxh3_64_intdigest(shape(w)) % classifier.BUCKETS]
            x[-1] += k > 0 and own[k - 1] == b
        x /= max(len(words), 1)
        hidden = [math.tanh(sum((x[i] - net.mean[i]) / net.scale[i] * net.w1[i, j] for i in range(len(x))) + net.b1[j]) for j in range(len(net.b1))]
        logit = sum(h * w for h, w in zip(hidden, net.w2)) + net.b2
        assert got[r["doc_id"]] == pytest.approx(1 / (1 + math.exp(-max(-30, min(30, logit / net.temperature)))), abs=1e-4)


def test_held_out_labels_teach_nothing(learned):
    docs, labels, model = learned
    held = classifier.crc32(F.col("doc_id")) % 5 == 0
    turned = labels.withColumn("quality", F.when(held, 1 - F.col("quality")).otherwise(F.col("quality")))
    other = classifier.learn(docs, classifier.taught(turned))
    assert labels.filter(held).count() > 0 and np.array_equal(other.network.w1, model.network.w1) and other.network.temperature == model.network.temperature


def kind(c):
    if ord(c) >= 128:
        return 8
    for k, chars in enumerate(("abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "0123456789", " \t\x0b\x0c", "\n\r", ".,;:!?'\"-()", "#*$%&|<>")):
        if c in chars:
            return k
    return 7


def distance(p, q):
    p, q = ({k: v / max(sum(d.values()), 1e-300) for k, v in d.items()} for d in (p, q))
    total = 0.0
    for k in p.keys() | q.keys():
        a, b = p.get(k, 0), q.get(k, 0)
        total += sum(x * math.log2(2 * x / (a + b)) for x in (a, b) if x > 0) / 2
    return math.sqrt(max(total, 0))


def test_verdicts_by_hand(spark, small):
    """References, distances and the verdict of every document; a small language and a null one are compared with all."""
    few = common.table(spark, small, "documents").select("doc_id", "text", "lang").collect()
    rows = [(r["doc_id"], r["text"], r["lang"]) for r in few] + [(-1, "zwölf Boxkämpfer jagen Viktor " * 20 + "quer über den großen Sylter Deich", "rare"), (-2, "$$ ## %% || " * 40 + "a b c d e f g h", None), (-3, None, None), (-4, "", "rare")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string").repartition(3)
    words, classes = {}, {}
    for _, t, lang in rows:
        words.setdefault(lang, Counter()).update((t or "").translate(LOW).encode().split())
        classes.setdefault(lang, Counter()).update(map(kind, t or ""))
    total = sum(c.total() for c in words.values())
    listed = {lang for lang, c in words.items() if c.total() >= max(rules.MIN_REFERENCE, rules.LEAST_SHARE * total)}
    assert listed and listed != set(words)
    words[False], classes[False] = sum(words.values(), Counter()), sum(classes.values(), Counter())
    common_words = {lang: {w for w, n in words[lang].items() if n >= 2 * rules.THETA * words[lang].total()} for lang in listed | {False}}

    def histogram(counts, picked):
        held = {w: n for w, n in counts.items() if w in picked}
        return held | {"": counts.total() - sum(held.values())}

    got = {r["doc_id"]: r for r in rules.quality_rules(docs).collect()}
    for i, t, lang in rows:
        key = lang if lang in listed else False
        own, r = Counter((t or "").translate(LOW).encode().split()), got[i]
        want = distance(Counter(map(kind, t or "")), classes[key]), distance(histogram(own, common_words[key]), histogram(words[key], common_words[key]))
        if own:
            assert (r["class_distance"], r["word_distance"]) == pytest.approx(want, abs=1e-9)
        odd = own.total() >= rules.MIN_WORDS and len(t or "") >= rules.MIN_CHARS and (want[0] > rules.MOST_CLASS_DISTANCE or want[1] > rules.MOST_WORD_DISTANCE)
        assert r["kept"] == (not r["base_failed"] and not odd)


def test_words_that_share_a_name_are_no_repeat(monkeypatch):
    """With every word under one name, windows are told apart by their words alone."""
    monkeypatch.setattr(repeats, "fingerprints", lambda words: np.full(len(words), 7, dtype=np.uint64))
    texts = [" ".join(f"w{k}" for k in range(60)), " ".join(f"v{k}" for k in range(70)), "x  " + "\n".join(f"w{k}" for k in range(5, 57)) + " y"]
    batch = pa.RecordBatch.from_pydict({"doc_id": pa.array([1, 2, 3]), "text": texts, "shared": pa.array([[7], [7], [7]], pa.list_(pa.int64()))})
    found = {}
    for out in repeats._windows(50)([batch]):
        for r in out.to_pylist():
            found.setdefault((r["h1"], r["h2"]), set()).add((r["doc_id"], r["at"]))
    assert {frozenset(v) for v in found.values() if len(v) > 1} == {frozenset({(1, 5 + k), (3, 1 + k)}) for k in range(3)}

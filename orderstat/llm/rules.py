r"""Quality rules: base counts, and distribution divergence against language references.

First pass: each task reports the words that make up a share of THETA or more of what it saw of a language, with their
counts. A word with twice that share of the whole language is then reported for THETA of the language at least, and at
most 1 / THETA words are, so those are the candidates. Second pass: counts per document, with a character-class histogram
and the counts of the candidates. The references are the sums of all documents' histograms
by language for languages of LEAST_SHARE of all words or more, of which there are at most 1 / LEAST_SHARE, whatever the lang column
holds; a document fails where its Jensen-Shannon distance (base 2) from its language is over a threshold and it is long
enough to judge.

Cases: null and empty texts have no words and fail the base rules; null lang is a language of its own; a language with under
MIN_REFERENCE words or LEAST_SHARE of all words is compared with the sum of all languages; repeated rows give repeated rows; other columns are
ignored; an empty table gives an empty one.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from orderstat.llm import recompress as R
from orderstat.llm.common import ASCII_LOWER, lean, pieces, raw_texts, stored
from orderstat.llm.repeats import fingerprints

#: Symbol characters of the base counts.
SYMBOLS = b"#*$%&|<>"
THETA = 0.001
MIN_REFERENCE = 2000
LEAST_SHARE = 0.001
#: Guards: words and characters below which a document is not judged by divergence.
MIN_WORDS, MIN_CHARS = 50, 200
MOST_CLASS_DISTANCE, MOST_WORD_DISTANCE = 0.32, 0.55
CLASSES = 9


def _class_table() -> np.ndarray:
    """Class of each byte: lower, upper, digit, space, line end, sentence mark, symbol, other mark, other letter; -1 inside a character."""
    kind = np.full(256, 7, dtype=np.int64)
    for k, chars in enumerate((b"abcdefghijklmnopqrstuvwxyz", b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"0123456789", b" \t\x0b\x0c", b"\n\r", b".,;:!?'\"-()", SYMBOLS)):
        kind[list(chars)] = k
    kind[0x80:0xC0] = -1
    kind[0xC0:] = 8
    return kind


KIND = _class_table()
WHITE = list(b" \t\n\x0b\x0c\r")


def _candidates(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    seen: dict = {}
    for batch in pieces(batches):
        for lang, raw in zip(batch.column("lang").to_pylist(), raw_texts(batch.column("text"))):
            seen.setdefault(lang, Counter()).update(raw.translate(ASCII_LOWER).split())
        if sum(map(len, seen.values())) > 1_000_000:  # what is reported so far counts as a task of its own
            yield _frequent(seen)
            seen = {}
    yield _frequent(seen)


def _frequent(seen: dict) -> pa.RecordBatch:
    """(lang, word, n) of the frequent words, and (lang, null, n) for all words."""
    found: list = [(lang, None, counts.total()) for lang, counts in seen.items()]
    for lang, counts in seen.items():
        least = THETA * counts.total()
        found += [(lang, w, n) for w, n in counts.items() if n >= least]
    langs, words, n = zip(*found) if found else ((), (), ())
    return pa.RecordBatch.from_pydict({"lang": pa.array(langs, pa.string()), "word": pa.array(words, pa.binary()), "n": pa.array(n, pa.int64())})


def _repeat_words(split: list[list[bytes]], width: int = 8) -> np.ndarray:
    out = np.zeros(len(split), dtype=np.int64)
    long = [k for k, w in enumerate(split) if len(w) >= width]
    if not long:
        return out
    words, wall, starts = R.lay_out([fingerprints(split[k]) for k in long])
    at = np.flatnonzero(R.whole_windows(wall, width))
    owner = np.searchsorted(starts, at, side="right") - 1
    key = R.mix(R.window_names(words, width, 0x5851F42D4C957F2D, 3)[at] + R.mix(owner.astype(np.uint64) + R.salt(5)))
    _, inverse, times = np.unique(key, return_inverse=True, return_counts=True)
    twice = at[times[inverse] > 1]
    step = np.zeros(len(words) + 1, dtype=np.int64)
    np.add.at(step, twice, 1)
    np.add.at(step, np.minimum(twice + width, len(words)), -1)
    covered = np.flatnonzero(np.cumsum(step)[:-1] > 0)
    np.add.at(out, np.array(long)[np.searchsorted(starts, covered, side="right") - 1], 1)
    return out


def _counts(common: dict[bytes, int]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches):
            texts = raw_texts(batch.column("text"))
            split = [t.split() for t in texts]
            out: dict[str, list] = {k: [] for k in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_chars", "classes", "which", "times")}
            for raw, words in zip(texts, split):
                per_byte = np.bincount(np.frombuffer(raw, dtype=np.uint8), minlength=256)
                chars = int(per_byte.sum() - per_byte[0x80:0xC0].sum())
                lines = [x for x in raw.split(b"\n") if x.strip()]
                found = Counter(common[w] for w in raw.translate(ASCII_LOWER).split() if w in common)
                out["n_words"].append(len(words))
                out["n_chars"].append(chars)
                out["word_chars"].append(chars - int(per_byte[WHITE].sum()))
                out["n_symbols"].append(int(per_byte[list(SYMBOLS)].sum()))
                out["n_dup_lines"].append(len(lines) - len(set(lines)))
                out["classes"].append(np.bincount(KIND[KIND >= 0], weights=per_byte[KIND >= 0], minlength=CLASSES).astype(np.int64))
                out["which"].append(list(found))
                out["times"].append(list(found.values()))
            ints = {k: pa.array(v, pa.list_(pa.int64()) if k in ("classes", "which", "times") else pa.int64()) for k, v in out.items()}
            yield pa.RecordBatch.from_pydict({"doc_id": batch.column("doc_id"), "lang": batch.column("lang"), "n_repeat_words": _repeat_words(split)} | ints)

    return run


def js_distance(p: np.ndarray, q: np.ndarray) -> np.ndarray:
    """Jensen-Shannon distance (base 2, 0 to 1) of each row of p from the row of q."""
    p = p / np.maximum(p.sum(axis=1, keepdims=True), 1e-300)
    q = q / np.maximum(q.sum(axis=1, keepdims=True), 1e-300)
    m = (p + q) / 2
    with np.errstate(divide="ignore", invalid="ignore"):
        left = np.where(p > 0, p * np.log2(p / m), 0).sum(axis=1)
        right = np.where(q > 0, q * np.log2(q / m), 0).sum(axis=1)
    return np.sqrt(np.maximum((left + right) / 2, 0))


def quality_rules(docs: DataFrame) -> DataFrame:
    """(doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, class_distance, word_distance, kept)."""
    text = docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs["text"].cast("string").alias("text"), docs["lang"].cast("string").alias("lang"))
    told = stored(text.select("text", "lang").mapInArrow(lean(_candidates), "lang string, word binary, n long").groupBy("lang", "word").agg(F.sum("n").alias("n")), "words")
    sums = told.filter("word is null")
    total = sums.agg(F.sum("n")).first()[0] or 0
    own = sums.filter((F.col("n") >= MIN_REFERENCE) & (F.col("n") >= LEAST_SHARE * total)).select(F.col("lang").alias("of"), F.col("n").alias("whole"))
    length = {r["of"]: int(r["whole"]) for r in own.collect()}  # at most 1 / LEAST_SHARE
    own = F.broadcast(docs.sparkSession.createDataFrame(list(length.items()), "of string, whole long"))
    found = told.filter("word is not null")
    by_lang = found.join(own, F.col("lang").eqNullSafe(F.col("of"))).filter(F.col("n") >= THETA * F.col("whole")).select("word")
    in_all = found.groupBy("word").agg(F.sum("n").alias("n")).filter(F.col("n") >= THETA * total).select("word")
    words = {bytes(r["word"]) for r in by_lang.union(in_all).distinct().collect()}  # at most 1 / THETA for each of the languages and for all
    common = {w: k for k, w in enumerate(sorted(words))}
    rows = stored(text.mapInArrow(lean(_counts(common)), "doc_id long, lang string, n_repeat_words long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_chars long, classes array<long>, which array<long>, times array<long>"), "counts")
    # Sums by language that has its own reference, and of the others together.
    marked = rows.join(own, F.col("lang").eqNullSafe(F.col("of")), "left").withColumn("listed", F.col("whole").isNotNull()).withColumn("of", F.when(F.col("listed"), F.col("of")))
    by_class = marked.select("of", "listed", F.posexplode("classes").alias("k", "n")).groupBy("of", "listed", "k").agg(F.sum("n").alias("n")).collect()
    by_word = stored(marked.select("of", "listed", "whole", F.explode(F.arrays_zip("which", "times")).alias("e")).groupBy("of", "listed", "whole", F.col("e.which").alias("k")).agg(F.sum("e.times").alias("n")), "by-word")
    # A reference keeps words of twice THETA of its language, at most 1 / (2 THETA) of them.
    picked_own = by_word.filter("listed").filter(F.col("n") >= 2 * THETA * F.col("whole")).select("of", "k", "n").collect()
    picked_all = by_word.groupBy("k").agg(F.sum("n").alias("n")).filter(F.col("n") >= 2 * THETA * max(total, 1)).orderBy("k").collect()
    classes = {key: np.zeros(CLASSES) for key in [(None, False), *((lang, True) for lang in length)]}
    for r in by_class:
        classes[r["of"], r["listed"]][r["k"]] = r["n"]

    def reference_of(counts: list, held: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        counts = sorted(counts)
        w = np.array([n for _, n in counts], dtype=float)
        return held, np.array([k for k, _ in counts], dtype=np.int64), np.append(w, size - w.sum())

    rest = reference_of([(r["k"], r["n"]) for r in picked_all], sum(classes.values(), np.zeros(CLASSES)), total)
    reference = {lang: reference_of([(r["k"], r["n"]) for r in picked_own if r["of"] == lang], classes[lang, True], n) for lang, n in length.items()}

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = batch.num_rows
            langs = batch.column("lang").to_pylist()
            class_d, word_d = np.zeros(n), np.zeros(n)
            held = np.array(batch.column("classes").to_pylist(), dtype=float).reshape(n, CLASSES)
            size = np.asarray(batch.column("n_words")).astype(float)
            which, times = batch.column("which").to_pylist(), batch.column("times").to_pylist()
            langs = [x if x in reference else False for x in langs]
            for lang in set(langs):
                at = np.array([k for k, x in enumerate(langs) if x == lang])
                c, picked, w = rest if lang is False else reference[lang]
                own = np.zeros((len(at), len(picked) + 1))
                for j, k in enumerate(at):
                    where = np.searchsorted(picked, which[k])
                    for i, x, y in zip(where, which[k], times[k]):
                        if i < len(picked) and picked[i] == x:
                            own[j, i] += y
                    own[j, -1] = size[k] - own[j].sum()
                class_d[at], word_d[at] = js_distance(held[at], c[None, :]), js_distance(own, w[None, :])
            yield pa.RecordBatch.from_pydict({k: batch.column(k) for k in ("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_chars")} | {"class_distance": class_d, "word_distance": word_d})

    judged = rows.mapInArrow(lean(judge), "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, n_chars long, class_distance double, word_distance double")
    base = (F.col("n_words") < 20) | (100 * F.col("n_repeat_words") > 30 * F.col("n_words"))
    judged_long = (F.col("n_words") >= MIN_WORDS) & (F.col("n_chars") >= MIN_CHARS)
    odd = judged_long & ((F.col("class_distance") > MOST_CLASS_DISTANCE) | (F.col("word_distance") > MOST_WORD_DISTANCE))
    return judged.withColumn("base_failed", base).withColumn("kept", ~F.col("base_failed") & ~odd).drop("n_chars")

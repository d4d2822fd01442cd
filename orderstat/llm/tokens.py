"""Token counts of byte-level BPE without merging most words.

Offline, every string of the vocabulary is run through the merges alone; those that come out as one token form the whole-token
table. Per text, the pre-tokenizer's pieces are counted; a piece in the table counts one, any other is merged once per
worker and its count kept. Texts with a character on which the two pattern engines could differ (outside the checked
ranges below) or with an added token's string are left whole to the library.

Cases: null and empty text have no bytes and no tokens; repeated rows give repeated rows; other columns are ignored.
"""

from __future__ import annotations

import json
import os
from collections import Counter

import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from orderstat.llm.common import by_doc, held_for_stage, id_and_text

#: Fixed value: the public pattern by which this vocabulary's pre-tokenizer splits text.
PIECES = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
#: A character outside the code points in which both engines' classes were checked to agree (tests/llm/test_operators.py).
UNCHECKED = "[^\\x00-\u0557\u0900-\u0bff\u2000-\u2089\u20a0-\u2bff\u3000-\ua48c\uac00-\ud7a3\U0001f000-\U0001faff]"
#: Merged pieces whose counts a worker keeps, about 100 bytes each.
MOST_KEPT = 250_000


def byte_letters() -> dict[int, str]:
    """The printable stand-in of each byte in byte-level vocabularies: itself where printable, else the next from 256 on."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    others = [b for b in range(256) if b not in plain]
    return {b: chr(b) for b in plain} | {b: chr(256 + k) for k, b in enumerate(others)}


def load(path: str):
    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
    from tokenizers import Tokenizer

    return Tokenizer.from_file(path)


def splits_as_pieces(path: str) -> bool:
    """Whether the file's tokenizer splits untouched text by the pattern PIECES, as its byte-level form states it."""
    with open(path, encoding="utf-8") as f:
        told = json.load(f)
    split = told.get("pre_tokenizer") or {}
    return told.get("normalizer") is None and split.get("type") == "ByteLevel" and split.get("use_regex", True) and not split.get("add_prefix_space") and told["model"]["type"] == "BPE" and not told["model"].get("dropout")


def whole_tokens(path: str) -> frozenset[str]:
    """Texts of the vocabulary's strings that the merges turn into exactly that one token and that are one piece."""
    t, back = load(path), {c: b for b, c in byte_letters().items()}
    pattern, out = regex.compile(PIECES), set()
    for word, number in t.get_vocab(with_added_tokens=False).items():
        made = t.model.tokenize(word)
        if len(made) != 1 or made[0].id != number:
            continue
        try:
            text = bytes(back[c] for c in word).decode("utf-8")
        except (KeyError, UnicodeDecodeError):
            continue
        if text and pattern.findall(text) == [text]:
            out.add(text)
    return frozenset(out)


class Counting:
    """Counts tokens of texts; one for each worker process."""

    def __init__(self, path: str, whole: frozenset[str]):
        self.tokenizer, self.whole, self.kept = load(path), whole, {}
        self.letters = byte_letters()
        self.pattern, self.other = regex.compile(PIECES), regex.compile(UNCHECKED)
        self.added = [a.content for a in self.tokenizer.get_added_tokens_decoder().values()]

    def merged(self, piece: str) -> int:
        n = self.kept.get(piece)
        if n is None:
            if len(self.kept) >= MOST_KEPT:
                self.kept.clear()
            n = self.kept[piece] = len(self.tokenizer.model.tokenize("".join(map(self.letters.__getitem__, piece.encode()))))
        return n

    def count(self, text: str) -> int:
        if not text:
            return 0
        if self.other.search(text) or any(a in text for a in self.added):
            return len(self.tokenizer.encode(text, add_special_tokens=False).ids)
        found = Counter(self.pattern.findall(text))
        whole, total = self.whole, 0
        for piece, times in found.items():
            total += times if piece in whole else times * self.merged(piece)
        return total


def token_counts(docs: DataFrame, path: str, limit: int = 512) -> DataFrame:
    """(doc_id, n_bytes, n_tokens, over_limit) for each row of docs; path is a byte-level BPE file for the tokenizers library."""
    if not splits_as_pieces(path):
        raise ValueError(f"{path} does not split text by the byte-level pattern that the whole-token table is proven for")
    shipped = docs.sparkSession.sparkContext.broadcast(whole_tokens(path))  # bounded by the vocabulary

    def work(ids: list, texts: list[bytes]) -> dict[str, list]:
        count = held_for_stage(("counts", path), lambda: Counting(path, shipped.value)).count
        return {"doc_id": pa.array(ids, pa.int64()), "n_bytes": pa.array([len(t) for t in texts], pa.int64()), "n_tokens": pa.array([count(t.decode("utf-8", "replace")) for t in texts], pa.int64())}

    out = id_and_text(docs).mapInArrow(by_doc(work), "doc_id long, n_bytes long, n_tokens long")
    return out.withColumn("over_limit", F.col("n_tokens") > limit)

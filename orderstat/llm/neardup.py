"""Near-duplicate documents by the share of word shingles they have in common, each link verified.

Texts with equal shingle sets are one vertex. Each has a SimHash of its shingles; the vantage-point tree of simhash.py connects the
fingerprints within NEAR bits, and two vertices are linked only where the Jaccard similarity of their shingles, compared as strings,
reaches the threshold. Texts at 0.8 lie about 10 bits apart, up to 14 on sf0.1, and at such radii the tree's bounds exclude next to
nothing. What the tree does not reach is therefore completed by BANDS x ROWS minima of hashed shingles: vertices with equal minima
throughout a band are candidates too, verified alike. A pair at similarity s is no candidate of the bands with probability
(1 - s**ROWS)**BANDS, which is 5e-8 at 0.8 and less above, at any size of the table.

A crowded band is not paired out while its members can be joined through a few of them: leaders are compared with those not yet in
their component, round by round. What is left then, at any size of the table, are mostly texts that share a long passage and little else. They
are joined anew by prefixes: shingles in order of how many of these texts have them, rarest first. A text of n shows the first
n - ceil(threshold n) + 1 to texts of its size or less, and looks for others by fewer. Texts as similar as the threshold share one of
those, and what many texts share comes last. Where at most LISTED share one, the pairs whose sizes allow it are listed.
Where more do, they meet in blocks with PARITY bits each, which rule out pairs that differ in too many shingles and no others; only texts
left with a possible partner bring their hashed shingles. Components are thus those of all verified candidate pairs.

Cases: null and empty texts have no shingles and are copies of each other; a text of fewer words than a shingle is one shingle; words
are compared in ASCII lower case; component_id is the least non-null doc_id of the component, null only where it has none;
repeated rows give repeated rows; other columns of docs are ignored; an empty table gives an empty one.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from orderstat.llm import recompress as R
from orderstat.llm.common import ASCII_LOWER, by_doc, components, id_and_text, lean, pieces, raw_texts, small_enough, stored
from orderstat.llm.decontaminate import names, shingles
from orderstat.llm.simhash import links as tree_links
from orderstat.llm.simhash import majority, standing

BANDS, ROWS = 32, 4
#: Bits within which the tree connects fingerprints: NEAR + 1 blocks of bits of some 12 bits each still part the fingerprints.
NEAR = 4
#: Leaders of a crowded band that are tried at most, and only while a leader settles a tenth of the pairs.
MOST_LEADERS = 12
#: Texts that share a shingle up to which their pairs are listed, and the parity bits of a text in larger groups.
LISTED, PARITY = 32, 1024
#: Texts of a block at most, and shingles in them.
BLOCK, CELLS = 1024, 1_000_000
#: Vertices up to which they are broadcast to the documents rather than met in a shuffle.
FEW = 500_000
_TURN = R.mix(np.arange(1, BANDS * ROWS + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)) | np.uint64(1)


def named(texts: list[bytes], width: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the distinct shingles of each text, and the text each belongs to, by text."""
    split = [t.translate(ASCII_LOWER).split() for t in texts]
    long = [k for k, w in enumerate(split) if len(w) >= width]
    short = [k for k, w in enumerate(split) if 0 < len(w) < width]
    h, doc = names([split[k] for k in long], width) if long else (np.zeros(0, dtype=np.uint64), np.zeros(0, dtype=np.int64))
    one = np.array([xxhash.xxh64_intdigest(b" ".join(split[k]), 42) for k in short], dtype=np.uint64)
    h = np.concatenate([R.mix(h), one])
    doc = np.concatenate([np.array(long, dtype=np.int64)[doc], np.array(short, dtype=np.int64)])
    order = np.lexsort((h, doc))
    h, doc = h[order], doc[order]
    fresh = np.ones(len(h), dtype=bool)
    fresh[1:] = (h[1:] != h[:-1]) | (doc[1:] != doc[:-1])
    return h[fresh], doc[fresh]


def vertices(texts: list[bytes], width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """A digest of each text's shingle set, the shingles, where each text with shingles starts, and which texts those are."""
    h, doc = named(texts, width)
    digest = np.zeros(len(texts), dtype=np.uint64)
    starts = np.flatnonzero(np.append(True, doc[1:] != doc[:-1])) if len(h) else np.zeros(0, dtype=np.int64)
    if len(h):
        sizes = np.diff(np.append(starts, len(h))).astype(np.uint64)
        digest[doc[starts]] = R.mix(np.add.reduceat(R.mix(h + np.uint64(1)), starts) + sizes)
    return digest, h, starts, doc[starts]


def signed(width: int):
    def run(ids: list, texts: list[bytes]) -> dict[str, list]:
        digest, h, starts, at = vertices(texts, width)
        keys = np.zeros((len(at), BANDS), dtype=np.uint64)
        for k in range(BANDS * ROWS if len(h) else 0):
            keys[:, k // ROWS] = R.mix(keys[:, k // ROWS] * np.uint64(0x9E3779B97F4A7C15) + np.minimum.reduceat((h ^ _TURN[-1 - k]) * _TURN[k], starts) + np.uint64(k))
        prints = np.zeros(len(texts), dtype=np.uint64)
        prints[at] = majority(h, starts)
        edges = np.zeros(len(texts) + 1, dtype=np.int32)
        edges[at + 1] = BANDS
        bands = pa.ListArray.from_arrays(np.cumsum(edges).astype(np.int32), keys.ravel().view(np.int64))
        return {"doc_id": pa.array(ids, pa.int64()), "vertex": digest.view(np.int64), "fp": prints.view(np.int64), "bands": bands}

    return by_doc(run)


def jaccard(a: set, b: set) -> float:
    return len(a & b) / (len(a) + len(b) - len(a & b)) if a or b else 1.0


def _texts(docs: DataFrame, wanted: DataFrame, width: int) -> DataFrame:
    """(vertex, text) for each row (vertex, first) of wanted: one text whose shingles are the vertex's, of document first if that is not null."""
    wanted = wanted.select(F.col("vertex").alias("_vertex"), "first")
    wanted = F.broadcast(wanted) if small_enough(wanted, FEW) else wanted.hint("merge")

    def digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches):
            yield pa.RecordBatch.from_pydict({"text": batch.column("text"), "vertex": vertices(raw_texts(batch.column("text")), width)[0].view(np.int64)})

    text = id_and_text(docs)
    # The id, where there is one, leaves few texts to be hashed again; null ids would all meet.
    some = text.join(wanted.filter("first IS NOT NULL"), F.col("doc_id") == F.col("first"), "left_semi").select("text")
    other = text.filter("doc_id IS NULL").select("text")
    met = some.unionByName(other).mapInArrow(lean(digest), "text string, vertex long").join(wanted, F.col("vertex") == F.col("_vertex"), "left_semi")
    return met.groupBy("vertex").agg(F.min("text").alias("text"))


def verified(pairs: DataFrame, texts: DataFrame, width: int, threshold: float) -> DataFrame:
    """The rows (a, b) of pairs whose texts are as similar as the threshold."""
    met = pairs.join(texts.select(F.col("vertex").alias("a"), F.col("text").alias("left")), "a").join(texts.select(F.col("vertex").alias("b"), F.col("text").alias("right")), "b")

    def check(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cut = lambda t: shingles(t.translate(ASCII_LOWER).split(), width)
        last, own = None, set()
        for batch in batches:
            ok = []
            for a, left, right in zip(batch.column("a").to_pylist(), raw_texts(batch.column("left")), raw_texts(batch.column("right"))):
                if a != last:
                    last, own = a, cut(left)
                ok.append(jaccard(own, cut(right)) >= threshold - 1e-9)
            yield batch.select(["a", "b"]).filter(pa.array(ok, pa.bool_()))

    return met.select("a", "b", "left", "right").mapInArrow(lean(check), "a long, b long")


def parity(h: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """PARITY bits a text, each the parity of the number of its shingles that fall on it, from h by text, each text's from starts on.

    A shingle that only one of two texts has changes one bit, so no two texts differ in more bits than in shingles.
    """
    out = np.zeros((len(starts), PARITY // 8), dtype=np.uint8)
    ends = np.append(starts[1:], len(h))
    at = (h % np.uint64(PARITY)).astype(np.int64)
    for k in range(0, len(starts), 1024):
        a, z = starts[k], ends[min(k + 1024, len(starts)) - 1]
        own = ends[k : k + 1024] - starts[k : k + 1024]
        odd = np.bincount(np.repeat(np.arange(len(own)), own) * PARITY + at[a:z], minlength=len(own) * PARITY) & 1
        out[k : k + 1024] = np.packbits(odd.astype(bool).reshape(len(own), PARITY), axis=1)
    return out


def by_prefix(texts: DataFrame, left: DataFrame, width: int, threshold: float) -> DataFrame:
    """Pairs (x, y) across the roots of left (vertex, root) that may be as similar as the threshold: all that are, and few others."""

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches):
            h, doc = named(raw_texts(batch.column("text")), width)
            ends = np.searchsorted(doc, np.arange(batch.num_rows + 1)).astype(np.int32)
            bits = np.zeros((batch.num_rows, PARITY // 8), dtype=np.uint8)
            at = np.flatnonzero(np.diff(ends))
            bits[at] = parity(h, ends[at])
            yield pa.RecordBatch.from_pydict({"vertex": batch.column("vertex"), "root": batch.column("root"), "n": np.diff(ends), "bits": pa.array([b.tobytes() for b in bits], pa.binary()), "hs": pa.ListArray.from_arrays(ends, h.view(np.int64))})

    known = stored(texts.join(left, "vertex").select("vertex", "root", "text").mapInArrow(lean(cut), "vertex long, root long, n int, bits binary, hs array<long>"), "sets")
    each = known.select("vertex", F.explode("hs").alias("h"))
    held = stored(each.groupBy("h").agg(F.count("*").alias("df")).filter("df > 1"), "held")  # on its own, so that hot shingles of the join can be split
    met = each.join(held, "h").groupBy("vertex").agg(F.array_sort(F.collect_list(F.struct("df", "h"))).alias("s"))
    met = met.join(known.select("vertex", "root", "n"), "vertex")
    # What only one text has comes before all that is left here. A text looks for texts of its size or more by a shorter prefix than
    # the one by which smaller texts find it, for it must have more in common with them.
    n = F.col("n")
    own, other = (n - F.ceil(share * n - 1e-6) + 1 for share in (2 * threshold / (1 + threshold), threshold))
    first = n - F.size("s")
    shown = met.select("vertex", "root", "n", (own - first).alias("own"), F.posexplode(F.slice("s", 1, F.greatest(other - first, F.lit(0)).cast("int"))).alias("at", "e"))
    shown = stored(shown.select("vertex", "root", "n", (F.col("at") < F.col("own")).alias("seeks"), "e.h"), "shown")
    open_ = shown.groupBy("h").agg(F.min("root").alias("p"), F.max("root").alias("q"), F.max("seeks").alias("seeks"), F.count("*").alias("members"), F.sum("n").alias("cells")).filter("p < q and seeks")
    open_ = stored(open_.select("h", "members", F.ceil(F.greatest(F.col("members") / BLOCK, F.col("cells") / CELLS)).cast("int").alias("blocks")), "shared")
    # A crowded group is cut to blocks, and every two of them meet in a task of their own.
    sought = shown.join(open_.filter(F.col("members") > LISTED), "h").withColumn("block", F.pmod(F.xxhash64("vertex"), F.col("blocks")).cast("int"))
    sought = sought.withColumn("with", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    sought = sought.select("h", F.least("block", "with").alias("u"), F.greatest("block", "with").alias("w"), "vertex", "root", "n")

    def narrow(group: pa.Table) -> pa.Table:
        return hopeful(group, threshold)

    def compare(group: pa.Table) -> pa.Table:
        return similar(group, threshold)

    # Only texts that may have a partner in the block take their shingles there.
    kept = sought.join(known.select("vertex", "bits"), "vertex").groupBy("h", "u", "w").applyInArrow(narrow, sought.schema)
    crowds = stored(kept, "sought").join(known.select("vertex", "hs"), "vertex").groupBy("h", "u", "w").applyInArrow(compare, "x long, y long")
    return listed(shown.join(open_.filter(F.col("members") <= LISTED).select("h"), "h"), threshold).unionByName(crowds).distinct()


def listed(shown: DataFrame, threshold: float) -> DataFrame:
    """Pairs (x, y) of texts that share a shingle with few others, across roots, whose sizes allow the threshold."""
    groups = shown.groupBy("h").agg(F.collect_list(F.struct("vertex", "root", "n", "seeks")).alias("all"))
    rows = groups.select(F.explode("all").alias("one"), "all")
    sizes = lambda y: F.least(F.col("one.n"), y["n"]) >= threshold * F.greatest(F.col("one.n"), y["n"]) - 1e-9
    fit = lambda y: (F.col("one.vertex") < y["vertex"]) & (F.col("one.root") != y["root"]) & (F.col("one.seeks") | y["seeks"]) & sizes(y)
    return rows.select(F.col("one.vertex").alias("x"), F.explode(F.transform(F.filter("all", fit), lambda y: y["vertex"])).alias("y"))


def hopeful(group: pa.Table, threshold: float) -> pa.Table:
    """The rows of a group that may reach the threshold with another of its rows under another root, by their sizes and parity bits."""
    n, root = (group.column(c).to_numpy() for c in ("n", "root"))
    bits = np.frombuffer(b"".join(group.column("bits").to_pylist()), dtype=np.uint64).reshape(len(n), PARITY // 64)
    most, keep = (1 - threshold) / (1 + threshold), np.zeros(len(n), dtype=bool)
    for i in range(len(n) - 1):
        at = i + 1 + np.flatnonzero((root[i + 1 :] != root[i]) & (np.minimum(n[i], n[i + 1 :]) >= threshold * np.maximum(n[i], n[i + 1 :]) - 1e-9))
        at = at[np.bitwise_count(bits[at] ^ bits[i]).sum(axis=1) <= most * (n[at].astype(np.int64) + n[i]) + 1e-6]
        keep[at] = True
        keep[i] |= len(at) > 0
    return group.drop_columns(["bits"]).filter(pa.array(keep)).select(["h", "u", "w", "vertex", "root", "n"])


def similar(group: pa.Table, threshold: float) -> pa.Table:
    """Pairs (x, y) of a group's texts that reach the threshold by their hashed shingles hs, as few as connect what all such pairs connect."""
    vertex, root, n = (group.column(c).to_numpy() for c in ("vertex", "root", "n"))
    lists = group.column("hs").combine_chunks()
    h, owner = lists.flatten().to_numpy(), np.repeat(np.arange(len(n)), lists.value_lengths().to_numpy())
    order = np.argsort(h, kind="stable")
    edges = np.flatnonzero(np.append(True, np.diff(h[order]) != 0)) if len(h) else np.zeros(0, dtype=np.int64)
    both = np.zeros((len(n), len(n)), dtype=np.int32)
    ends, owner = np.append(edges[1:], len(h)), owner[order]
    for k in np.flatnonzero(ends - edges > 1):
        part = owner[edges[k] : ends[k]]
        both[np.ix_(part, part)] += 1
    a, b = np.nonzero(np.triu(both, 1))
    ok = (both[a, b] >= threshold * (n[a].astype(np.int64) + n[b] - both[a, b]) - 1e-9) & (root[a] != root[b])
    label = {int(r): int(r) for r in root}

    def top(r: int) -> int:
        while label[r] != r:
            label[r] = label[label[r]]
            r = label[r]
        return r

    out = []
    for i, j in zip(a[ok].tolist(), b[ok].tolist()):
        p, q = top(int(root[i])), top(int(root[j]))
        if p != q:
            label[max(p, q)] = min(p, q)
            out.append((vertex[i], vertex[j]))
    return pa.table({"x": pa.array([x for x, _ in out], pa.int64()), "y": pa.array([y for _, y in out], pa.int64())})


def _rooted(rows: DataFrame, roots: DataFrame, name: str, out: str = "root") -> DataFrame:
    """rows with the root of column name; vertices without a link are their own root."""
    known = roots.select(F.col("vertex").alias("_vertex"), F.col("root").alias("_root"))
    return rows.join(known, F.col(name) == F.col("_vertex"), "left").withColumn(out, F.coalesce("_root", name)).drop("_vertex", "_root")


def _merged(links: DataFrame, roots: DataFrame | None) -> DataFrame:
    """(vertex, root) of all vertices with a link, from the roots so far and new links: only roots are joined anew."""
    if roots is None:
        return stored(components(links).select(F.col("node").alias("vertex"), "root"), "roots")
    ends = _rooted(_rooted(links, roots, "a", "p"), roots, "b", "q")
    moved = stored(components(ends.filter("p <> q").select(F.col("p").alias("a"), F.col("q").alias("b"))).select(F.col("node").alias("vertex"), "root"), "moved")
    old = _rooted(roots.select("vertex", F.col("root").alias("was")), moved, "was").select("vertex", "root")
    fresh = moved.join(roots.select("vertex"), "vertex", "left_anti")
    return stored(old.unionByName(fresh), "roots")


def tree_pairs(prints: DataFrame) -> DataFrame:
    """Pairs (a, b) of vertices that connect those whose fingerprints the tree connects: (vertex, fp) has each vertex once.

    The least vertex of a fingerprint stands for it. Vertices without shingles are one vertex, which is left out.
    """
    leads = stored(prints.groupBy("fp").agg(F.min("vertex").alias("lead")), "leads")
    same = prints.join(leads, "fp").filter("vertex <> lead").select(F.col("vertex").alias("x"), F.col("lead").alias("y"))
    edges = stored(tree_links(leads.select("fp"), NEAR), "tree")
    ends = edges.join(leads.select(F.col("fp").alias("a"), F.col("lead").alias("x")), "a").join(leads.select(F.col("fp").alias("b"), F.col("lead").alias("y")), "b").select("x", "y")
    return same.unionByName(ends).select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct()


def near_duplicates(docs: DataFrame, width: int = 5, threshold: float = 0.8) -> DataFrame:
    """(doc_id, vertex, component_id) for each row of docs."""
    prints = stored(id_and_text(docs).mapInArrow(signed(width), "doc_id long, vertex long, fp long, bands array<long>"), "signed")
    groups = stored(prints.groupBy("vertex").agg(F.min("doc_id").alias("first")), "vertices")
    every = prints.dropDuplicates(["vertex"]).select("vertex", F.explode("bands").alias("band"))
    crowded = stored(every.groupBy("band").agg(F.min("vertex").alias("least"), F.max("vertex").alias("most")).filter("least < most").select("band"), "crowded")
    members = stored(every.join(crowded, "band", "left_semi"), "members")
    pairs = stored(tree_pairs(prints.filter("size(bands) > 0").select("vertex", "fp").dropDuplicates(["vertex"])), "pairs")
    wanted = members.select("vertex").unionByName(pairs.select(F.col("a").alias("vertex"))).unionByName(pairs.select(F.col("b").alias("vertex"))).distinct()
    texts = stored(_texts(docs, groups.join(wanted, "vertex", "left_semi"), width), "candidates")
    links = stored(verified(pairs, texts, width, threshold), "links")
    tested, roots, before = pairs, None if links.isEmpty() else _merged(links, None), None
    for turn in () if members.isEmpty() else range(MOST_LEADERS + 1):
        now = members.withColumn("root", F.col("vertex")) if roots is None else _rooted(members, roots, "vertex")
        now = stored(now.select("band", "vertex", "root"), "labelled")
        # Pairs across components by band: half of all pairs less those within a component.
        parts = now.groupBy("band", "root").agg(F.count("*").alias("n"), F.min(F.struct(F.xxhash64(F.lit(turn), "vertex").alias("h"), "vertex", "root")).alias("lead"))
        bands = stored(parts.groupBy("band").agg(((F.pow(F.sum("n"), 2) - F.sum(F.pow("n", F.lit(2)))) / 2).alias("cross"), F.min("lead").alias("lead")).filter("cross > 0").select("band", "cross", F.col("lead.vertex").alias("leader"), F.col("lead.root").alias("led")), "open")
        cross = bands.agg(F.sum("cross")).first()[0] or 0
        if not cross:
            break
        last = turn == MOST_LEADERS or (before is not None and cross > 0.9 * before)
        before = cross
        # Bands whose components are whole need no further look.
        members = stored(now.join(bands.select("band"), "band", "left_semi").select("band", "vertex", "root"), "across")
        if last:
            pairs = by_prefix(texts, members.select("vertex", "root").distinct(), width, threshold)
        else:
            pairs = members.join(bands.select("band", "leader", "led"), "band").filter("root <> led").select(F.col("vertex").alias("x"), F.col("leader").alias("y"))
        members = members.select("band", "vertex")
        pairs = pairs.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct()
        pairs = stored(pairs.join(tested, ["a", "b"], "left_anti"), "pairs")
        tested = tested.unionByName(pairs)
        links = stored(verified(pairs, texts, width, threshold), "links")
        if not links.isEmpty():
            roots = _merged(links, roots)
        if last:
            break
    tree = groups.withColumn("root", F.col("vertex")) if roots is None else groups.join(roots, "vertex", "left").withColumn("root", F.coalesce("root", "vertex"))
    least = tree.groupBy("root").agg(F.min("first").alias("component_id"))
    return prints.select("doc_id", "vertex").join(tree.join(least, "root").select("vertex", "component_id"), "vertex").select("doc_id", "vertex", "component_id")


def one_of_each(docs: DataFrame, width: int = 5, threshold: float = 0.8) -> DataFrame:
    """The rows of docs whose document stands for its component, each document once, with all their columns."""
    return standing(docs, near_duplicates(docs, width, threshold))

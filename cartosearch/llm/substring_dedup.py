"""Substring dedup with prefix-partitioned suffix trees.

Suffixes of DEPTH words decide: a word goes if a suffix of DEPTH words over it also starts in a document of
smaller id. Three steps keep this within memory and disk.

1. Each window of DEPTH words has an anchor, the run of ANCHOR words in it with the smallest hash. Equal
   windows have equal anchors, so only windows whose anchor occurs in two texts can repeat; the rest are
   dropped. Each group of texts sends its distinct anchor hashes once.
2. The surviving windows are sent, as word segments around their anchors, to the group of their anchor; of an anchor that
   very many texts share, window by window to the groups of their whole words, so that no prefix fills a task. There
   prefixes of as many words as needed split the suffixes into parts of bounded size; each part is sorted
   with its common prefix lengths, which is its suffix tree, and the nodes of depth DEPTH are the repeats, each
   with its smallest document. Words are compared as such there, hashes only chose the candidates.
3. The groups of texts get the smallest documents back and mark the covered words.

Whole-text copies are one text with the smallest id; the others lose all words if they have DEPTH or more.
Segments are sent once per group of texts, so a passage in a third of all documents adds one per group.

Null or empty text: no words, nothing removed. Null doc_id: neither smaller nor larger than any, so nothing
is removed there and nothing goes because of it. Rows that share a doc_id do not remove each other's words.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textblocks as tb
from . import unique_texts as ut

DEPTH = 13
ANCHOR = 5
#: Suffixes that are sorted together.
PART = 250_000
#: Texts, as far as groups tell, beyond which windows are dealt by all their words and not by their anchor.
HEAVY = 2_000


class Windows:
    """The windows of a slice of texts and their anchors."""

    def __init__(self, raw: list[bytes], depth: int = DEPTH, anchor: int = ANCHOR):
        self.data, offsets = ut.flat_of(raw)
        self.starts, self.ends, self.rows = tb.word_bounds(self.data, offsets)
        words = tb.word_hashes(self.data, self.starts, self.ends)
        text = np.repeat(np.arange(len(raw)), np.diff(self.rows))
        self.at = np.zeros(0, np.int64)
        self.text = np.zeros(0, np.int64)
        self.place = np.zeros(0, np.int64)
        self.hash = np.zeros(0, np.uint64)
        self.whole = np.zeros(0, np.uint64)
        if len(words) >= depth:
            runs = tb.shingle_hashes(words, anchor)
            span = depth - anchor + 1
            least = np.lib.stride_tricks.sliding_window_view(runs, span).argmin(axis=1)
            at = np.arange(len(words) - depth + 1)
            whole = text[at] == text[at + depth - 1]
            self.at, least = at[whole], least[whole]
            self.text, self.place = text[self.at], self.at + least
            self.hash = runs[self.place]
            self.whole = tb.shingle_hashes(words, depth)[self.at]

    def segments(self, use: np.ndarray, alone: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """First window (an index into at) and number of windows of the runs of `use` around one anchor; windows `alone`
        are one each."""
        index = np.flatnonzero(use)
        if not len(index):
            return index, index
        new = np.ones(len(index), bool)
        new[1:] = (np.diff(index) != 1) | (np.diff(self.place[index]) != 0) | (np.diff(self.text[index]) != 0) | alone[index[1:]]
        first = np.flatnonzero(new)
        return index[first], np.diff(np.append(first, len(index)))

    def words_of(self, window: int, count: int, depth: int = DEPTH) -> bytes:
        i = self.at[window]
        return b" ".join(self.data[self.starts[i] : self.ends[i + count + depth - 2]].tobytes().split())


def bucket_of(hashes: np.ndarray, buckets: int) -> np.ndarray:
    return ((hashes >> np.uint64(32)) * np.uint64(buckets)) >> np.uint64(32)


def _anchors(buckets: int):
    def run(table: pa.Table) -> pa.Table:
        p = table.column("p")[0].as_py()
        group = ut.Group(table)
        hashes, owners = [], []
        for numbers, raw in group.slices(lambda k: group.ids[k] is not None):
            w = Windows(raw)
            new = np.ones(len(w.place), bool)
            new[1:] = (np.diff(w.place) != 0) | (np.diff(w.text) != 0)
            hashes.append(w.hash[new])
            owners.append(np.array(numbers)[w.text[new]])
        h, t = np.concatenate([*hashes, np.zeros(0, np.uint64)]), np.concatenate([*owners, np.zeros(0, np.int64)])
        order = np.lexsort((t, h))
        h, t = h[order], t[order]
        begin = np.flatnonzero(np.concatenate(([True], h[1:] != h[:-1]))) if len(h) else np.zeros(0, np.int64)
        # Texts of the group that hold the anchor, up to what a byte tells.
        other = np.concatenate(([True], (h[1:] != h[:-1]) | (t[1:] != t[:-1]))) if len(h) else np.zeros(0, bool)
        held = np.minimum(np.add.reduceat(other, begin), 255).astype(np.uint8) if len(h) else np.zeros(0, np.uint8)
        distinct = h[begin]
        cuts = np.searchsorted(bucket_of(distinct, buckets), np.arange(buckets + 1)) if len(distinct) else np.zeros(buckets + 1, np.int64)
        full = [b for b in range(buckets) if cuts[b] < cuts[b + 1]]
        return pa.table({"b": pa.array(full, pa.int32()), "p": pa.array([p] * len(full), pa.int32()), "hashes": pa.array([distinct[cuts[b] : cuts[b + 1]].tobytes() for b in full], pa.binary()), "held": pa.array([held[cuts[b] : cuts[b + 1]].tobytes() for b in full], pa.binary())})

    return run


def _repeated(heavy: int):
    def run(table: pa.Table) -> pa.Table:
        """For each group its anchors that occur in two texts (kind 0), and those of them that occur in more than `heavy` (kind 2)."""
        hashes = [np.frombuffer(x, np.uint64) for x in table.column("hashes").to_pylist()]
        held = np.concatenate([np.frombuffer(x, np.uint8) for x in table.column("held").to_pylist()])
        _, inverse = np.unique(np.concatenate(hashes), return_inverse=True)
        texts = np.bincount(inverse, held)[inverse]
        out, at = [], 0
        for h, p, b in zip(hashes, table.column("p").to_pylist(), table.column("b").to_pylist()):
            n = texts[at : at + len(h)]
            at += len(h)
            out += [(p, 0, b, h[n > 1].tobytes()), (p, 2, b, h[n > heavy].tobytes())]
        cols = list(zip(*(r for r in out if r[3]))) or [()] * 4
        return pa.table([pa.array(c, t) for c, t in zip(cols, (pa.int32(), pa.int32(), pa.int32(), pa.binary()))], names=["p", "kind", "b", "payload"])

    return run


def _among(values: np.ndarray, known: np.ndarray) -> np.ndarray:
    """Which values are among the sorted known ones."""
    if not len(known):
        return np.zeros(len(values), bool)
    return known[np.minimum(np.searchsorted(known, values), len(known) - 1)] == values


def _kept_windows(raw: list[bytes], repeated: np.ndarray, heavy: np.ndarray, buckets: int):
    """(windows, segments as (bucket, words, first window, windows)) of the texts that may repeat.

    The prefix that deals them is the anchor, or for a heavy anchor, whose windows would not fit a task, all words of the window.
    """
    w = Windows(raw)
    use, alone = _among(w.hash, repeated), _among(w.hash, heavy)
    first, count = w.segments(use, alone)
    prefix = np.where(alone[first], w.whole[first], w.hash[first])
    where = bucket_of(prefix, buckets).astype(np.int64).tolist() if len(first) else []
    return w, [(b, w.words_of(f, c), f, c) for b, f, c in zip(where, first.tolist(), count.tolist())]


def _told_hashes(table: pa.Table, kind: int) -> np.ndarray:
    found = [np.frombuffer(x, np.uint64) for k, x in zip(table.column("kind").to_pylist(), table.column("payload").to_pylist()) if k == kind]
    return np.sort(np.concatenate([*found, np.zeros(0, np.uint64)]))


def _segments(buckets: int):
    def run(texts: pa.Table, told: pa.Table) -> pa.Table:
        out: dict[int, dict[tuple[bytes, int], int]] = {}
        if texts.num_rows:
            p, repeated, heavy = texts.column("p")[0].as_py(), _told_hashes(told, 0), _told_hashes(told, 2)
            group = ut.Group(texts)
            for numbers, raw in group.slices(lambda k: group.ids[k] is not None):
                w, found = _kept_windows(raw, repeated, heavy, buckets)
                for b, words, first, count in found:
                    doc, own = group.ids[numbers[w.text[first]]], out.setdefault(b, {})
                    own[words, count] = min(doc, own.get((words, count), doc))
        rows = []
        for b, own in out.items():
            order = sorted(own)
            rows.append((b, p, np.array([own[x] for x in order], np.int64).tobytes(), np.array([c for _, c in order], np.int32).tobytes(), b" ".join(x for x, _ in order)))
        cols = list(zip(*rows)) or [()] * 5
        return pa.table({"b": pa.array(cols[0], pa.int32()), "p": pa.array(cols[1], pa.int32()), "docs": pa.array(cols[2], pa.binary()), "counts": pa.array(cols[3], pa.binary()), "words": pa.array(cols[4], pa.large_binary()).cast(pa.binary())})

    return run


def prefix_parts(words: np.ndarray, suffixes: np.ndarray, most: int, depth: int):
    """Suffix numbers in parts of at most `most`, each part whole prefixes; a prefix of `depth` words stays whole."""
    todo = [(suffixes, 0)]
    while todo:
        part, d = todo.pop()
        if len(part) <= most or d == depth:
            yield part
            continue
        part = part[np.argsort(words[part + d], kind="stable")]
        value = words[part + d]
        cuts = np.flatnonzero(np.concatenate(([True], value[1:] != value[:-1])))
        pending: list[np.ndarray] = []
        size = 0
        for a, b in zip(cuts, np.append(cuts[1:], len(part))):
            if b - a > most:
                todo.append((part[a:b], d + 1))
                continue
            if size + b - a > most:
                yield np.concatenate(pending)
                pending, size = [], 0
            pending.append(part[a:b])
            size += b - a
        if pending:
            yield np.concatenate(pending)


def subtree_nodes(words: np.ndarray, part: np.ndarray, depth: int) -> tuple[np.ndarray, np.ndarray]:
    """The part in lexicographic order and, for each place, its node of that depth."""
    columns = [words[part + d] for d in range(depth)]
    order = np.lexsort(columns[::-1])
    common = np.ones(len(part) - 1, np.int64) * depth
    alive = np.ones(len(part) - 1, bool)
    for d, c in enumerate(columns):
        c = c[order]
        differs = alive & (c[1:] != c[:-1])
        common[differs] = d
        alive &= ~differs
    return part[order], np.concatenate(([0], np.cumsum(common < depth)))


def _subtrees(table: pa.Table) -> pa.Table:
    docs = [np.frombuffer(x, np.int64) for x in table.column("docs").to_pylist()]
    counts = np.concatenate([np.frombuffer(x, np.int32) for x in table.column("counts").to_pylist()]).astype(np.int64)
    known: dict[bytes, int] = {}
    coded = []
    for blob in table.column("words"):
        coded.append(np.fromiter((known.setdefault(w, len(known)) for w in blob.as_py().split()), np.int32))
    words = np.concatenate(coded)
    offsets = np.concatenate(([0], np.cumsum(counts + DEPTH - 1)[:-1]))
    inside = np.arange(counts.sum()) - np.repeat(np.cumsum(counts) - counts, counts)
    suffixes = np.repeat(offsets, counts) + inside
    doc_of = np.zeros(len(words), np.int64)
    doc_of[suffixes] = np.repeat(np.concatenate(docs), counts)
    least = doc_of.copy()
    for part in prefix_parts(words, suffixes, PART, DEPTH):
        ordered, node = subtree_nodes(words, part, DEPTH)
        begin = np.flatnonzero(np.concatenate(([True], node[1:] != node[:-1])))
        least[ordered] = np.minimum.reduceat(doc_of[ordered], begin)[node]
    least, out, at = least[suffixes], [], 0
    for row in table.column("counts").to_pylist():
        n = int(np.frombuffer(row, np.int32).sum())
        out.append(least[at : at + n].tobytes())
        at += n
    return pa.table({"p": table.column("p"), "kind": pa.array([1] * len(out), pa.int32()), "b": table.column("b"), "payload": pa.array(out, pa.binary())})


def _removal(buckets: int, with_text: bool):
    def run(texts: pa.Table, told: pa.Table) -> pa.Table:
        rows = []
        if texts.num_rows:
            repeated, heavy = _told_hashes(told, 0), _told_hashes(told, 2)
            minima = {b: np.frombuffer(x, np.int64) for k, b, x in zip(told.column("kind").to_pylist(), told.column("b").to_pylist(), told.column("payload").to_pylist()) if k == 1}
            group = ut.Group(texts)
            marks: dict[int, list[tuple[int, int, bytes, int]]] = {}
            segments: dict[int, set[tuple[bytes, int]]] = {}
            for numbers, raw in group.slices(lambda k: group.ids[k] is not None):
                w, found = _kept_windows(raw, repeated, heavy, buckets)
                for b, words, first, count in found:
                    t = int(w.text[first])
                    segments.setdefault(b, set()).add((words, count))
                    marks.setdefault(numbers[t], []).append((b, int(w.at[first] - w.rows[t]), words, count))
            places: dict[int, dict[tuple[bytes, int], int]] = {}
            for b, own in segments.items():
                at = 0
                for s in sorted(own):
                    places.setdefault(b, {})[s] = at
                    at += s[1]
            for i, data in (x for numbers, raw in group.slices() for x in zip(numbers, raw)):
                key, doc, words = group.keys[i], group.ids[i], unspaced(data)
                gone = np.zeros(len(words) + 1, np.int64)
                for b, at, segment, count in marks.get(i, ()):
                    k = places[b][segment, count]
                    starts = at + np.flatnonzero(minima[b][k : k + count] < doc)
                    np.add.at(gone, starts, 1)
                    np.add.at(gone, starts + DEPTH, -1)
                gone = np.cumsum(gone[:-1]) > 0
                kept = b" ".join([x for x, g in zip(words, gone.tolist()) if not g])
                whole = b" ".join(words)
                if with_text:
                    rows.append((key, doc, len(words), int(gone.sum()), kept.decode(), whole.decode()))
                else:
                    rows.append((key, doc, len(words), int(gone.sum()), hashlib.sha256(kept).hexdigest(), hashlib.sha256(whole).hexdigest()))
        cols = list(zip(*rows)) or [()] * 6
        kinds = (pa.binary(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.string())
        return pa.table([pa.array(c, k) for c, k in zip(cols, kinds)], names=["tkey", "first_doc", "n_words", "n_removed", "kept", "whole"])

    return run


def unspaced(text: bytes) -> list[bytes]:
    """The words of a text."""
    return text.split()


def _results(docs: DataFrame, with_text: bool, heavy: int) -> DataFrame:
    """doc_id, n_words, n_removed and kept: the words that stay, or their digest."""
    keyed = ut.keyed(docs)
    groups = ut.group_count(docs)
    texts = ut.grouped_texts(keyed, groups)
    anchors = texts.groupBy("p").applyInArrow(_anchors(groups), "b int, p int, hashes binary, held binary")
    told = "p int, kind int, b int, payload binary"
    repeated = anchors.groupBy("b").applyInArrow(_repeated(heavy), told)
    segments = texts.groupBy("p").cogroup(repeated.groupBy("p")).applyInArrow(_segments(groups), "b int, p int, docs binary, counts binary, words binary")
    minima = segments.groupBy("b").applyInArrow(_subtrees, told)
    results = texts.groupBy("p").cogroup(repeated.union(minima).groupBy("p")).applyInArrow(_removal(groups, with_text), "tkey binary, first_doc long, n_words long, n_removed long, kept string, whole string")
    r = results.withColumnRenamed("tkey", "_key")
    joined = keyed.select("doc_id", "tkey").join(r, F.col("tkey") == F.col("_key"))
    copy = (F.col("doc_id") != F.col("first_doc")) & (F.col("n_words") >= DEPTH)
    nothing = "" if with_text else hashlib.sha256(b"").hexdigest()
    return joined.select(
        "doc_id",
        "n_words",
        F.when(F.col("doc_id").isNull(), F.lit(0)).when(copy, F.col("n_words")).otherwise(F.col("n_removed")).cast("long").alias("n_removed"),
        F.when(F.col("doc_id").isNull(), F.col("whole")).when(copy, F.lit(nothing)).otherwise(F.col("kept")).alias("kept"),
    )


def remove_repeats(docs: DataFrame, heavy: int = HEAVY) -> DataFrame:
    """doc_id, n_words, n_removed and kept_sha256, one row per document."""
    return _results(docs, False, heavy).withColumnRenamed("kept", "kept_sha256")


def deduplicated(docs: DataFrame, heavy: int = HEAVY) -> DataFrame:
    """doc_id, n_words, n_removed and text, the words that stay joined by one space, one row per document."""
    return _results(docs, True, heavy).withColumnRenamed("kept", "text")


def sql(documents: str = "documents") -> str:
    """The same in SQL, over a table of documents."""
    return rf"""
WITH w AS (SELECT row_number() OVER () AS rid, doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS ws FROM {documents}),
p AS (SELECT rid, doc_id, len(ws) AS n, unnest(range(1, len(ws) + 1)) AS i, unnest(ws) AS word FROM w),
g AS (SELECT rid, doc_id, i, n, string_agg(word, ' ') OVER (PARTITION BY rid ORDER BY i ROWS BETWEEN CURRENT ROW AND {DEPTH - 1} FOLLOWING) AS k FROM p),
f AS (SELECT rid, i, doc_id, min(doc_id) OVER (PARTITION BY k) AS m FROM g WHERE i <= n - {DEPTH - 1}),
c AS (SELECT p.rid, p.i, p.word, max(CASE WHEN f.m < f.doc_id THEN 1 ELSE 0 END) OVER (PARTITION BY p.rid ORDER BY p.i ROWS BETWEEN {DEPTH - 1} PRECEDING AND CURRENT ROW) AS gone FROM p LEFT JOIN f ON p.rid = f.rid AND p.i = f.i),
r AS (SELECT rid, count(*) FILTER (WHERE gone = 1) AS n_removed, string_agg(word, ' ' ORDER BY i) FILTER (WHERE gone = 0) AS kept FROM c GROUP BY rid)
SELECT w.doc_id, CAST(len(w.ws) AS BIGINT) AS n_words, CAST(coalesce(r.n_removed, 0) AS BIGINT) AS n_removed, sha256(coalesce(r.kept, '')) AS kept_sha256
FROM w LEFT JOIN r ON w.rid = r.rid
"""

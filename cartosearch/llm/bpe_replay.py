"""Byte-level BPE encoding and decoding by corpus-level merge replay.

A block of text is a small corpus: its distinct pieces, of any length, are laid end to end as byte tokens, and an
inverted index lists the places of every adjacent token pair under the rank of its merge. The index is worked off in
rank order, a band of ranks at a time; only the two neighbours of each applied merge are looked up and entered again.
Pieces do not touch each other, so one step applies to every piece that has entries in the band all places of its least
rank. Encoded pieces stay in a bounded table of the worker.

Null or empty text: no tokens, digests of the empty string. Rows are independent: ties, repeated rows and an
empty table need no rule; whole texts are encoded however long.
"""

from __future__ import annotations

import base64
import hashlib

import numpy as np
import regex
from pyspark.sql import DataFrame

from . import textblocks as tb

#: Pieces that a worker keeps encoded, twice; what falls out is encoded again when it returns, which costs time, not results.
KEPT_PIECES = 120_000

#: Bands of ranks that the index of a block is kept in.
BANDS = 16
NO_MERGE = 1 << 30
WALL, MERGED = -1, -2


def read_ranks(data: bytes) -> dict[bytes, int]:
    return {base64.b64decode(a): int(b) for a, b in (line.split() for line in data.splitlines() if line)}


class MergeReplay:
    """Encoder over one rank table; see the module's docstring."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        self.ranks, self.pattern = ranks, regex.compile(pattern)
        self.bytes_of = {i: b for b, i in ranks.items()}
        self.byte_ids = [ranks[bytes([b])] for b in range(256)]
        #: Index entries made after the first ones, two at most for each merge.
        self.updates = 0
        self.byte_pairs = np.array([ranks.get(bytes([a, b]), -1) for a in range(256) for b in range(256)], np.int32)
        self.id_of_byte = np.array(self.byte_ids, np.int64)
        # Every pair of tokens that merges, as one sorted number, with the rank of the merge.
        pairs = sorted((ranks[t[:i]] << 20 | ranks[t[i:]], r) for t, r in ranks.items() for i in range(1, len(t)) if t[:i] in ranks and t[i:] in ranks)
        self.pair_keys, self.pair_ranks = (np.array(x, np.int64) for x in zip(*pairs))
        self.shown = {i: str(i) for i in ranks.values()}
        # Two generations: what is used again moves to the younger one, the older one is dropped when that is full.
        self.kept: dict[str, tuple[str, bytes]] = {}
        self.older: dict[str, tuple[str, bytes]] = {}

    def encode_pieces(self, pieces: list[bytes]) -> list[list[int]]:
        """The ids of each piece; a piece that is a token itself is that token."""
        ranks = self.ranks
        out: list[list[int] | None] = [[ranks[p]] if p in ranks else None for p in pieces]
        part = [i for i, p in enumerate(pieces) if out[i] is None]
        if part:
            for i, ids in zip(part, self._replay([pieces[i] for i in part])):
                out[i] = ids
        return out

    def _rank_of(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Rank of the merge of two neighbours, which is also the id that it makes; a wall (below 0) merges with nothing."""
        key = left << 20 | right
        at = np.minimum(np.searchsorted(self.pair_keys, key), len(self.pair_keys) - 1)
        return np.where((self.pair_keys[at] == key) & (left >= 0) & (right >= 0), self.pair_ranks[at], NO_MERGE)

    def _replay(self, pieces: list[bytes]) -> list[list[int]]:
        # Pieces end to end, each followed by a wall; tokens are linked to their neighbours by place.
        sizes = np.array([len(p) + 1 for p in pieces])
        ends = np.cumsum(sizes)
        raw = np.frombuffer(b"\0".join(pieces) + b"\0", np.uint8)
        token, piece = self.id_of_byte[raw], np.repeat(np.arange(len(pieces)), sizes)
        token[ends - 1] = WALL
        after, before = np.arange(1, len(raw) + 1), np.arange(-1, len(raw) - 1)
        rank_at = np.full(len(raw), NO_MERGE, np.int64)
        pairs = self.byte_pairs[raw[:-1].astype(np.int32) << 8 | raw[1:]].astype(np.int64)
        rank_at[:-1] = np.where((pairs >= 0) & (token[:-1] >= 0) & (token[1:] >= 0), pairs, NO_MERGE)
        # The index: places under their rank, as numbers rank << 32 | place, in bands of ranks that are worked off in order.
        places = np.flatnonzero(rank_at < NO_MERGE)
        entries = np.sort(rank_at[places] << 32 | places)
        edges = np.unique(entries[:: max(1, len(entries) // BANDS)] >> 32)[1:]
        due: list[list[np.ndarray]] = [[x] for x in np.split(entries, np.searchsorted(entries, edges << 32))]
        least = np.empty(len(pieces), np.int64)
        for band in range(len(due)):
            top = edges[band] if band < len(edges) else NO_MERGE
            open_, due[band] = np.sort(np.concatenate(due[band])), []
            while len(open_):
                rank, at = open_ >> 32, open_ & 0xFFFFFFFF
                valid = rank_at[at] == rank
                valid[1:] &= open_[1:] != open_[:-1]
                open_, rank, at = open_[valid], rank[valid], at[valid]
                if not len(open_):
                    break
                own = piece[at]
                least[own[::-1]] = rank[::-1]  # the first entry of each piece is written last
                touched = self._apply(np.sort(at[rank == least[own]]), token, piece, after, before, rank_at)
                new = touched[rank_at[touched] < NO_MERGE]
                self.updates += len(new)
                new = rank_at[new] << 32 | new
                now = new >> 32 < top
                open_ = np.sort(np.concatenate((open_, new[now])), kind="stable")
                if not now.all():
                    later = new[~now]
                    where = np.searchsorted(edges, later >> 32, side="right")
                    order = np.argsort(where, kind="stable")
                    cuts = np.flatnonzero(np.diff(where[order])) + 1
                    for a, b in zip([0, *cuts.tolist()], [*cuts.tolist(), len(order)]):
                        due[where[order[a]]].append(later[order[a:b]])
        left = token >= 0
        ids, stops = token[left].tolist(), np.cumsum(np.bincount(piece[left], minlength=len(pieces))).tolist()
        return [ids[a:b] for a, b in zip([0, *stops], stops)]

    def _apply(self, at: np.ndarray, token, piece, after, before, rank_at) -> np.ndarray:
        """Merge at the places given, all of the least rank of their pieces, from left to right; the places whose pair changed.

        Of places that overlap every other one merges. A piece stops after a merge that makes an earlier one possible;
        its other places stay in the index.
        """
        if len(at) > 1:
            i = np.arange(len(at))
            begin = np.concatenate(([True], after[at[:-1]] != at[1:]))
            at = at[(i - np.maximum.accumulate(np.where(begin, i, 0))) & 1 == 0]
        rank, own = rank_at[at], piece[at]
        same = own[1:] == own[:-1]
        if same.any():
            follows = np.concatenate(([False], after[after[at[:-1]]] == at[1:]))
            before_it = np.where(follows, np.concatenate(([0], rank[:-1])), np.where(before[at] >= 0, token[before[at]], WALL))
            lower = np.minimum(self._rank_of(before_it, rank), self._rank_of(rank, token[after[after[at]]])) < rank
            seen = np.cumsum(lower) - lower
            first = np.concatenate(([True], ~same))
            at = at[seen == np.repeat(seen[first], np.diff(np.append(np.flatnonzero(first), len(at))))]
            rank = rank_at[at]
        gone = after[at]
        token[at], token[gone], rank_at[gone] = rank, MERGED, NO_MERGE
        after[at] = after[gone]
        before[after[at]] = at
        left = before[at]
        new = left >= 0
        new[1:] &= left[1:] != at[:-1]  # it has merged itself
        touched = np.concatenate((at, left[new]))
        rank_at[touched] = self._rank_of(token[touched], token[after[touched]])
        return touched

    def pieces(self, texts: list[str]) -> list[list[str]]:
        """The pieces of each text, all of them encoded and kept."""
        split = [self.pattern.findall(t) for t in texts]
        seen = set().union(*split)
        if len(self.kept) > KEPT_PIECES:
            self.kept, self.older = {}, self.kept
        kept, older, new = self.kept, self.older, []
        for piece in seen.difference(kept):
            if piece in older:
                kept[piece] = older[piece]
            else:
                new.append(piece)
        for i in range(0, len(new), 20_000):
            block = new[i : i + 20_000]
            for piece, ids in zip(block, self.encode_pieces([p.encode() for p in block])):
                kept[piece] = ",".join(map(self.shown.__getitem__, ids)), b"".join(map(self.bytes_of.__getitem__, ids))
        return split

    def encode(self, text: str) -> list[int]:
        joined = ",".join(self.kept[p][0] for p in self.pieces([text])[0])
        return [int(x) for x in joined.split(",")] if joined else []

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(map(self.bytes_of.__getitem__, ids))


def rank_file(path: str | None = None) -> bytes:
    """The rank file's content, read once on the driver; it is of fixed size and goes along with the tasks."""
    if path is None:
        import public_tokenizers

        path = public_tokenizers.path("byte_bpe_multi_50k.tiktoken")
    with open(path, "rb") as f:
        return f.read()


def split_pattern() -> str:
    import public_tokenizers

    return public_tokenizers.PATTERN


_worker: dict[bytes, MergeReplay] = {}


def worker_replay(shared) -> MergeReplay:
    data, pattern = shared.value
    key = hashlib.sha256(data + pattern.encode()).digest()
    if key not in _worker:
        _worker[key] = MergeReplay(read_ranks(data), pattern)
    return _worker[key]


def digests(docs: DataFrame, path: str | None = None) -> DataFrame:
    """One row per document: number of tokens, digest of the ids, digest of the bytes decoded from them."""
    shared = docs.sparkSession.sparkContext.broadcast((rank_file(path), split_pattern()))

    def make(part):
        replay, rows = worker_replay(shared), []
        for pieces in replay.pieces(tb.texts(part)):
            ids, raw = zip(*map(replay.kept.__getitem__, pieces)) if pieces else ((), ())
            joined = ",".join(ids).encode()
            rows.append((joined.count(b",") + bool(joined), hashlib.sha256(joined).hexdigest(), hashlib.sha256(b"".join(raw)).hexdigest()))
        n, a, b = map(list, zip(*rows))
        return {"doc_id": tb.column(part, "doc_id"), "n_tokens": n, "ids_sha256": a, "decoded_sha256": b}

    return tb.per_slice(docs, make, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def encode(docs: DataFrame, path: str | None = None) -> DataFrame:
    """doc_id and the token ids of its text."""
    shared = docs.sparkSession.sparkContext.broadcast((rank_file(path), split_pattern()))

    def make(part):
        replay = worker_replay(shared)
        return {"doc_id": tb.column(part, "doc_id"), "ids": [[int(x) for p in pieces for x in replay.kept[p][0].split(",")] for pieces in replay.pieces(tb.texts(part))]}

    return tb.per_slice(docs, make, "doc_id long, ids array<int>")


def decode(tokens: DataFrame, path: str | None = None) -> DataFrame:
    """doc_id and the text of its ids; null ids give an empty text, bytes that are not UTF-8 a replacement mark."""
    import pyarrow as pa

    shared = tokens.sparkSession.sparkContext.broadcast((rank_file(path), split_pattern()))

    def run(batches):
        for b in batches:
            replay = worker_replay(shared)
            text = [replay.decode(ids or []).decode("utf-8", "replace") for ids in tb.column(b, "ids").to_pylist()]
            yield pa.RecordBatch.from_arrays([tb.column(b, "doc_id"), pa.array(text, pa.string())], names=["doc_id", "text"])

    return tokens.select("doc_id", "ids").mapInArrow(run, "doc_id long, text string")

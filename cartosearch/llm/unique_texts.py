"""Distinct texts in groups of bounded size, each with the smallest doc_id that carries it.

Copies of one text meet by its SHA-256. Every input partition sends a text once however many rows repeat it, so a
group of copies that holds a third of all rows adds one row per partition. Texts travel compressed.
"""

from __future__ import annotations

import functools

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textblocks as tb

SCHEMA = "p int, tkeys binary, ids binary, known binary, sizes binary, z binary"
#: Bytes of text that a task gathers before it sends packs.
HELD_BYTES = 24 << 20


@functools.cache
def _coders():
    import zstandard

    return zstandard.ZstdCompressor(level=1), zstandard.ZstdDecompressor(), zstandard.ZstdCompressor(level=6)


def squeeze(data: bytes) -> bytes:
    return _coders()[0].compress(data)


def unsqueeze(data: bytes) -> bytes:
    return _coders()[1].decompress(data)


def keyed(docs: DataFrame) -> DataFrame:
    """doc_id, text and the text's key; a null text is an empty one."""
    text = F.coalesce(F.col("text"), F.lit(""))
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), text.alias("text"), F.unhex(F.sha2(text, 256)).alias("tkey"))


def group_count(docs: DataFrame, group_bytes: int = 8 << 20, soft_most: int = 2000) -> int:
    """Groups of about group_bytes of text; beyond soft_most of them groups grow up to 64 times as large first."""
    total = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    size = min(max(group_bytes, total // soft_most), 64 * group_bytes)
    return max(1, -(-total // size))


def _distinct(batches):
    """(slice, positions of texts that this input partition has not met yet, smaller doc_ids) for every slice; the last item
    has the doc_ids smaller than the one a text was sent with."""
    told: dict[bytes, int | None] = {}
    smaller: dict[bytes, int] = {}
    for batch in batches:
        for part in tb.text_slices(batch):
            new = []
            for i, (key, doc) in enumerate(zip(tb.column(part, "tkey").to_pylist(), tb.column(part, "doc_id").to_pylist())):
                if key not in told:
                    told[key] = doc
                    new.append((i, key, doc))
                elif doc is not None and (told[key] is None or doc < told[key]):
                    smaller[key] = min(doc, smaller.get(key, doc))
            if new:
                yield part, new, {}
    if smaller:
        yield None, [], smaller


def unique_texts(keyed_docs: DataFrame) -> DataFrame:
    """(tkey, z) of each text, once per input partition."""

    def run(batches):
        for part, new, _ in _distinct(batches):
            if part is not None:
                text = tb.column(part, "text").cast(pa.binary())
                yield pa.RecordBatch.from_arrays([pa.array([k for _, k, _ in new], pa.binary()), pa.array([squeeze(text[i].as_py()) for i, _, _ in new], pa.binary())], names=["tkey", "z"])

    return keyed_docs.select("doc_id", "text", "tkey").mapInArrow(run, "tkey binary, z binary")


def grouped_texts(keyed_docs: DataFrame, groups: int) -> DataFrame:
    """Rows of SCHEMA: packs of texts of one group, compressed together, each with its key and a doc_id (known: whether there
    is one). A size of -1 has no text: only a smaller doc_id of a text sent before. Group puts packs together."""
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import _parse_datatype_string

    arrow = to_arrow_schema(_parse_datatype_string(SCHEMA))

    def run(batches):
        held: dict[int, list[tuple[bytes, int | None, bytes | None]]] = {}
        size = 0

        def packs():
            rows = []
            for p, texts in held.items():
                keys, ids, raw = zip(*texts)
                known = [d is not None for d in ids]
                rows.append((p, b"".join(keys), np.array([d or 0 for d in ids], np.int64).tobytes(), bytes(known), np.array([-1 if t is None else len(t) for t in raw], np.int64).tobytes(), _coders()[2].compress(b"".join([t for t in raw if t is not None]))))
            held.clear()
            return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows), arrow)], schema=arrow)

        group = lambda key: int.from_bytes(key[:6], "big") % groups
        for part, new, smaller in _distinct(batches):
            text = tb.column(part, "text").cast(pa.binary()) if part is not None else None
            for i, key, doc in new:
                raw = text[i].as_py()
                held.setdefault(group(key), []).append((key, doc, raw))
                size += len(raw) + 100
            for key, doc in smaller.items():
                held.setdefault(group(key), []).append((key, doc, None))
            if size > HELD_BYTES:
                yield packs()
                size = 0
        if held:
            yield packs()

    return keyed_docs.select("doc_id", "text", "tkey").mapInArrow(run, SCHEMA)


class Group:
    """The distinct texts of a group: key and smallest doc_id of each, and the texts pack by pack."""

    def __init__(self, table: pa.Table):
        self.keys: list[bytes] = []
        self.ids: list[int | None] = []
        self._packs: list[tuple[bytes, list[int], list[int]]] = []
        number: dict[bytes, int] = {}
        least: dict[bytes, int] = {}
        rows = [table.column(c).to_pylist() for c in ("tkeys", "ids", "known", "sizes", "z")]
        for tkeys, ids, known, sizes, z in sorted(zip(*rows)):  # the same order in every task
            own, sizes = [], np.frombuffer(sizes, np.int64).tolist()
            for i, (doc, there, size) in enumerate(zip(np.frombuffer(ids, np.int64).tolist(), known, sizes)):
                key = tkeys[32 * i : 32 * i + 32]
                if there:
                    least[key] = min(doc, least.get(key, doc))
                if size >= 0:
                    own.append(-1 if key in number else len(self.keys))  # -1: a text that another pack has sent
                    if own[-1] >= 0:
                        number[key] = own[-1]
                        self.keys.append(key)
            self._packs.append((z, own, [x for x in sizes if x >= 0]))
        self.ids = [least.get(k) for k in self.keys]

    def slices(self, keep=None, limit: int = tb.SLICE_BYTES):
        """(numbers, raw texts) of about `limit` bytes together; keep(number): whether a text is wanted."""
        numbers, raw, held = [], [], 0
        for z, own, sizes in self._packs:
            data, at = unsqueeze(z), 0
            for k, size in zip(own, sizes):
                if k >= 0 and (keep is None or keep(k)):
                    if raw and held + size > limit:
                        yield numbers, raw
                        numbers, raw, held = [], [], 0
                    numbers.append(k)
                    raw.append(data[at : at + size])
                    held += size
                at += size
        if raw:
            yield numbers, raw


def group_slices(z: list[bytes], limit: int = tb.SLICE_BYTES):
    """(first index, raw texts) of consecutive texts of about `limit` bytes together."""
    start, raw, size = 0, [], 0
    for i, data in enumerate(z):
        text = unsqueeze(data)
        if raw and size + len(text) > limit:
            yield start, raw
            start, raw, size = i, [], 0
        raw.append(text)
        size += len(text)
    if raw:
        yield start, raw


def flat_of(raw: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    offsets = np.zeros(len(raw) + 1, np.int64)
    np.cumsum([len(x) for x in raw], out=offsets[1:])
    return np.frombuffer(b"".join(raw), np.uint8), offsets

"""Media columns with content-defined payload chunking.

A text's UTF-8 bytes, padded with zero bytes to a positive multiple of 64, are the samples of an 8-bit mono
WAVE file. A rolling gear hash over the last 32 bytes cuts the file where its low bits vanish, so equal
passages give equal chunks wherever they stand. A join on chunk digests gives each chunk one owner among the groups of
files that hold it; the owner writes it to the store, once, and every group writes the ordered chunk lists of its files.
Both are read back, owners send chunks to the groups that list them, files are rebuilt from their lists, checked against
their digests, and only then read for features.

Null or empty text: 0 bytes, a payload of 64 zero bytes. Equal texts are one file. Null or repeated doc_ids are
carried through. Files of any length are cut and rebuilt whole; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
import struct
import uuid
import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..checkpoints import checkpoint_dir
from . import unique_texts as ut

UNIT = 64
RATE = 8000
LEAST, MASK, MOST = 256, np.uint32(0x3FF), 8192
_GEAR = np.random.Generator(np.random.PCG64(77)).integers(0, 2**32, 256, dtype=np.uint32)


def wave(payload: bytes) -> bytes:
    n = len(payload)
    return b"RIFF" + struct.pack("<I", 36 + n) + b"WAVEfmt " + struct.pack("<IHHIIHH", 16, 1, 1, RATE, RATE, 1, 8) + b"data" + struct.pack("<I", n) + payload


def samples(media: bytes) -> bytes:
    """The samples of an 8-bit mono file made by wave()."""
    if media[:4] != b"RIFF" or media[8:12] != b"WAVE" or struct.unpack("<HH", media[20:24]) != (1, 1) or media[34:36] != b"\x08\0":
        raise ValueError("not an 8-bit mono WAVE file")
    return media[44 : 44 + struct.unpack("<I", media[40:44])[0]]


def padded(text: bytes) -> bytes:
    return text + bytes(max(UNIT, -(-len(text) // UNIT) * UNIT) - len(text))


def cut(files: list[bytes]) -> list[list[int]]:
    """Ends of the chunks of each file."""
    data, offsets = ut.flat_of(files)
    rolling = _GEAR[data]
    for step in (1, 2, 4, 8, 16):  # after each step the hash covers twice as many bytes
        rolling[step:] += rolling[:-step] << np.uint32(step)
    hits = np.flatnonzero((rolling & MASK) == 0) + 1
    where = np.searchsorted(hits, offsets)
    out = []
    for f in range(len(files)):
        begin, end = int(offsets[f]), int(offsets[f + 1])
        ends, at, own = [], begin, hits[where[f] : where[f + 1]].tolist()
        k = 0
        while end - at > LEAST:
            while k < len(own) and own[k] < at + LEAST:
                k += 1
            stop = min(own[k] if k < len(own) else end, at + MOST, end)
            ends.append(stop - begin)
            at = stop
        if at < end:
            ends.append(end - begin)
        out.append(ends)
    return out


def digest(chunk: bytes) -> bytes:
    return hashlib.blake2b(chunk, digest_size=16).digest()


def chunked(files: list[bytes]) -> list[list[tuple[bytes, bytes]]]:
    """(digest, bytes) of the chunks of each file, in order."""
    out = []
    for f, ends in zip(files, cut(files)):
        out.append([(digest(c), c) for a, b in zip([0, *ends], ends) for c in (f[a:b],)])
    return out


def features(payload: bytes) -> str:
    """Peak, mean, deviation and energy of the samples around the middle 128, and how often they cross it."""
    x = np.frombuffer(payload, np.uint8).astype(np.int64) - 128
    total, square = int(x.sum()), int((x * x).sum())
    crossings = int(((x[1:] >= 0) != (x[:-1] >= 0)).sum())
    return f"peak={int(np.abs(x).max())};sum={total};energy={square};crossings={crossings};range={int(x.max() - x.min())}"


STORED = "p int, tkey binary, n_bytes long, media_sha256 binary, digests array<binary>, digest binary, chunk binary, owner int"
READ = "tkey binary, n_bytes long, payload_bytes long, payload_sha256 binary, tail_crc32 long, media_bytes long, media_sha256 binary, feature string, n_chunks long"
#: Groups that one shipped copy of a chunk serves.
RELAY = 256
#: Files of a store, however many groups there are.
MOST_BUCKETS = 20_000


@dataclass(frozen=True)
class Store:
    """What was written, rows of STORED in groups p: chunks, each digest once, manifests, and for each chunk that a group
    lists but does not keep the group that owns it."""

    rows: DataFrame

    @property
    def chunks(self) -> DataFrame:
        return self.rows.filter("chunk IS NOT NULL").select("p", "digest", "chunk")

    @property
    def manifests(self) -> DataFrame:
        return self.rows.filter("tkey IS NOT NULL").select("p", "tkey", "n_bytes", "media_sha256", "digests")

    @property
    def wanted(self) -> DataFrame:
        return self.rows.filter("owner IS NOT NULL").select("p", "digest", "owner")


def _files(table: pa.Table):
    """(keys, raw texts, files) of a group in slices."""
    group = ut.Group(table)
    for numbers, raw in group.slices():
        yield [group.keys[k] for k in numbers], raw, [wave(padded(t)) for t in raw]


def _digests(table: pa.Table) -> pa.Table:
    found: set[bytes] = set()
    for _, _, files in _files(table):
        found.update(d for chunks in chunked(files) for d, _ in chunks)
    return pa.table({"digest": pa.array(sorted(found), pa.binary()), "p": pa.array([table.column("p")[0].as_py()] * len(found), pa.int32())})


def _table(rows: list[tuple], names: list[str], kinds: tuple) -> pa.Table:
    cols = list(zip(*rows)) or [()] * len(names)
    return pa.table([pa.array(c, k) for c, k in zip(cols, kinds)], names=names)


def _keep(texts: pa.Table, foreign: pa.Table) -> pa.Table:
    """The manifests of a group, and its chunks that no other group owns."""
    rows, seen = [], set(foreign.column("digest").to_pylist())
    if texts.num_rows:
        p = texts.column("p")[0].as_py()
        rows += [(p, None, None, None, None, d, None, owner) for d, owner in zip(foreign.column("digest").to_pylist(), foreign.column("owner").to_pylist())]
        for keys, raw, files in _files(texts):
            for key, text, media, chunks in zip(keys, raw, files, chunked(files)):
                rows.append((p, key, len(text), hashlib.sha256(media).digest(), [d for d, _ in chunks], None, None, None))
                for d, c in chunks:
                    if d not in seen:
                        seen.add(d)
                        rows.append((p, None, None, None, None, d, c, None))
    binary = pa.binary()
    return _table(rows, [x.split()[0] for x in STORED.split(", ")], (pa.int32(), binary, pa.int64(), binary, pa.list_(binary), binary, binary, pa.int32()))


def write_store(docs: DataFrame) -> Store:
    """Cut the file of every distinct text, write each chunk once and each file's ordered list of chunks.

    Groups of texts meet by digests alone: a join on them gives a chunk that several groups hold one owner. The store is
    a Parquet table in the checkpoint folder, bucketed by group, so that later stages read a group without moving it.
    """
    spark = docs.sparkSession
    groups = ut.group_count(docs)
    texts = ut.grouped_texts(ut.keyed(docs).withColumn("doc_id", F.lit(None).cast("long")), groups)
    listed = texts.groupBy("p").applyInArrow(_digests, "digest binary, p int")
    owner = F.min(F.struct(F.xxhash64("digest", "p").alias("h"), F.col("p"))).getField("p")
    owners = listed.groupBy("digest").agg(owner.alias("owner"), F.count(F.lit(1)).alias("n")).filter("n > 1").select(F.col("digest").alias("_digest"), "owner")
    wanted = listed.join(owners, F.col("digest") == F.col("_digest")).filter("p != owner").select("digest", "p", "owner")
    rows = texts.groupBy("p").cogroup(wanted.groupBy("p")).applyInArrow(_keep, STORED)
    name = f"media_store_{uuid.uuid4().hex}"
    # With fewer buckets than shuffle partitions the planner would move the store again.
    buckets = max(min(groups, MOST_BUCKETS), int(spark.conf.get("spark.sql.shuffle.partitions")))
    rows.write.format("parquet").option("compression", "zstd").option("parquet.compression.codec.zstd.level", "6").option("path", f"{checkpoint_dir(spark)}/{name}").bucketBy(buckets, "p").saveAsTable(name)
    return Store(spark.table(name))


def _ship(stored: pa.Table, asked: pa.Table) -> pa.Table:
    """One row for each relay of each chunk that other groups want."""
    rows = []
    if asked.num_rows:
        chunks = dict(zip(stored.column("digest").to_pylist(), stored.column("chunk").to_pylist()))
        for d, relay, groups in zip(*(asked.column(c).to_pylist() for c in ("digest", "relay", "groups"))):
            if d not in chunks:
                raise ValueError(f"the store has no chunk {d.hex()}")
            rows.append((d, relay, groups, chunks[d]))
    return _table(rows, ["digest", "relay", "groups", "chunk"], (pa.binary(), pa.int32(), pa.list_(pa.int32()), pa.binary()))


def _media(stored: pa.Table, received: pa.Table):
    """(key, bytes of the text, file, number of chunks) of each file of a group, put together and verified."""
    chunks = dict(zip(received.column("digest").to_pylist(), received.column("chunk").to_pylist()))
    manifests = []
    for key, n, whole, listed, d, c in zip(*(stored.column(x).to_pylist() for x in ("tkey", "n_bytes", "media_sha256", "digests", "digest", "chunk"))):
        if key is not None:
            manifests.append((key, n, whole, listed))
        elif c is not None:
            chunks[d] = c
    for key, n, whole, listed in manifests:
        try:
            media = b"".join([chunks[d] for d in listed])
        except KeyError as missing:
            raise ValueError(f"the store has no chunk {missing.args[0].hex()} of file {key.hex()}") from None
        if hashlib.sha256(media).digest() != whole:
            raise ValueError(f"chunks do not give back file {key.hex()}")
        yield key, n, media, len(listed)


def _whole(stored: pa.Table, received: pa.Table) -> pa.Table:
    return _table(list(_media(stored, received)), ["tkey", "n_bytes", "media", "n_chunks"], (pa.binary(), pa.int64(), pa.binary(), pa.int64()))


def _read(stored: pa.Table, received: pa.Table) -> pa.Table:
    rows = []
    for key, n, media, chunks in _media(stored, received):
        payload = samples(media)
        rows.append((key, n, len(payload), hashlib.sha256(payload).digest(), zlib.crc32(payload[-UNIT:]), len(media), hashlib.sha256(media).digest(), features(payload), chunks))
    return _table(rows, [x.split()[0] for x in READ.split(", ")], (pa.binary(), pa.int64(), pa.int64(), pa.binary(), pa.int64(), pa.int64(), pa.binary(), pa.string(), pa.int64()))


def _from_store(store: Store, make, schema: str) -> DataFrame:
    """make(stored rows of a group, chunks that other groups sent it) for every group.

    A chunk that many groups want goes out once for each RELAY of them and is multiplied behind the next exchange.
    """
    relay = F.floor(F.col("p") / RELAY).cast("int").alias("relay")
    asked = store.wanted.groupBy(F.col("owner").alias("p"), "digest", relay).agg(F.collect_set("p").alias("groups"))
    sent = store.chunks.groupBy("p").cogroup(asked.groupBy("p")).applyInArrow(_ship, "digest binary, relay int, groups array<int>, chunk binary")
    received = sent.repartition("digest", "relay").select(F.explode("groups").alias("p"), "digest", "chunk")
    return store.rows.groupBy("p").cogroup(received.groupBy("p")).applyInArrow(make, schema)


def reconstruct(store: Store) -> DataFrame:
    """tkey, n_bytes, media and n_chunks of every file; a missing chunk or a digest that does not fit stops the job."""
    return _from_store(store, _whole, "tkey binary, n_bytes long, media binary, n_chunks long")


def media_features(docs: DataFrame) -> DataFrame:
    """One row per document: sizes and digests of payload and file as read back from the store, and the features."""
    read = _from_store(write_store(docs), _read, READ)
    joined = ut.keyed(docs).select("doc_id", F.col("tkey").alias("_key")).join(read, F.col("_key") == F.col("tkey")).drop("_key", "tkey")
    return joined.withColumns({c: F.lower(F.hex(c)) for c in ("payload_sha256", "media_sha256")})

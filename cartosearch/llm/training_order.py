"""Token-ID output in training order.

Documents become token ids, ids become records of a fixed number of tokens (the last one of a document padded),
and a keyed Feistel permutation with cycle-walking gives every record one slot of 0..n-1. Slots are dense, so
the range of slots of each partition is plain arithmetic: partitions hold consecutive shards, shards consecutive
slots, and a record's place in its shard's bytes is slot % shard size times the stride. A reader resumes at any
slot by skipping whole shards and a multiple of the stride.

A record: doc_id (8 bytes, little-endian; the least number for null), number of the record in its document (4), tokens used
(4), then the ids as 16-bit numbers, padded with PAD. Null or empty text: one record without tokens. Repeated
rows are separate records. An empty table gives no shards.
Records are numbered by document, not by place in a file, so every layout of the input gives the same order.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..checkpoints import checkpointed
from . import textblocks as tb
from .bpe_replay import rank_file, read_ranks, split_pattern
from .unique_texts import squeeze, unsqueeze

TOKENS = 256
PAD = 50256
HEAD = 16
STRIDE = HEAD + 2 * TOKENS
SHARD = 4096
#: Documents of a cell when records are numbered.
CELL_ROWS = 8_192
NO_ID = -(1 << 63)


class Feistel:
    """A keyed permutation of 0..n-1 over NumPy arrays, and its inverse."""

    def __init__(self, n: int, key: int, rounds: int = 6):
        self.n = n
        self.half = np.uint64(max(1, -(-max(n - 1, 1).bit_length() // 2)))
        self.mask = np.uint64((1 << int(self.half)) - 1)
        self.keys = [np.uint64(int.from_bytes(hashlib.blake2b(f"{key}:{r}".encode(), digest_size=8).digest(), "big")) for r in range(rounds)]

    def _once(self, x: np.ndarray, back: bool) -> np.ndarray:
        left, right = x >> self.half, x & self.mask
        for k in reversed(self.keys) if back else self.keys:
            if back:
                left, right = right ^ (tb.mix(left + k) & self.mask), left
            else:
                left, right = right, left ^ (tb.mix(right + k) & self.mask)
        return left << self.half | right

    def _walk(self, x: np.ndarray, back: bool) -> np.ndarray:
        out = self._once(np.asarray(x, np.uint64), back)
        while len(outside := np.flatnonzero(out >= np.uint64(self.n))):
            out[outside] = self._once(out[outside], back)
        return out.astype(np.int64)

    def forward(self, x: np.ndarray) -> np.ndarray:
        return self._walk(x, False)

    def backward(self, x: np.ndarray) -> np.ndarray:
        return self._walk(x, True)


_encoders: dict[bytes, object] = {}


def _encoder(shared):
    import tiktoken

    data, pattern = shared.value
    key = hashlib.sha256(data).digest()
    if key not in _encoders:
        _encoders[key] = tiktoken.Encoding("ranks", pat_str=pattern, mergeable_ranks=read_ranks(data), special_tokens={})
    return _encoders[key]


def token_rows(docs: DataFrame, path: str | None = None) -> DataFrame:
    """(doc_id, records, z): how many records the document fills, and its ids, compressed."""
    shared = docs.sparkSession.sparkContext.broadcast((rank_file(path), split_pattern()))

    def make(part):
        encoder = _encoder(shared)
        ids = [np.array(encoder.encode_ordinary(t), np.uint16) for t in tb.texts(part)]
        return {"doc_id": tb.column(part, "doc_id"), "records": [max(1, -(-len(x) // TOKENS)) for x in ids], "z": [squeeze(x.tobytes()) for x in ids]}

    return tb.per_slice(docs, make, "doc_id long, records long, z binary")


def record(doc_id: int | None, number: int, ids: np.ndarray) -> bytes:
    body = np.full(TOKENS, PAD, np.uint16)
    body[: len(ids)] = ids
    return (NO_ID if doc_id is None else doc_id).to_bytes(8, "little", signed=True) + number.to_bytes(4, "little") + len(ids).to_bytes(4, "little") + body.tobytes()


def numbered(docs: DataFrame, path: str | None = None) -> tuple[DataFrame, int, int]:
    """(doc_id, records, z, first) with the number of each document's first record, the number of all records, and of partitions
    of the token table.

    Documents are ordered by cell, doc_id and content, so numbers do not depend on how the input lies in files. Cells are
    few enough for one task to add up their counts and to be broadcast: one for CELL_ROWS documents.
    """
    tokens = checkpointed(token_rows(docs, path))
    n, total = tokens.agg(F.count(F.lit(1)), F.coalesce(F.sum("records"), F.lit(0))).first()
    celled = tokens.withColumn("hash", F.xxhash64("z")).withColumn("cell", F.pmod(F.xxhash64("doc_id", "hash"), F.lit(max(64, -(-n // CELL_ROWS)))))
    along = Window.orderBy("cell").rowsBetween(Window.unboundedPreceding, -1)
    starts = celled.groupBy("cell").agg(F.sum("records").alias("n")).select("cell", F.coalesce(F.sum("n").over(along), F.lit(0)).alias("start"))
    inside = Window.partitionBy("cell").orderBy("doc_id", "hash", "records").rowsBetween(Window.unboundedPreceding, -1)
    ahead = celled.withColumn("ahead", F.coalesce(F.sum("records").over(inside), F.lit(0)))
    return ahead.join(F.broadcast(starts), "cell").select("doc_id", "records", "z", (F.col("start") + F.col("ahead")).alias("first")), int(total), tokens.rdd.getNumPartitions()


def shards(docs: DataFrame, key: int = 20240607, path: str | None = None) -> DataFrame:
    """(shard, records, bytes) in slot order, one row per shard."""
    tokens, total, parts = numbered(docs, path)
    return shards_of(tokens, total, parts, key)


def shards_of(tokens: DataFrame, total: int, parts: int, key: int, begin: int = 0, end: int | None = None) -> DataFrame:
    """The shards begin..end of numbered documents: records of other shards leave before the exchange."""
    order = Feistel(max(total, 1), key)
    n_shards = -(-total // SHARD)
    end = n_shards if end is None else min(end, n_shards)
    parts = max(1, min(end - begin, parts))

    def number(batches):
        for b in batches:
            for start in range(0, b.num_rows, 500):
                part = b.slice(start, 500)
                rows, numbers = [], []
                for doc, n, z, first in zip(*(tb.column(part, c).to_pylist() for c in ("doc_id", "records", "z", "first"))):
                    ids = np.frombuffer(unsqueeze(z), np.uint16)
                    rows += [record(doc, k, ids[k * TOKENS : (k + 1) * TOKENS]) for k in range(n)]
                    numbers.append(np.arange(first, first + n))
                slot = order.forward(np.concatenate([*numbers, np.zeros(0, np.int64)]))
                shard = slot // SHARD
                here = np.flatnonzero((shard >= begin) & (shard < end))
                yield pa.RecordBatch.from_arrays([pa.array(((shard[here] - begin) * parts // max(1, end - begin)).astype(np.int32)), pa.array(slot[here]), pa.array([rows[i] for i in here], pa.binary())], names=["part", "slot", "record"])

    def gather(batches):
        held, shard = [], None
        for b in batches:
            for s, r in zip((tb.column(b, "slot").to_numpy() // SHARD).tolist(), tb.column(b, "record").to_pylist()):
                if s != shard and held:
                    yield _shard_row(shard, held)
                    held = []
                shard = s
                held.append(r)
        if held:
            yield _shard_row(shard, held)

    records = tokens.mapInArrow(number, "part int, slot long, record binary")
    ranged = records.repartitionById(parts, F.col("part")).sortWithinPartitions("slot")
    return ranged.select("slot", "record").mapInArrow(gather, "shard long, records long, bytes binary")


def _shard_row(shard: int, held: list[bytes]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([shard], pa.int64()), pa.array([len(held)], pa.int64()), pa.array([b"".join(held)], pa.binary())], names=["shard", "records", "bytes"])


def read_records(made: DataFrame, start: int = 0) -> DataFrame:
    """The records from slot `start` on: slot, shard, offset in the shard, doc_id, seq_no, n_tokens, sha256 of the record."""
    schema = "slot long, shard long, offset long, doc_id long, seq_no long, n_tokens long, record_sha256 string"

    def run(batches):
        for b in batches:
            for shard, data in zip(tb.column(b, "shard").to_pylist(), tb.column(b, "bytes").to_pylist()):
                rows = []
                for k in range(max(0, start - shard * SHARD), len(data) // STRIDE):
                    r = data[k * STRIDE : (k + 1) * STRIDE]
                    doc = int.from_bytes(r[:8], "little", signed=True)
                    rows.append((shard * SHARD + k, shard, k * STRIDE, None if doc == NO_ID else doc, int.from_bytes(r[8:12], "little"), int.from_bytes(r[12:16], "little"), hashlib.sha256(r).hexdigest()))
                if rows:
                    yield tb.as_batch(dict(zip([x.split()[0] for x in schema.split(", ")], map(list, zip(*rows)))), arrow)

    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import _parse_datatype_string

    arrow = to_arrow_schema(_parse_datatype_string(schema))
    return made.filter(F.col("shard") >= start // SHARD).mapInArrow(run, schema)


def _finished(spark: SparkSession, path: str) -> bool:
    """Whether a job has written this folder to its end."""
    done = spark._jvm.org.apache.hadoop.fs.Path(f"{path}/_SUCCESS")
    return done.getFileSystem(spark._jsc.hadoopConfiguration()).exists(done)


def write_shards(docs: DataFrame, path: str, key: int = 20240607, rounds: int = 1, ranks: str | None = None) -> DataFrame:
    """The shards as written below path, in `rounds` folders of consecutive shards, files in shard order.

    A folder that is finished is read and not made again, so a run that was stopped goes on with the next one.
    Documents and key have to be the same; the numbers of records do not depend on the files of the input.
    """
    spark = docs.sparkSession
    folders = [f"{path}/round={r}" for r in range(rounds)]
    todo = [r for r in range(rounds) if not _finished(spark, folders[r])]
    if todo:
        tokens, total, parts = numbered(docs, ranks)
        n_shards = -(-total // SHARD)
        for r in todo:
            made = shards_of(tokens, total, parts, key, r * n_shards // rounds, (r + 1) * n_shards // rounds)
            made.write.mode("overwrite").option("compression", "zstd").parquet(folders[r])
    return spark.read.schema("shard long, records long, bytes binary").parquet(*folders)

"""Arrow text columns as flat byte arrays, in slices of bounded size.

Every Arrow-batch operator of this subpackage reads its documents through these helpers, so that a null
text is an empty one everywhere and a worker's memory follows the slice size, not the batch size.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

SLICE_BYTES = 1 << 20

#: Bytes that separate words: space and 0x09 to 0x0D. They never occur inside a UTF-8 sequence.
IS_SPACE = np.zeros(256, dtype=bool)
IS_SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True

_rng = np.random.Generator(np.random.PCG64(20240229))
_BYTE_VALUES = _rng.integers(1, 2**63, 256, dtype=np.uint64) | np.uint64(1)
_BASE = np.uint64(0x9E3779B97F4A7C15)
_BASE_INVERSE = np.uint64(pow(0x9E3779B97F4A7C15, -1, 2**64))
_powers: dict[str, np.ndarray] = {}


def _power_table(base: np.uint64, n: int, key: str) -> np.ndarray:
    table = _powers.get(key)
    if table is None or len(table) < n:
        size = max(n, SLICE_BYTES + (SLICE_BYTES >> 2))
        steps = np.full(size, base, dtype=np.uint64)
        steps[0] = 1
        table = _powers[key] = np.cumprod(steps, dtype=np.uint64)
    return table[:n]


def mix(x: np.ndarray) -> np.ndarray:
    """The finaliser of splitmix64, over unsigned 64-bit values."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def text_slices(batch: pa.RecordBatch | pa.Table, limit: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Consecutive rows of at most `limit` text bytes together, or one longer row."""
    if batch.num_rows == 0:
        return
    text = batch.column(batch.schema.get_field_index("text"))
    sizes = pc.fill_null(pc.binary_length(text), 0).to_numpy(zero_copy_only=False) if isinstance(text, pa.Array) else pc.fill_null(pc.binary_length(text), 0).to_numpy()
    ends = np.cumsum(sizes.astype(np.int64))
    start = 0
    while start < batch.num_rows:
        before = ends[start - 1] if start else 0
        stop = max(start + 1, int(np.searchsorted(ends, before + limit, side="right")))
        yield batch.slice(start, stop - start)
        start = stop


def column(batch: pa.RecordBatch | pa.Table, name: str) -> pa.Array:
    got = batch.column(batch.schema.get_field_index(name))
    return got.combine_chunks() if isinstance(got, pa.ChunkedArray) else got


def texts(batch: pa.RecordBatch | pa.Table) -> list[str]:
    return pc.fill_null(column(batch, "text"), "").to_pylist()


def flat_bytes(batch: pa.RecordBatch | pa.Table) -> tuple[np.ndarray, np.ndarray]:
    """All texts end to end as bytes, and the n + 1 offsets of the rows."""
    array = pc.fill_null(column(batch, "text"), "").cast(pa.large_string())
    _, offsets, data = array.buffers()
    at = np.frombuffer(offsets, dtype=np.int64)[array.offset : array.offset + len(array) + 1]
    if data is None or not len(at):
        return np.zeros(0, np.uint8), np.zeros(len(array) + 1, np.int64)
    return np.frombuffer(data, dtype=np.uint8)[at[0] : at[-1]], at - at[0]


def word_bounds(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Byte starts and ends of the words, and the n + 1 offsets of the rows into them."""
    if not len(data):
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(offsets), np.int64)
    word = ~IS_SPACE[data]
    row_start = np.zeros(len(data) + 1, bool)
    row_start[offsets] = True
    previous = np.concatenate(([False], word[:-1])) & ~row_start[:-1]
    following = np.concatenate((word[1:], [False])) & ~row_start[1:]
    starts, ends = np.flatnonzero(word & ~previous), np.flatnonzero(word & ~following) + 1
    return starts, ends, np.searchsorted(starts, offsets)


def word_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit value for each word that depends on its bytes alone."""
    if not len(starts):
        return np.zeros(0, np.uint64)
    sums = np.zeros(len(data) + 1, np.uint64)
    np.cumsum(_BYTE_VALUES[data] * _power_table(_BASE, len(data), "up"), out=sums[1:])
    value = (sums[ends] - sums[starts]) * _power_table(_BASE_INVERSE, len(data), "down")[starts]
    return mix(value + (ends - starts).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93))


def shingle_hashes(words: np.ndarray, width: int) -> np.ndarray:
    """A 64-bit value for each run of `width` consecutive words."""
    n = len(words) - width + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    total = np.zeros(n, np.uint64)
    for k in range(width):
        total = total * np.uint64(0x5851F42D4C957F2D) + words[k : k + n]
    return mix(total)


def per_slice(docs: DataFrame, make: Callable[[pa.RecordBatch], dict | pa.RecordBatch], schema: str, columns: tuple[str, ...] = ("doc_id", "text")) -> DataFrame:
    """Apply `make` to slices of the named columns; other columns are never read."""
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import _parse_datatype_string

    arrow = to_arrow_schema(_parse_datatype_string(schema))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in text_slices(batch):
                yield as_batch(make(part), arrow)

    return docs.select(*columns).mapInArrow(run, schema)


def as_batch(made: dict | pa.RecordBatch, arrow: pa.Schema) -> pa.RecordBatch:
    if isinstance(made, pa.RecordBatch):
        return made
    return pa.RecordBatch.from_arrays([x if isinstance(x, pa.Array) and x.type == f.type else x.cast(f.type) if isinstance(x, pa.Array) else pa.array(x, f.type) for f in arrow for x in (made[f.name],)], schema=arrow)

"""Arrow text batches: bounded slices, byte-level word splitting and hashing.

Every helper takes whole texts.  A null text counts as empty.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

SLICE_BYTES = 2_000_000

#: Bytes that separate words (space and U+0009..U+000D).
SPACES = np.zeros(256, bool)
SPACES[[0x20, *range(0x09, 0x0E)]] = True

_MIX_A = np.uint64(0x9E3779B97F4A7C15)
_MIX_B = np.uint64(0xD6E8FEB86659FD93)
_TAIL_MASKS = np.array([(1 << (8 * k)) - 1 for k in range(8)] + [2**64 - 1], np.uint64)


def mix(h: np.ndarray) -> np.ndarray:
    """One 64-bit finalising round."""
    h = (h ^ (h >> np.uint64(32))) * _MIX_B
    h = (h ^ (h >> np.uint64(29))) * _MIX_A
    return h ^ (h >> np.uint64(32))


def sliced(batches: Iterator[pa.RecordBatch], text_col: str, limit: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Cuts batches so that a slice holds at most ``limit`` text bytes, or one row."""
    for batch in batches:
        if batch.num_rows == 0:
            continue
        off = text_offsets(batch.column(text_col))
        start = 0
        while start < batch.num_rows:
            stop = int(np.searchsorted(off, off[start] + limit, "right")) - 1
            stop = min(max(stop, start + 1), batch.num_rows)
            yield batch.slice(start, stop - start)
            start = stop


def spark_schema(schema: pa.Schema):
    """The Spark form of an Arrow schema; Arrow is what workers can build without a session."""
    from pyspark.sql.pandas.types import from_arrow_schema

    return from_arrow_schema(schema)


def fields(**kinds) -> pa.Schema:
    """An Arrow schema of named types."""
    return pa.schema(list(kinds.items()))


def text_offsets(col: pa.Array) -> np.ndarray:
    """Byte offsets of a string column, as int64, n + 1 of them."""
    kind = np.int64 if pa.types.is_large_string(col.type) else np.int32
    raw = np.frombuffer(col.buffers()[1], kind)
    return raw[col.offset : col.offset + len(col) + 1].astype(np.int64)


def text_bytes(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The text bytes of a string column and the offsets of its rows in them."""
    off = text_offsets(col)
    data = col.buffers()[2]
    if data is None or off[-1] == off[0]:
        return np.zeros(0, np.uint8), np.zeros(len(off), np.int64)
    raw = np.frombuffer(data, np.uint8)[off[0] : off[-1]]
    return raw, off - off[0]


def texts(col: pa.Array) -> list[str]:
    """Python strings, null as empty."""
    return [x or "" for x in col.to_pylist()]


def word_spans(raw: np.ndarray, off: np.ndarray, separator: np.ndarray = SPACES) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start and end byte of every word, and for each row the number of words before it."""
    if not len(raw):
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(off), np.int64)
    inside = ~separator[raw]
    first = np.empty(len(raw), bool)
    first[0] = True
    np.logical_not(inside[:-1], out=first[1:])
    edges = off[:-1][off[:-1] < len(raw)]
    first[edges] = True
    first &= inside
    last = np.empty(len(raw), bool)
    last[-1] = True
    np.logical_not(inside[1:], out=last[:-1])
    edges = off[1:] - 1
    last[edges[edges >= 0]] = True
    last &= inside
    starts = np.flatnonzero(first)
    return starts, np.flatnonzero(last) + 1, np.searchsorted(starts, off)


def word_hashes(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each word, eight bytes at a time."""
    n = len(starts)
    h = np.zeros(n, np.uint64)
    if not n:
        return h
    padded = np.concatenate([raw, np.zeros(8, np.uint8)])
    view = np.ndarray((len(raw) + 1,), "<u8", padded, strides=(1,))
    length = ends - starts
    h = (view[starts] & _TAIL_MASKS[np.minimum(length, 8)]) * _MIX_A
    h ^= length.astype(np.uint64) << np.uint64(56)
    h = mix(h)
    todo = np.flatnonzero(length > 8)
    at = 8
    while len(todo):
        rest = length[todo] - at
        h[todo] = mix((h[todo] ^ (view[starts[todo] + at] & _TAIL_MASKS[np.minimum(rest, 8)])) * _MIX_A)
        todo, at = todo[rest > 8], at + 8
    return h


def row_of(counts_before: np.ndarray) -> np.ndarray:
    """The row of each item, from the counts before each row."""
    return np.repeat(np.arange(len(counts_before) - 1), np.diff(counts_before))

"""Vectorised text primitives over Arrow string buffers.

A batch of documents is handled as one byte buffer plus document offsets, so
that word boundaries, word hashes and sliding windows cost a few numpy passes
for a whole batch and not one Python call for each word.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from cityweave.session import ship

# Workers live long and share an executor's memory; Arrow's own pool would keep what is freed.
pa.set_memory_pool(pa.system_memory_pool())

#: Bytes of text that one numpy pass handles; a longer single text is a block of its own.
BLOCK_BYTES = 1 << 20

# Word separators: space and the control characters tab to carriage return.
SEPARATOR = np.zeros(256, bool)
SEPARATOR[[0x20, *range(0x09, 0x0E)]] = True

LOWER = np.arange(256, dtype=np.uint8)
LOWER[ord("A") : ord("Z") + 1] += 32
LOWER_TABLE = bytes(LOWER)

_BASE = 0x9E3779B97F4A7C15
_INVERSE = pow(_BASE, -1, 1 << 64)
BYTE_CODE = np.random.default_rng(20240101).integers(1, 1 << 63, 256, dtype=np.int64).astype(np.uint64)

_powers: dict[int, np.ndarray] = {}


def powers(base: int, n: int) -> np.ndarray:
    """base**0 .. base**(n-1) modulo 2**64, kept for the next call."""
    have = _powers.get(base)
    if have is None or len(have) < n:
        steps = np.full(max(n, 1 << 16), base, np.uint64)
        steps[0] = 1
        have = _powers[base] = np.multiply.accumulate(steps)
    return have[:n]


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit words."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def mapped(df: DataFrame, run, schema: str) -> DataFrame:
    """df.mapInArrow, after seeing that workers know this package."""
    ship(df.sparkSession)
    return df.mapInArrow(run, schema)


def buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets (one more than rows, from 0) of a string column; null counts as empty."""
    if pa.types.is_large_string(column.type):
        column = column.cast(pa.string())
    if column.null_count:
        column = column.fill_null("")
    if not len(column):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, where, data = column.buffers()
    offsets = np.frombuffer(where, np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    text = np.frombuffer(data, np.uint8)[offsets[0] : offsets[-1]] if data is not None else np.zeros(0, np.uint8)
    return text, offsets - offsets[0]


def blocks(batches, text: str = "text") -> Iterator[pa.RecordBatch]:
    """Cuts record batches into slices of at most BLOCK_BYTES of text (or one row)."""
    for batch in batches:
        if not batch.num_rows:
            continue
        for row, piece in parts(batch.column(batch.schema.get_field_index(text))):
            yield batch.slice(row, len(piece))


def parts(column: pa.Array) -> Iterator[tuple[int, pa.Array]]:
    """(first row, slice) of a text column in pieces of at most BLOCK_BYTES (or one row)."""
    _, offsets = buffers(column)
    row = 0
    while row < len(column):
        end = min(max(int(np.searchsorted(offsets, offsets[row] + BLOCK_BYTES, "right")) - 1, row + 1), len(column))
        yield row, column.slice(row, end - row)
        row = end


class Words:
    """Separator-delimited words of a block: byte spans, document index and counts."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray, separator: np.ndarray = SEPARATOR):
        self.data, self.offsets = data, offsets
        n_docs = len(offsets) - 1
        inside = ~separator[data]
        opens, closes = inside.copy(), inside.copy()
        if len(data):
            opens[1:] &= ~inside[:-1]
            closes[:-1] &= ~inside[1:]
            edge = offsets[:-1][offsets[:-1] < len(data)]
            opens[edge] = inside[edge]
            edge = offsets[1:][offsets[1:] > 0] - 1
            closes[edge] = inside[edge]
        self.start = np.flatnonzero(opens)
        self.end = np.flatnonzero(closes) + 1
        #: index of each document's first word, and one past the last document's
        self.first = np.searchsorted(self.start, offsets)
        self.count = np.diff(self.first)
        self.doc = np.repeat(np.arange(n_docs), self.count)

    def hashes(self, fold: bool = False) -> np.ndarray:
        """A 64-bit hash of each word's bytes (ASCII letters lower-cased first, if fold)."""
        data = LOWER[self.data] if fold else self.data
        prefix = prefix_hash(data)
        return mix(span_hash(prefix, self.start, self.end) + (self.end - self.start).astype(np.uint64))

    def windows(self, width: int) -> np.ndarray:
        """Indices of words that begin a window of `width` words within one document."""
        n = len(self.start)
        if n < width:
            return np.zeros(0, np.int64)
        return np.flatnonzero(self.doc[: n - width + 1] == self.doc[width - 1 :])


def exact_names(data: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """A number for each of the byte strings that lie one behind another in data, equal for equal strings only."""
    ends = np.zeros(len(lengths) + 1, np.int64)
    np.cumsum(lengths, out=ends[1:])
    strings = pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(lengths), [None, pa.py_buffer(ends), pa.py_buffer(np.ascontiguousarray(data))])
    return strings.dictionary_encode().indices.to_numpy(zero_copy_only=False).astype(np.int64)


def prefix_hash(data: np.ndarray) -> np.ndarray:
    out = np.zeros(len(data) + 1, np.uint64)
    np.cumsum(BYTE_CODE[data] * powers(_BASE, len(data)), out=out[1:])
    return out


def span_hash(prefix: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """Hash of data[start:end] that doesn't depend on where the span lies."""
    return (prefix[end] - prefix[start]) * powers(_INVERSE, len(prefix))[start]


def window_hash(word_hash: np.ndarray, offsets: tuple[int, ...], width: int) -> np.ndarray:
    """For each run of `width` words, a hash of those at the given offsets from its first."""
    n = max(len(word_hash) - width + 1, 0)
    out = np.zeros(n, np.uint64)
    for k, step in enumerate(offsets):
        out += word_hash[step : step + n] * np.uint64((_BASE * (2 * k + 3)) % (1 << 64) | 1)
    return mix(out)


def gram_counts(data: np.ndarray, offsets: np.ndarray, dims: int, size: int = 3, fold: bool = True) -> np.ndarray:
    """Counts of (case-folded) byte n-grams by hash bucket, one row of `dims` for each document."""
    n_docs, n = len(offsets) - 1, len(data) - size + 1
    if n <= 0:
        return np.zeros((n_docs, dims), np.float32)
    plain = np.where(SEPARATOR[data], np.uint8(32), data)
    folded = (LOWER[plain] if fold else plain).astype(np.uint32)
    code = np.zeros(n, np.uint32)
    for k in range(size):
        code = code * np.uint32(0x01000193) + folded[k : k + n]
    code = ((code * np.uint32(0x9E3779B1)) >> np.uint32(32 - (dims - 1).bit_length())).astype(np.int64)
    doc = np.repeat(np.arange(n_docs), np.diff(offsets))
    whole = doc[:n] == doc[size - 1 :]
    return np.bincount(doc[:n][whole] * dims + code[whole], minlength=n_docs * dims).reshape(n_docs, dims).astype(np.float32)


def has_letter(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Whether each document has a letter of any script."""
    ascii_letter = np.zeros(256, bool)
    ascii_letter[[*range(65, 91), *range(97, 123)]] = True
    seen = np.concatenate(([0], np.cumsum(ascii_letter[data])))
    out = seen[offsets[1:]] > seen[offsets[:-1]]
    for k in np.flatnonzero(~out & (np.diff(offsets) > 0)):
        out[k] = any(c.isalpha() for c in data[offsets[k] : offsets[k + 1]].tobytes().decode("utf-8", "ignore"))
    return out

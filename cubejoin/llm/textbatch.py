"""Vectorised word hashing over Arrow string batches.

Everything works on the UTF-8 bytes of a slice of documents at once: word
borders come from a 256-entry byte class, word hashes from one segmented
polynomial sum, n-gram hashes from shifted sums of word hashes.  No Python loop
runs per word.  Hashes are 64 bits of a keyed polynomial followed by a mixing
step; equal words always get equal hashes, on every machine.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

SLICE_BYTES = 2 << 20
_RNG = np.random.Generator(np.random.PCG64(20240117))
_BYTE_KEYS = _RNG.integers(1, 2**63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_WORD_STEP = np.uint64(0x9E3779B97F4A7C15 | 3)
_GRAM_STEP = np.uint64(0xD6E8FEB86659FD93)
_POWERS = np.cumprod(np.full(128, _WORD_STEP, dtype=np.uint64))

LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


def byte_class(is_word) -> np.ndarray:
    """Boolean table of the bytes that belong to words."""
    return np.array([bool(is_word(b)) for b in range(256)])


#: Words of the shingle contract: anything but space and TAB..CR.
NON_BLANK = byte_class(lambda b: b != 0x20 and not 0x09 <= b <= 0x0D)
#: Words of the decontamination contract, after lower-casing: digits, a-z, non-ASCII.
ALNUM = byte_class(lambda b: 0x30 <= b <= 0x39 or 0x61 <= b <= 0x7A or b >= 0x80)


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser; wraps on purpose."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def string_buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and row borders of a string column; nulls become empty rows."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("")
    if pa.types.is_large_string(column.type):
        offsets = np.frombuffer(column.buffers()[1], dtype=np.int64)
    else:
        column = column.cast(pa.string())
        offsets = np.frombuffer(column.buffers()[1], dtype=np.int32)
    offsets = offsets[column.offset : column.offset + len(column) + 1].astype(np.int64)
    data = column.buffers()[2]
    if data is None or len(column) == 0:
        return np.empty(0, np.uint8), np.zeros(len(column) + 1, np.int64)
    raw = np.frombuffer(data, dtype=np.uint8)[offsets[0] : offsets[-1]]
    return raw, offsets - offsets[0]


def slices(batch: pa.RecordBatch, text: str, limit: int = SLICE_BYTES) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    """Row ranges of about ``limit`` text bytes (one row at least) with their bytes and borders."""
    at = batch.schema.get_field_index(text)
    raw, borders = string_buffers(batch.column(at))
    lo = 0
    while lo < batch.num_rows:
        hi = int(np.searchsorted(borders, borders[lo] + limit, "right")) - 1
        hi = min(max(hi, lo + 1), batch.num_rows)
        yield batch.slice(lo, hi - lo), raw[borders[lo] : borders[hi]], borders[lo : hi + 1] - borders[lo]
        lo = hi


class Words:
    """Words of a slice: hash, byte start and end, and the word range of each row."""

    __slots__ = ("hashes", "starts", "ends", "rows")

    def __init__(self, raw: np.ndarray, borders: np.ndarray, table: np.ndarray, lower: bool = True):
        if lower:
            raw = LOWER[raw]
        inside = table[raw]
        first, last = inside.copy(), inside.copy()
        if len(raw):
            first[1:] &= ~inside[:-1]
            last[:-1] &= ~inside[1:]
            heads = borders[:-1][borders[:-1] < borders[1:]]
            first[heads] = inside[heads]
            tails = borders[1:][borders[:-1] < borders[1:]] - 1
            last[tails] = inside[tails]
        self.starts = np.flatnonzero(first)
        self.ends = np.flatnonzero(last) + 1
        self.rows = np.searchsorted(self.starts, borders)
        self.hashes = segment_hashes(raw[inside], self.ends - self.starts)


def segment_hashes(data: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Hash of each consecutive segment of ``data`` (all lengths positive)."""
    if not len(lengths):
        return np.empty(0, np.uint64)
    global _POWERS
    longest = int(lengths.max())
    if longest > len(_POWERS):
        _POWERS = np.cumprod(np.full(2 * longest, _WORD_STEP, dtype=np.uint64))
    heads = np.cumsum(lengths) - lengths
    place = np.arange(len(data), dtype=np.int32) - np.repeat(heads.astype(np.int32), lengths)
    values = _BYTE_KEYS[data]
    values *= _POWERS[place]
    total = np.add.reduceat(values, heads)
    return mix(total + lengths.astype(np.uint64))


def gram_hashes(words: np.ndarray, rows: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """n-gram hashes inside rows: (hashes, first word index of each, gram range of each row)."""
    counts = np.maximum(np.diff(rows) - (n - 1), 0)
    borders = np.concatenate(([0], np.cumsum(counts)))
    total = int(borders[-1])
    if not total:
        return np.empty(0, np.uint64), np.empty(0, np.int64), borders
    at = np.arange(total) + np.repeat(rows[:-1] - borders[:-1], counts)
    length = len(words) - n + 1
    grams = words[:length].copy()
    for j in range(1, n):
        grams *= _GRAM_STEP
        grams += words[j : j + length]
    return mix(grams[at] + np.uint64(n)), at, borders

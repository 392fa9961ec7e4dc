"""Whole Arrow text columns as byte arrays: words, hashes and distinct words without a Python loop.

A word is a maximal run of bytes other than space and 0x09-0x0D, which for UTF-8 is the same as
the pattern [^\\x20\\x09-\\x0D]+ over code points.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

SPACE = np.zeros(256, dtype=bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
_BASE = 0x9E3779B97F4A7C15
_BASE_INVERSE = pow(_BASE, -1, 2**64)
_powers: dict[int, np.ndarray] = {}


def powers(base: int, n: int) -> np.ndarray:
    """base**0 .. base**(n-1) modulo 2**64; kept for the next call, doubled when too short."""
    have = _powers.get(base)
    if have is None or len(have) < n:
        size = max(1 << 16, 1 << (int(n) - 1).bit_length())
        have = np.full(size, base, dtype=np.uint64)
        have[0] = 1
        have = np.multiply.accumulate(have)
        _powers[base] = have
    return have[:n]


def release() -> None:
    """Gives back what a finished task no longer needs: a worker may stay idle beside other work."""
    import ctypes
    import gc

    _powers.clear()
    gc.collect()
    pa.default_memory_pool().release_unused()
    libc = ctypes.CDLL(None)
    if hasattr(libc, "malloc_trim"):
        libc.malloc_trim(0)


def tidy(run):
    """run, a function of Arrow batches, with release() after its last batch."""

    def whole(batches):
        try:
            yield from run(batches)
        finally:
            release()

    return whole


def mix(h: np.ndarray) -> np.ndarray:
    """The finaliser of splitmix64."""
    h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def text_bytes(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """All texts end to end as uint8, and the n + 1 offsets; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = pc.fill_null(column.cast(pa.large_string()), "")
    if len(column) == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, off, data = column.buffers()
    offsets = np.frombuffer(off, dtype=np.int64)[column.offset : column.offset + len(column) + 1]
    raw = np.frombuffer(data, dtype=np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def word_spans(buf: np.ndarray, offsets: np.ndarray, space: np.ndarray = SPACE, breaks: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """starts, ends (exclusive) of all words, and the n + 1 offsets of each text's words.

    breaks: true at bytes where a new word begins although the byte before belongs to one.
    """
    if len(buf) == 0:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(offsets), np.int64)
    inside = ~space[buf]
    edge = np.zeros(len(buf) + 1, dtype=bool)  # a text begins here
    edge[offsets] = True
    if breaks is not None:
        edge[:-1] |= breaks
    first = inside.copy()
    first[1:] &= ~inside[:-1] | edge[1:-1]
    last = inside.copy()
    last[:-1] &= ~inside[1:] | edge[1:-1]
    starts = np.flatnonzero(first)
    return starts, np.flatnonzero(last) + 1, np.searchsorted(starts, offsets)


def span_hashes(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray, block: int = 1 << 21) -> np.ndarray:
    """A 64-bit hash of each span; spans are in order and do not overlap. Works in blocks of bytes.

    A polynomial modulo 2**64, for features alone: texts can be built whose hashes meet. distinct_spans tells words apart.
    """
    out = np.empty(len(starts), dtype=np.uint64)
    i = 0
    while i < len(starts):
        at = starts[i]
        j = max(i + 1, int(np.searchsorted(starts, at + block)))
        top = ends[j - 1]
        sums = np.zeros(top - at + 1, dtype=np.uint64)
        np.cumsum((buf[at:top].astype(np.uint64) + np.uint64(1)) * powers(_BASE, top - at), out=sums[1:])
        s, e = starts[i:j] - at, ends[i:j] - at
        h = (sums[e] - sums[s]) * powers(_BASE_INVERSE, top - at)[s]
        out[i:j] = mix(h + (e - s).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93))
        i = j
    return out


def distinct_spans(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each span its number among the distinct ones by their bytes, and where each distinct one first stands; spans are in order and do not overlap."""
    if len(starts) == 0:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    edge = np.zeros(len(buf) + 1, dtype=np.int8)
    edge[starts] = 1
    edge[ends] -= 1
    flat = buf[np.cumsum(edge[:-1], dtype=np.int8).view(bool)]
    wide = len(flat) >= 1 << 31
    at = np.zeros(len(starts) + 1, dtype=np.int64 if wide else np.int32)
    np.cumsum(ends - starts, out=at[1:])
    spans = pa.Array.from_buffers(pa.large_binary() if wide else pa.binary(), len(starts), [None, pa.py_buffer(at), pa.py_buffer(flat)])
    found = spans.dictionary_encode()
    codes = found.indices.to_numpy().astype(np.int64)
    first = np.zeros(len(found.dictionary), dtype=np.int64)
    first[codes[::-1]] = np.arange(len(codes) - 1, -1, -1)  # the last write to a place stays: the smallest
    return codes, first


def slices(batch: pa.RecordBatch, column: str = "text", limit: int = 4 << 20) -> Iterator[pa.RecordBatch]:
    """The batch in runs of rows with about limit bytes of text each, at least a row."""
    if batch.num_rows == 0:
        return
    sizes = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    total = np.cumsum(sizes)
    i = 0
    while i < len(sizes):
        done = total[i - 1] if i else 0
        j = max(i + 1, int(np.searchsorted(total, done + limit, side="right")))
        yield batch.slice(i, j - i)
        i = j


def sum_by_text(values: np.ndarray, word_offsets: np.ndarray) -> np.ndarray:
    """Sums of values over each text's words."""
    total = np.concatenate([np.zeros(1, values.dtype), np.cumsum(values)])
    return total[word_offsets[1:]] - total[word_offsets[:-1]]

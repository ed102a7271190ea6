"""Vectorised word splitting and hashing of Arrow text columns."""

from __future__ import annotations

import ctypes
import inspect

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401  used as pa.compute

#: White space: 0x20 and 0x09 to 0x0D.
SPACE = np.zeros(256, bool)
SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32

_BASE = 0x9E3779B97F4A7C15 | 1
_INVERSE = pow(_BASE, -1, 1 << 64)
_powers = {"n": 0, "up": np.ones(1, np.uint64), "down": np.ones(1, np.uint64)}
SLICE = 1 << 18


def mix64(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (xor-shift and odd multipliers): every output bit depends on every input bit."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def _pow(n: int) -> tuple[np.ndarray, np.ndarray]:
    if _powers["n"] < n:
        n = max(n, SLICE)
        for key, base in (("up", _BASE), ("down", _INVERSE)):
            a = np.full(n, base, np.uint64)
            a[0] = 1
            _powers[key] = np.multiply.accumulate(a)
        _powers["n"] = n
    return _powers["up"], _powers["down"]


def flatten(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of all rows, and row offsets (int64, one more than rows). Null rows are empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("")
    column = column.cast(pa.large_string())
    if len(column) == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, offs, data = column.buffers()
    offsets = np.frombuffer(offs, np.int64)[column.offset : column.offset + len(column) + 1]
    raw = np.frombuffer(data, np.uint8)[offsets[0] : offsets[-1]] if data is not None else np.zeros(0, np.uint8)
    return raw, offsets - offsets[0]


def spans(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of all words, and for each row the index of its first word (one more than rows)."""
    n = len(raw)
    if n == 0:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(offsets), np.int64)
    solid = ~SPACE[raw]
    edge = np.zeros(n + 1, bool)
    edge[offsets] = True
    first = edge[:-1].copy()
    first[1:] |= ~solid[:-1]
    last = edge[1:].copy()
    last[:-1] |= ~solid[1:]
    starts = np.flatnonzero(solid & first)
    ends = np.flatnonzero(solid & last) + 1
    return starts, ends, np.searchsorted(starts, offsets)


def hash_spans(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hash of each span: a polynomial of its bytes, from prefix sums modulo 2^64, then mixed."""
    out = np.empty(len(starts), np.uint64)
    i = 0
    while i < len(starts):
        lo = int(starts[i])
        j = max(i + 1, int(np.searchsorted(ends, lo + SLICE, "right")))
        hi = int(ends[j - 1])
        up, down = _pow(hi - lo + 1)
        sums = np.zeros(hi - lo + 1, np.uint64)
        np.cumsum((raw[lo:hi].astype(np.uint64) + np.uint64(1)) * up[: hi - lo], out=sums[1:])
        s, e = starts[i:j] - lo, ends[i:j] - lo
        out[i:j] = (sums[e] - sums[s]) * down[s]
        i = j
    return mix64(out ^ (ends - starts).astype(np.uint64))


def doc_index(first: np.ndarray) -> np.ndarray:
    """Row of each word, from spans()'s third result."""
    return np.repeat(np.arange(len(first) - 1), np.diff(first))


def word_hashes(column, lower: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """Hash of each word of all rows (A-Z lower-cased first), and each row's first word index."""
    raw, offsets = flatten(column)
    if lower:
        raw = LOWER[raw]
    starts, ends, first = spans(raw, offsets)
    return hash_spans(raw, starts, ends), first


def shingles(words: np.ndarray, first: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of each row's `width`-word shingles (the whole sequence if shorter), and row offsets. Not distinct."""
    counts = np.diff(first)
    n = len(words)
    if n == 0:
        return np.zeros(0, np.uint64), np.zeros(len(first), np.int64)
    h = np.zeros(n, np.uint64)
    for k in range(width):
        part = np.zeros(n, np.uint64)
        part[: n - k] = words[k:]
        h = mix64(h * np.uint64(0xD6E8FEB86659FD93) + part + np.uint64(k + 1))
    row = doc_index(first)
    left = first[1:][row] - np.arange(n)
    keep = left >= width
    for r in np.flatnonzero((counts > 0) & (counts < width)):
        i, whole = first[r], np.uint64(counts[r])
        for w in words[first[r] : first[r + 1]]:
            whole = mix64(np.array([w ^ (whole << np.uint64(1))], np.uint64))[0]
        h[i] = whole
        keep[i] = True
    sizes = np.bincount(row[keep], minlength=len(counts))
    return h[keep], np.concatenate([[0], np.cumsum(sizes)])


def slices(batch: pa.RecordBatch, column: str, most: int = 1 << 20):
    """Consecutive parts of a batch whose texts hold about `most` bytes at most; a longer text is a part of its own.
    This bounds the arrays that a task works with, whatever the batch holds."""
    text = batch.column(column)
    sizes = pa.compute.fill_null(pa.compute.binary_length(text), 0).to_numpy(zero_copy_only=False)
    ends = np.cumsum(sizes, dtype=np.int64)
    i = 0
    while i < batch.num_rows:
        before = int(ends[i - 1]) if i else 0
        j = max(i + 1, int(np.searchsorted(ends, before + most, "right")))
        yield batch.slice(i, j - i)
        i = j


def released(run):
    """`run`, a generator over a task's batches, or a function of a group's table or of two, that gives freed memory back
    to the system at its end: Python workers outlive tasks, and what they keep counts while later stages run."""

    def over_batches(batches):
        try:
            yield from run(batches)
        finally:
            _release()

    def over_group(table):
        out = run(table)
        _release()
        return out

    def over_two(left, right):
        out = run(left, right)
        _release()
        return out

    return over_batches if inspect.isgeneratorfunction(run) else over_two if run.__code__.co_argcount == 2 else over_group


def _release() -> None:
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc alone has it
    if trim is not None:
        trim(0)

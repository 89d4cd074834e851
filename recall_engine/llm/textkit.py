"""Vectorised text primitives on Arrow buffers, shared by the Python-side operators.

A word is a maximal run of characters other than space and U+0009 to U+000D, so word borders can be found on the
UTF-8 bytes; no other code point contains one of those bytes.
"""

from __future__ import annotations

import ctypes
import functools
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa

#: Text that rules and encoders take at a time: their arrays are up to a hundred bytes for each of text.
SMALL_SLICE = 1_000_000


def give_back() -> None:
    """Returns memory that this process has freed to the system. Allocators keep it otherwise, and a worker outlives its
    task by many: what its largest task took would stay on the executor beside all later ones."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # not every C library has it
    if trim is not None:
        trim(0)


def giving_back(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """``run``, a function for mapInArrow, which gives back its memory at the end of each task."""

    @functools.wraps(run)
    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(batches)
        finally:
            give_back()

    return task


def slices(batches: Iterator[pa.RecordBatch], text: str, max_bytes: int = 3_000_000) -> Iterator[pa.RecordBatch]:
    """The batches cut so that each holds about ``max_bytes`` of the column ``text`` (a longer text stands alone)."""
    for batch in batches:
        if batch.num_rows == 0:
            continue
        col = batch.column(batch.schema.get_field_index(text))
        ends = np.cumsum(np.diff(string_buffers(col)[1]))
        lo = 0
        while lo < batch.num_rows:
            base = ends[lo - 1] if lo else 0
            hi = max(lo + 1, int(np.searchsorted(ends, base + max_bytes, side="right")))
            yield batch.slice(lo, hi - lo)
            lo = hi


def string_buffers(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets (n + 1, from 0) of a string or binary column; null counts as empty."""
    if pa.types.is_string(col.type) or pa.types.is_large_string(col.type):
        wide = pa.large_string()
    else:
        wide = pa.large_binary()
    col = col.cast(wide)
    if col.null_count:
        col = col.fill_null("" if wide == pa.large_string() else b"")
    _, off, data = col.buffers()
    n = len(col)
    if n == 0 or off is None:
        return np.zeros(0, np.uint8), np.zeros(n + 1, np.int64)
    off = np.frombuffer(off, np.int64)[col.offset : col.offset + n + 1]
    raw = np.frombuffer(data, np.uint8)[off[0] : off[-1]] if data is not None and data.size else np.zeros(0, np.uint8)
    return raw, off - off[0]


def space_mask(raw: np.ndarray) -> np.ndarray:
    return (raw == 32) | ((raw >= 9) & (raw <= 13))


def lower_ascii(raw: np.ndarray) -> np.ndarray:
    """A to Z become a to z; no other byte changes."""
    return np.where((raw >= 65) & (raw <= 90), raw + 32, raw).astype(np.uint8)


def words(raw: np.ndarray, off: np.ndarray) -> tuple[pa.Array, np.ndarray]:
    """All words of all texts in order, and per text the index of its first word (n + 1 entries)."""
    space = space_mask(raw)
    edge = np.ones(len(raw) + 1, bool)
    edge[1:-1] = space[:-1]
    edge[off] = True
    first = np.flatnonzero(~space & edge[:-1]) if len(raw) else np.zeros(0, np.int64)
    kept = raw[~space]
    at = np.cumsum(~space) - 1 if len(raw) else np.zeros(0, np.int64)
    starts = np.append(at[first], len(kept)).astype(np.int64)
    flat = pa.LargeStringArray.from_buffers(len(first), pa.py_buffer(starts), pa.py_buffer(np.ascontiguousarray(kept)))
    return flat, np.searchsorted(first, off)


def owner(bounds: np.ndarray) -> np.ndarray:
    """For each element of runs with the given n + 1 bounds, the index of its run."""
    return np.repeat(np.arange(len(bounds) - 1), np.diff(bounds))


def codes(flat: pa.Array) -> tuple[np.ndarray, pa.Array]:
    """Dictionary codes (exact, per batch) and the distinct values."""
    enc = flat.dictionary_encode()
    return enc.indices.to_numpy(zero_copy_only=False).astype(np.int64), enc.dictionary


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser (published multiply-xorshift constants)."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def hash_values(values: pa.Array, seed: int = 0) -> np.ndarray:
    """64-bit hash of each string, the same on every machine."""
    import xxhash

    h = xxhash.xxh3_64_intdigest
    return np.fromiter((h(v, seed) for v in values.cast(pa.large_binary()).to_pylist()), np.uint64, len(values))


_BASE = np.uint64(0x9E3779B97F4A7C15 | 1)
_BASE_INVERSE = np.uint64(pow(int(_BASE), -1, 1 << 64))
_POWERS: dict[str, np.ndarray] = {}


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """The first n powers of the base and of its inverse modulo 2^64."""
    if len(_POWERS.get("up", ())) < n:
        size = max(n, 1 << 16)
        for name, base in (("up", _BASE), ("down", _BASE_INVERSE)):
            p = np.full(size, base, np.uint64)
            p[0] = 1
            _POWERS[name] = np.multiply.accumulate(p)
    return _POWERS["up"][:n], _POWERS["down"][:n]


def word_hashes(raw: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """A 64-bit hash of every word, without making the words: differences of a running polynomial over mixed byte
    values, moved to position zero by the inverse base. Also each text's first word (n + 1)."""
    if not len(raw):
        return np.zeros(0, np.uint64), np.zeros(len(off), np.int64)
    space = space_mask(raw)
    edge = np.zeros(len(raw) + 1, bool)
    edge[off] = True
    first, last = ~space, ~space
    first[1:] &= space[:-1] | edge[1:-1]
    last[:-1] &= space[1:] | edge[1:-1]
    start, end = np.flatnonzero(first), np.flatnonzero(last)
    table = mix64(np.arange(1, 257, dtype=np.uint64))
    up, down = _powers(len(raw))
    run = table[raw]
    run *= up
    np.add.accumulate(run, out=run)
    h = run[end]
    h[start > 0] -= run[start[start > 0] - 1]
    h *= down[start]
    return mix64(h + (end - start).astype(np.uint64) * _BASE), np.searchsorted(start, off)


def range_hashes(codes: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """A 64-bit hash of ``codes[start:end]`` for each range, in time of the whole and the number of ranges: nested ranges
    are not read again. Equal ranges have equal hashes wherever they stand."""
    up, down = _powers(len(codes) + 1)
    run = mix64(codes.astype(np.uint64) + np.uint64(1))
    run *= up[: len(codes)]
    run = np.concatenate([np.zeros(1, np.uint64), np.cumsum(run, dtype=np.uint64)])
    return mix64((run[end] - run[start]) * down[start] + (end - start).astype(np.uint64) * _BASE)

"""Vectorised text primitives shared by the operators of this folder.

Everything works on the UTF-8 bytes of a whole Arrow string column at once:
words are found with a byte table, hashed with a polynomial prefix sum and
combined into shingles, so no Python loop runs per word.  Texts of any length
are hashed in slices cut between words, so memory does not follow the longest
text.
"""

from __future__ import annotations

import ctypes
import sys

import numpy as np
import pyarrow as pa

U = np.uint64
#: Hands freed memory back to the system, where the C library has it.
_TRIM = getattr(ctypes.CDLL(None), "malloc_trim", None) if sys.platform.startswith("linux") else None
#: A word is a maximal run of bytes other than these (fixed values).
SPACE_BYTES = (0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D)
_MASK = (1 << 64) - 1
_BASE = 0x9E3779B97F4A7C15 | 1
_BASE_INV = pow(_BASE, -1, 1 << 64)
#: Bytes that are hashed at a time; the tables of powers follow it.
CHUNK_BYTES = 1 << 18

_rng = np.random.default_rng(20240611)
_CODES = _rng.integers(1, 1 << 63, 256, dtype=np.uint64) * U(2) + U(1)
_CODES_LOWER = _CODES.copy()
_CODES_LOWER[65:91] = _CODES[97:123]
_SHINGLE_KEYS = _rng.integers(1, 1 << 63, 64, dtype=np.uint64) * U(2) + U(1)
_NOT_SPACE = np.ones(256, bool)
_NOT_SPACE[list(SPACE_BYTES)] = False
_powers: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser over unsigned 64-bit numbers."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> U(30)
    x *= U(0xBF58476D1CE4E5B9)
    x ^= x >> U(27)
    x *= U(0x94D049BB133111EB)
    x ^= x >> U(31)
    return x


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    size = max(CHUNK_BYTES, n) + 1
    if 0 not in _powers or len(_powers[0][0]) < size:
        with np.errstate(over="ignore"):
            _powers[0] = tuple(np.cumprod(np.concatenate([[U(1)], np.full(size - 1, b, np.uint64)]), dtype=np.uint64) for b in (U(_BASE), U(_BASE_INV)))
    return _powers[0]


def text_view(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes and int64 offsets of a string column; null counts as empty."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    if len(col) == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    if col.null_count:
        col = col.fill_null("")
    wide = pa.types.is_large_string(col.type) or pa.types.is_large_binary(col.type)
    bufs = col.buffers()
    off = np.frombuffer(bufs[1], np.int64 if wide else np.int32)[col.offset : col.offset + len(col) + 1].astype(np.int64)
    data = np.frombuffer(bufs[2], np.uint8)[off[0] : off[-1]] if bufs[2] is not None else np.zeros(0, np.uint8)
    return data, off - off[0]


def row_chunks(off: np.ndarray, limit: int = CHUNK_BYTES):
    """Ranges of rows of about ``limit`` bytes each, one row at least."""
    lo, n = 0, len(off) - 1
    while lo < n:
        hi = max(lo + 1, int(np.searchsorted(off, off[lo] + limit, side="right")) - 1)
        yield lo, hi
        lo = hi


def slices(batches, limit: int = 1 << 20):
    """The rows of Arrow batches in slices of about ``limit`` bytes, one row at least.

    What a task does with a slice then needs memory for that slice, not for all
    rows of a batch; what is freed goes back to the system when the task ends.
    """
    for batch in batches:
        if batch.num_rows:
            size = max(1, batch.num_rows * limit // max(1, batch.nbytes))
            for lo in range(0, batch.num_rows, size):
                yield batch.slice(lo, size)
        del batch
    pa.default_memory_pool().release_unused()
    if _TRIM is not None:
        _TRIM(0)


def word_table(data: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of all words, and per row the index of its first word."""
    if not len(data):
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(off), np.int64)
    solid = _NOT_SPACE[data]
    before = np.empty_like(solid)
    before[0], before[1:] = False, solid[:-1]
    before[off[:-1][off[:-1] < len(data)]] = False
    after = np.empty_like(solid)
    after[-1], after[:-1] = False, solid[1:]
    after[off[1:][off[1:] > 0] - 1] = False
    starts = np.flatnonzero(solid & ~before)
    return starts, np.flatnonzero(solid & ~after) + 1, np.searchsorted(starts, off)


def word_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, lower: bool) -> np.ndarray:
    """A 64-bit hash of each word; ``lower`` maps A-Z to a-z first."""
    out = np.empty(len(starts), np.uint64)
    codes = _CODES_LOWER if lower else _CODES
    lo = 0
    while lo < len(starts):
        hi = max(lo + 1, int(np.searchsorted(ends, starts[lo] + CHUNK_BYTES, side="right")))
        at, to = int(starts[lo]), int(ends[hi - 1])
        power, inverse = _power_tables(to - at)
        total = np.zeros(to - at + 1, np.uint64)
        with np.errstate(over="ignore"):
            np.cumsum(codes[data[at:to]] * power[: to - at], out=total[1:])
            s = starts[lo:hi] - at
            out[lo:hi] = mix64((total[ends[lo:hi] - at] - total[s]) * inverse[s])
        lo = hi
    return out


def run_hashes(words: np.ndarray, k: int) -> np.ndarray:
    """Hash of each run of ``k`` consecutive words (runs over row borders included)."""
    n = len(words) - k + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    with np.errstate(over="ignore"):
        if k <= 8:
            acc = words[:n] * _SHINGLE_KEYS[0]
            for i in range(1, k):
                acc += words[i : i + n] * _SHINGLE_KEYS[i]
        else:
            acc = np.empty(n, np.uint64)
            power, inverse = _power_tables(2 * k)
            step = len(power) - k
            for at in range(0, n, step):
                part = words[at : min(n, at + step) + k - 1]
                total = np.zeros(len(part) + 1, np.uint64)
                np.cumsum(part * power[: len(part)], out=total[1:])
                acc[at : at + step] = (total[k:] - total[:-k]) * inverse[: len(part) - k + 1]
        return mix64(acc + U(k))


def shingle_rows(data: np.ndarray, off: np.ndarray, k: int, lower: bool = True, also: tuple[int, ...] = ()):
    """For each row the sorted distinct hashes of its k-word shingles.

    A row of fewer than k words, but one at least, gives its whole sequence as
    the only shingle; a row without words gives an empty array.  Runs of the
    numbers of words in ``also`` are added to every row that has them.
    """
    for lo, hi in row_chunks(off):
        base = off[lo]
        starts, ends, first = word_table(data[base : off[hi]], off[lo : hi + 1] - base)
        words = word_hashes(data[base : off[hi]], starts, ends, lower)
        runs = run_hashes(words, k)
        more = [(w, run_hashes(words, w)) for w in also]
        for i in range(hi - lo):
            a, b = int(first[i]), int(first[i + 1])
            own = runs[a : b - k + 1] if b - a >= k else run_hashes(words[a:b], b - a) if b > a else np.zeros(0, np.uint64)
            short = [x[a : b - w + 1] for w, x in more if b - a >= w]
            yield np.unique(np.concatenate([own, *short]) if short else own)


def spare_name(taken: list[str], name: str) -> str:
    """``name``, lengthened until no column in ``taken`` has it (case aside)."""
    used = {t.lower() for t in taken}
    while name in used:
        name += "_"
    return name

"""Vectorised scans of Arrow text columns: words, word hashes and shingles without a Python loop over words.

Words are maximal runs without ``[\\x20\\x09-\\x0D]``; A-Z count as a-z. A word's 64-bit hash is a polynomial over random
byte values modulo 2**64, finished by a mixer; equal hashes are taken as equal words (for V distinct words about
V**2 / 2**65 pairs collide).
"""

from __future__ import annotations

import ctypes

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

BLOCK = 1 << 17
_SPACE = np.zeros(256, bool)
_SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
_BASE = 0x9E3779B97F4A7C15 | 5
_WORD_ALNUM = None


def mix(x: np.ndarray, seed: int = 0) -> np.ndarray:
    """A bijection of 64-bit values whose output bits all depend on all input bits."""
    with np.errstate(over="ignore"):
        x = x + np.uint64((0x9E3779B97F4A7C15 * (seed + 1)) & (2**64 - 1))
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return x ^ (x >> np.uint64(31))


def _byte_values() -> np.ndarray:
    v = mix(np.arange(256, dtype=np.uint64), 77)
    v[65:91] = v[97:123]
    return v


_VALUES = _byte_values()
_powers: dict[str, np.ndarray] = {"p": np.ones(1, np.uint64), "q": np.ones(1, np.uint64)}


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse modulo 2**64, for at least n positions; kept up to a few blocks' length."""
    if len(_powers["p"]) < n:
        size = max(n, 2 * BLOCK)
        tables = []
        for b in (_BASE, pow(_BASE, -1, 2**64)):
            t = np.full(size, b, np.uint64)
            t[0] = 1
            with np.errstate(over="ignore"):
                tables.append(np.multiply.accumulate(t))
        if size > 8 * BLOCK:
            return tables[0], tables[1]
        _powers["p"], _powers["q"] = tables
    return _powers["p"], _powers["q"]


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a string column (null: empty) and the n + 1 offsets of its rows."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = pc.fill_null(column, "")
    n = len(column)
    if n == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, off, data = column.buffers()
    off = np.frombuffer(off, np.int64 if wide else np.int32)[column.offset : column.offset + n + 1].astype(np.int64)
    data = np.frombuffer(data, np.uint8)[off[0] : off[-1]] if data is not None and off[-1] > off[0] else np.zeros(0, np.uint8)
    return data, off - off[0]


def tidy() -> None:
    """Hand freed memory back to the system: workers are reused, and all of an executor's share its budget."""
    pa.default_memory_pool().release_unused()
    if _trim is not None:
        _trim(0)


try:
    _trim = ctypes.CDLL(None).malloc_trim
except (OSError, AttributeError):  # another C library
    _trim = None


def pieces(batch: pa.RecordBatch, column: int, limit: int = 2 << 20):
    """The batch in slices of whole rows whose texts have about ``limit`` bytes, or one row."""
    sizes = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False)
    part = np.cumsum(sizes, dtype=np.int64) // limit
    cuts = [0, *(np.flatnonzero(np.diff(part)) + 1).tolist(), batch.num_rows]
    for a, b in zip(cuts[:-1], cuts[1:]):
        if b > a:
            yield batch.slice(a, b - a)
    tidy()


def _blocks(data: np.ndarray, off: np.ndarray, space: np.ndarray):
    """Cuts [a, b) of about BLOCK bytes that lie on white space or on a row's border."""
    a, n = 0, len(data)
    while a < n:
        b = a + BLOCK
        if b >= n:
            b = n
        else:
            border = int(off[np.searchsorted(off, b)])
            while b < border and not space[data[b]]:
                step = data[b : min(border, b + 4096)]
                hit = np.flatnonzero(space[step])
                b = b + int(hit[0]) if len(hit) else b + len(step)
        yield a, b
        a = b


class Words:
    """Words of a batch: ``hash``, byte ranges ``start``/``end``, and ``first[i]:first[i + 1]`` for the words of row i.

    ``prefix``: also the hash of the word's last ``prefix`` bytes, as ``tail``.
    """

    def __init__(self, column: pa.Array, space: np.ndarray = _SPACE, tail: int = 0):
        data, off = text_bytes(column)
        self.data, self.off = data, off
        starts, ends, hashes, tails = [], [], [], []
        with np.errstate(over="ignore"):
            for a, b in _blocks(data, off, space):
                d = data[a:b]
                sp = space[d]
                before = np.empty(b - a, bool)
                before[0], before[1:] = True, sp[:-1]
                inner = off[np.searchsorted(off, a, "left") : np.searchsorted(off, b, "left")] - a
                before[inner] = True
                after = np.empty(b - a, bool)
                after[-1], after[:-1] = True, sp[1:]
                after[inner[inner > 0] - 1] = True
                s = np.flatnonzero(before & ~sp)
                e = np.flatnonzero(after & ~sp) + 1
                p, q = _power_tables(b - a)
                c = np.empty(b - a + 1, np.uint64)
                c[0] = 0
                np.cumsum(_VALUES[d] * p[: b - a], out=c[1:])
                hashes.append((c[e] - c[s]) * q[s])
                if tail:
                    t = np.maximum(s, e - tail)
                    tails.append((c[e] - c[t]) * q[t])
                starts.append(s + a)
                ends.append(e + a)
        cat = lambda xs, kind: np.concatenate(xs) if xs else np.zeros(0, kind)
        self.start, self.end = cat(starts, np.int64), cat(ends, np.int64)
        with np.errstate(over="ignore"):
            self.hash = mix(cat(hashes, np.uint64) + (self.end - self.start).astype(np.uint64))
            self.tail = mix(cat(tails, np.uint64), 5) if tail else None
        self.first = np.searchsorted(self.start, off, "left")

    def row_of(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.first) - 1), np.diff(self.first))


def shingles(words: Words, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hashes of all k-word shingles in text order, the index of each one's first word, and row bounds.

    A row with 1 to k - 1 words has one shingle, its whole sequence; a row without words has none.
    """
    h, first = words.hash, words.first
    count = np.diff(first)
    n_sh = np.where(count >= k, count - k + 1, (count > 0).astype(np.int64))
    bounds = np.concatenate([[0], np.cumsum(n_sh)])
    at = np.arange(bounds[-1]) - np.repeat(bounds[:-1] - first[:-1], n_sh)
    length = np.minimum(np.repeat(count, n_sh), k)
    out = np.zeros(len(at), np.uint64)
    with np.errstate(over="ignore"):
        for j in range(k):
            use = length > j
            nxt = h[np.where(use, at + j, 0)] if len(h) else out
            out = np.where(use, mix(out * np.uint64(0xD6E8FEB86659FD93) + nxt, j), out)
    return out, at, bounds


def distinct_by_row(values: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct values of every row and the new row bounds."""
    out, n = [], [0]
    for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist()):
        v = np.sort(values[a:b])
        if len(v) > 1:
            keep = np.empty(len(v), bool)
            keep[0] = True
            np.not_equal(v[1:], v[:-1], out=keep[1:])
            v = v[keep]
        out.append(v)
        n.append(len(v))
    return (np.concatenate(out) if out else values[:0]), np.cumsum(n)

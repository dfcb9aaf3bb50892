"""Vectorised word hashing on Arrow text buffers.

A word is a run of bytes other than space and 0x09-0x0D; A-Z are lower-cased. Words of a whole block of
texts are hashed at once: prefix sums of ``byte * base**position`` modulo 2**64 give every word's polynomial,
which a finaliser then mixes. Nothing here depends on a process seed, so every executor agrees.

Long texts are whole, too, but are worked through in chunks of fixed size: beyond its bytes and a few numbers a word, a text
costs no memory, and nothing that follows its length stays when a task ends.
"""

from __future__ import annotations

import ctypes
import gc
from collections.abc import Callable, Iterator
from contextlib import suppress
from functools import lru_cache, wraps

import numpy as np
import pyarrow as pa

#: Text bytes that are cut into words together, unless one text is longer.
BLOCK_BYTES = 1 << 20
#: Bytes that are hashed together: the working memory beyond a block's bytes and its words follows this, not the text.
CHUNK = 1 << 17
BASE = np.uint64(0x9E3779B97F4A7C15)
INVERSE = np.uint64(pow(0x9E3779B97F4A7C15, -1, 1 << 64))
SEPARATOR = np.zeros(256, bool)
SEPARATOR[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
LOWER = np.arange(1, 257, dtype=np.uint64)
LOWER[ord("A") : ord("Z") + 1] += np.uint64(32)


def mix(x: np.ndarray, seed: int = 0) -> np.ndarray:
    """A 64-bit finaliser of full avalanche."""
    x = x + np.uint64((0x9E3779B97F4A7C15 * (seed + 1)) & 0xFFFFFFFFFFFFFFFF)
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


@lru_cache(1)
def powers() -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse, 0 to ``CHUNK``."""
    up, down = np.full(CHUNK + 1, BASE), np.full(CHUNK + 1, INVERSE)
    up[0] = down[0] = 1
    return np.multiply.accumulate(up), np.multiply.accumulate(down)


def polynomials(values: np.ndarray, start: np.ndarray, end: np.ndarray, take=lambda x: x) -> np.ndarray:
    """Sum of ``take(values)[start + j] * base**j`` for each of the ascending slices ``start:end``, chunk by chunk.

    Chunks begin and end with a slice; a slice longer than a chunk is added up from several.
    """
    up, down = powers()
    out = np.empty(len(start), np.uint64)
    i = 0
    while i < len(start):
        at = int(start[i])
        j = int(np.searchsorted(end, at + CHUNK, "right"))
        if j <= i:
            total, scale = np.uint64(0), np.uint64(1)
            for a in range(at, int(end[i]), CHUNK):
                part = take(values[a : min(a + CHUNK, int(end[i]))])
                with np.errstate(over="ignore"):
                    total += scale * (part * up[: len(part)]).sum(dtype=np.uint64)
                    scale *= up[CHUNK]
            out[i] = total
            i += 1
            continue
        part = take(values[at : int(end[j - 1])])
        total = np.zeros(len(part) + 1, np.uint64)
        np.cumsum(part * up[: len(part)], out=total[1:])
        out[i:j] = (total[end[i:j] - at] - total[start[i:j] - at]) * down[start[i:j] - at]
        i = j
    return out


class Block:
    """A block of whole texts: bytes, text limits, and its words.

    ``data`` are the concatenated UTF-8 bytes; text i is ``data[at[i]:at[i + 1]]`` and its words are
    ``first[i]`` to ``first[i + 1]`` of ``start``/``end``/``word`` (hash).
    """

    def __init__(self, data: np.ndarray, at: np.ndarray, separator: np.ndarray = SEPARATOR):
        self.data, self.at = data, at
        kind = np.int32 if len(data) < 1 << 31 else np.int64
        starts, ends = [np.zeros(0, kind)], [np.zeros(0, kind)]
        edges, n = np.unique(at), len(data)
        for a in range(0, n, 8 * CHUNK):
            b = min(a + 8 * CHUNK, n)
            # one byte more on either side tells whether a word goes on
            lo, hi = max(a - 1, 0), min(b + 1, n)
            word = ~separator[data[lo:hi]]
            inner = edges[np.searchsorted(edges, lo, "right") : np.searchsorted(edges, hi)] - lo
            first, last = word.copy(), word.copy()
            first[1:] &= ~word[:-1]
            last[:-1] &= ~word[1:]
            first[inner] = word[inner]
            last[inner - 1] = word[inner - 1]
            starts.append((np.flatnonzero(first[a - lo : b - lo]) + a).astype(kind))
            ends.append((np.flatnonzero(last[a - lo : b - lo]) + (a + 1)).astype(kind))
        self.start, self.end = np.concatenate(starts), np.concatenate(ends)
        self.first = np.searchsorted(self.start, at)

    @property
    def counts(self) -> np.ndarray:
        return np.diff(self.first)

    def hashes(self, lower: np.ndarray = LOWER, prefix: int = 0) -> np.ndarray:
        """Of every word, or with ``prefix`` of the first bytes of every word that is longer."""
        start, end = self.start, self.end
        if prefix:
            start = start[end - start > prefix]
            end = start + np.int32(prefix)
        poly = polynomials(self.data, start, end, lower.__getitem__)
        poly ^= (end - start).astype(np.uint64) << np.uint64(56)
        return mix(poly)


def text_blocks(column: pa.Array, limit: int | None = None) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Slices (from, to, bytes, limits) of a string column, whole texts only; null is empty.

    A text longer than ``limit`` is a block of its own.
    """
    limit = limit or BLOCK_BYTES
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_string()).fill_null("")
    n = len(column)
    if not n:
        return
    _, offsets, values = column.buffers()
    offsets = np.frombuffer(offsets, np.int64)[column.offset : column.offset + n + 1]
    values = np.frombuffer(values, np.uint8) if values is not None and values.size else np.zeros(0, np.uint8)
    i = 0
    while i < n:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + limit, "right")) - 1)
        yield i, j, values[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]
        i = j


def shingles(word: np.ndarray, first: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all runs of ``size`` words of each text, with repeats, and each text's limits.

    A text of fewer words gives its whole sequence as one; a text without words gives none.
    """
    count = np.diff(first)
    made = np.where(count == 0, 0, np.maximum(count - size + 1, 1))
    limits = np.concatenate([[0], np.cumsum(made)])
    out = np.empty(limits[-1], np.uint64)
    for i in np.flatnonzero((count > 0) & (count < size)):
        h = np.array([count[i] + 0x51], np.uint64)
        for w in word[first[i] : first[i + 1]]:
            h = mix(h * STEP_FACTOR + w, 7)
        out[limits[i]] = h[0]
    long = np.flatnonzero(count >= size)
    shift = first[long] - limits[long]
    for c in range(0, len(word) - size + 1, CHUNK):
        # every run that begins in the chunk, also those that cross into the next text
        rolled = rolling(word[c : c + CHUNK + size - 1], size)
        lo = np.maximum(first[long], c)
        hi = np.minimum(first[long] + made[long], c + len(rolled))
        for a, b, s in zip(*(x[lo < hi] for x in (lo, hi, shift))):
            out[a - s : b - s] = rolled[a - c : b - c]
    return out, limits


STEP_FACTOR = np.uint64(0xD6E8FEB86659FD93)


def rolling(word: np.ndarray, size: int) -> np.ndarray:
    """Mixed hash of the ``size`` words from each place that has as many after it."""
    n = len(word) - size + 1
    rolled = word[:n].copy()
    for k in range(1, size):
        rolled *= STEP_FACTOR
        rolled += word[k : n + k]
    return mix(rolled)


def distinct(values: np.ndarray, limits: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct values of each slice ``limits[i]:limits[i + 1]``; ``values`` are sorted in place."""
    parts = []
    for a, b in zip(limits[:-1], limits[1:]):
        part = values[a:b]
        part.sort()
        new = np.ones(len(part), bool)
        np.not_equal(part[1:], part[:-1], out=new[1:])
        parts.append(part if new.all() else part[new])
    if len(parts) == 1:
        return parts[0], np.array([0, len(parts[0])])
    return (np.concatenate(parts) if parts else values[:0]), np.concatenate([[0], np.cumsum([len(p) for p in parts])]).astype(np.int64)


def fold(values: np.ndarray, limits: np.ndarray, make: Callable, ufunc: np.ufunc, out: np.ndarray) -> np.ndarray:
    """``out[i] = ufunc(out[i], *make(values[limits[i]:limits[i + 1]]))``, chunk by chunk."""
    for c in range(0, len(values), CHUNK // 4):
        part = make(values[c : c + CHUNK // 4])
        inside = limits[np.searchsorted(limits, c, "right") : np.searchsorted(limits, c + len(part))]
        at = np.unique(np.concatenate([[0], inside - c]))
        owner = np.searchsorted(limits, c + at, "right") - 1
        out[owner] = ufunc(out[owner], ufunc.reduceat(part, at))
    return out


def release() -> None:
    """Give freed memory back to the machine."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    with suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


def tidy(run: Callable) -> Callable:
    """A batch function after whose last batch the worker, which serves later tasks too, keeps no freed memory."""

    @wraps(run)
    def wrapped(batches):
        yield from run(batches)
        release()

    return wrapped

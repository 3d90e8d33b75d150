"""Words of Arrow text columns as arrays: boundaries and 64-bit hashes without a Python object per word.

A word is a maximal run of bytes of a class; all separators here are ASCII, so UTF-8 text can be cut by
bytes. The hash of a word is a polynomial over a random table of its bytes, taken from one running sum,
then mixed. Work goes in pieces of bounded size, so memory does not grow with a document.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Bytes of text that are hashed at once, and bytes of rows that are handed out together.
PIECE, BLOCK = 1 << 19, 1 << 22
U = np.uint64
_BASE = 0x9E3779B97F4A7C15
_TABLE = np.random.default_rng(7).integers(1, 2**63, 256, dtype=np.uint64) * U(2) + U(1)


@dataclass(frozen=True)
class WordClass:
    """Which bytes belong to words, and whether A-Z count as a-z."""

    inside: np.ndarray
    table: np.ndarray
    lower: np.ndarray


def _word_class(separators: set[int], lower: bool) -> WordClass:
    inside = np.ones(256, bool)
    low = np.arange(256, dtype=np.uint8)
    if lower:
        low[65:91] += 32
    for b in separators:
        inside[b] = False
    return WordClass(inside, _TABLE[low], low)


_SPACE = {0x20, *range(0x09, 0x0E)}
#: Runs of anything but space and 0x09-0x0D, as written and with A-Z lowered.
SPACED, SPACED_LOWER = _word_class(_SPACE, False), _word_class(_SPACE, True)
#: Letters, digits and everything beyond ASCII, A-Z lowered.
ALNUM_LOWER = _word_class({*range(0x00, 0x30), *range(0x3A, 0x41), *range(0x5B, 0x61), *range(0x7B, 0x80)}, True)


class _Powers:
    up = np.ones(1, np.uint64)
    down = np.ones(1, np.uint64)

    @classmethod
    def to(cls, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(cls.up) < n:
            step = np.full(n, _BASE, np.uint64)
            step[0] = 1
            cls.up = np.multiply.accumulate(step)
            step[1:] = pow(_BASE, -1, 1 << 64)
            cls.down = np.multiply.accumulate(step)
        return cls.up, cls.down


def mix(h: np.ndarray) -> np.ndarray:
    """Finaliser of splitmix64: every input bit reaches every output bit."""
    h = h ^ (h >> U(30))
    h = h * U(0xBF58476D1CE4E5B9)
    h ^= h >> U(27)
    h *= U(0x94D049BB133111EB)
    h ^= h >> U(31)
    return h


def text_rows(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """``(bytes, offsets)`` of a text column; nulls are empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if pa.types.is_large_string(column.type):
        width = np.int64
    else:
        column, width = column.cast(pa.string()), np.int32
    if column.null_count:
        column = pc.fill_null(column, "")
    buffers = column.buffers()
    if not len(column):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    offsets = np.frombuffer(buffers[1], width)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    data = np.frombuffer(buffers[2], np.uint8) if buffers[2] is not None else np.zeros(0, np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def blocks(column: pa.Array, limit: int = BLOCK) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Row ranges ``(from, to, bytes, offsets)`` of at most ``limit`` bytes, or of one longer row."""
    data, offsets = text_rows(column)
    lo, n = 0, len(offsets) - 1
    while lo < n:
        hi = max(lo + 1, int(np.searchsorted(offsets, offsets[lo] + limit, "right")) - 1)
        yield lo, hi, data[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo]
        lo = hi


@dataclass
class Words:
    """Words of a block: first byte, byte after the last, hash, and the first word of each row."""

    start: np.ndarray
    end: np.ndarray
    hash: np.ndarray | None
    split: np.ndarray

    def __len__(self) -> int:
        return len(self.start)


def bounds(data: np.ndarray, offsets: np.ndarray, kind: WordClass) -> Words:
    """Words without their hashes."""
    n = len(data)
    if not n:
        none = np.zeros(0, np.int64)
        return Words(none, none, None, np.zeros(len(offsets), np.int64))
    inside = kind.inside[data]
    first, last = inside.copy(), inside.copy()
    first[1:] &= ~inside[:-1]
    last[:-1] &= ~inside[1:]
    cut = offsets[(offsets > 0) & (offsets < n)]
    first[cut] = inside[cut]
    last[cut - 1] = inside[cut - 1]
    start, end = np.flatnonzero(first), np.flatnonzero(last) + 1
    return Words(start, end, None, np.searchsorted(start, offsets))


def words(data: np.ndarray, offsets: np.ndarray, kind: WordClass) -> Words:
    """Words with hashes, a piece of whole words at a time."""
    found = bounds(data, offsets, kind)
    out, at = np.empty(len(found), np.uint64), 0
    while at < len(found):
        base = found.start[at]
        to = max(at + 1, int(np.searchsorted(found.end, base + PIECE, "right")))
        s, e = found.start[at:to] - base, found.end[at:to] - base
        n = int(e[-1])
        up, down = _Powers.to(max(n, PIECE) + 1)
        sums = np.zeros(n + 1, np.uint64)
        np.cumsum(kind.table[data[base : base + n]] * up[:n], out=sums[1:])
        out[at:to] = mix((sums[e] - sums[s]) * down[s] + (e - s).astype(np.uint64))
        at = to
    found.hash = out
    return found


def shingles(found: Words, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of runs of ``size`` words inside rows and the first of each row; a shorter row is one run."""
    h, split = found.hash, found.split
    count = np.diff(split)
    made = np.where(count >= size, count - size + 1, (count > 0).astype(np.int64))
    out_split = np.concatenate([[0], np.cumsum(made)])
    n = len(h)
    full = np.zeros(max(0, n - size + 1), np.uint64)
    for k in range(size):
        full = mix(full * U(_BASE) + h[k : n - size + 1 + k]) if len(full) else full
    out = np.empty(out_split[-1], np.uint64)
    long = np.flatnonzero(count >= size)
    at = np.repeat(split[long] - out_split[long], made[long]) + _ranges(out_split[long], made[long])
    out[_ranges(out_split[long], made[long])] = full[at]
    for r in np.flatnonzero((count > 0) & (count < size)):
        v = np.full(1, count[r], np.uint64) * U(0xD6E8FEB86659FD93)
        for x in h[split[r] : split[r + 1]]:
            v = mix(v * U(_BASE) + x)
        out[out_split[r]] = v[0]
    return out, out_split


def _ranges(start: np.ndarray, length: np.ndarray) -> np.ndarray:
    """All of ``start[i] .. start[i] + length[i] - 1``, one after the other."""
    total = int(length.sum())
    if not total:
        return np.zeros(0, np.int64)
    return np.arange(total) + np.repeat(start - np.concatenate([[0], np.cumsum(length)[:-1]]), length)

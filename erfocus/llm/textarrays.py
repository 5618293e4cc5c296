"""Words of many texts at once, as numpy arrays over Arrow string buffers.

No text is decoded: words are byte ranges of the UTF-8 buffer, hashes are wrapped 64-bit sums.
Texts are taken in slices of a megabyte, so the arrays stay small whatever the batch holds;
one very long text makes its own slice.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

SLICE_BYTES = 1 << 20
U = np.uint64
_BASE = 0x9E3779B97F4A7C15
_MASK = (1 << 64) - 1
_BLOCK = 4096

#: Byte classes of the two word definitions and the A-Z lower-casing.
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
LOWER_BYTES = LOWER.tobytes()
NOT_SPACE = np.ones(256, dtype=bool)
NOT_SPACE[[9, 10, 11, 12, 13, 32]] = False
ALNUM = np.zeros(256, dtype=bool)
ALNUM[48:58] = ALNUM[65:91] = ALNUM[97:123] = ALNUM[128:] = True


def _powers(base: int, n: int) -> np.ndarray:
    out = np.empty(n, dtype=U)
    x = 1
    for i in range(n):
        out[i] = x
        x = x * base & _MASK
    return out


_LOW = _powers(_BASE, _BLOCK)


def mix(h: np.ndarray, salt: int = 0) -> np.ndarray:
    """A bijective finaliser of 64-bit words."""
    h = h + U(salt & _MASK)
    h = (h ^ (h >> U(33))) * U(0xFF51AFD7ED558CCD)
    h = (h ^ (h >> U(33))) * U(0xC4CEB9FE1A85EC53)
    return h ^ (h >> U(33))


def slices(column: pa.Array, size: int = SLICE_BYTES) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, end row, bytes, offsets) of consecutive rows; null is the empty text."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_binary()).fill_null(b"")
    n = len(column)
    if not n:
        return
    _, where, data = column.buffers()
    where = np.frombuffer(where, dtype=np.int64)[column.offset : column.offset + n + 1]
    data = np.frombuffer(data, dtype=np.uint8) if data is not None else np.empty(0, dtype=np.uint8)
    row = 0
    while row < n:
        end = max(row + 1, int(np.searchsorted(where, where[row] + size, side="right")) - 1)
        yield row, end, data[where[row] : where[end]], where[row : end + 1] - where[row]
        row = end


@dataclass
class Words:
    """start, end: byte ranges; text: the row each word is of; first[r]: index of row r's first word."""

    data: np.ndarray
    start: np.ndarray
    end: np.ndarray
    text: np.ndarray
    first: np.ndarray

    @property
    def counts(self) -> np.ndarray:
        return np.diff(self.first)


def words(data: np.ndarray, offsets: np.ndarray, kind: np.ndarray) -> Words:
    """Maximal runs of bytes of a kind, broken at the ends of texts; A-Z lower-cased."""
    data = LOWER[data]
    on = kind[data]
    edge = offsets[(offsets > 0) & (offsets < len(data))]
    before = np.empty_like(on)
    before[:1] = False
    before[1:] = on[:-1]
    before[edge] = False
    after = np.empty_like(on)
    after[-1:] = False
    after[:-1] = on[1:]
    after[edge - 1] = False
    start = np.flatnonzero(on & ~before)
    end = np.flatnonzero(on & ~after) + 1
    first = np.searchsorted(start, offsets)
    text = np.repeat(np.arange(len(offsets) - 1), np.diff(first))
    return Words(data, start, end, text, first)


def word_hashes(w: Words) -> np.ndarray:
    """A 64-bit hash of each word's bytes."""
    if not len(w.start):
        return np.empty(0, dtype=U)
    length = w.end - w.start
    at = np.cumsum(length) - length
    total = int(at[-1] + length[-1])
    inside = np.arange(total) - np.repeat(at, length)
    value = w.data[np.repeat(w.start, length) + inside].astype(U) + U(1)
    value *= _LOW[inside & (_BLOCK - 1)]
    longest = int(length.max())
    if longest > _BLOCK:
        value *= _powers(pow(_BASE, _BLOCK, 1 << 64), longest // _BLOCK + 1)[inside // _BLOCK]
    return mix(np.add.reduceat(value, at), 0) ^ mix(length.astype(U), 7)


def gram_hashes(h: np.ndarray, n: int) -> np.ndarray:
    """Hash of each n consecutive words, without regard to the ends of texts."""
    m = len(h) - n + 1
    if m <= 0:
        return np.empty(0, dtype=U)
    if n <= 16:
        out = h[:m].copy()
        for j in range(1, n):
            out *= U(_BASE)
            out += h[j : j + m]
        return mix(out, n)
    # Horner's sums of a long window, carried on by blocks of 16 words.
    whole, rest = divmod(n, 16)
    block, step = gram_hashes(h, 16), U(0xD6E8FEB86659FD93)
    out = block[:m].copy()
    for j in range(1, whole):
        out *= step
        out += block[16 * j : 16 * j + m]
    if rest:
        out *= step
        out += gram_hashes(h, rest)[16 * whole : 16 * whole + m]
    return mix(out, n)


def whole(w: Words, n: int) -> np.ndarray:
    """Which windows of n words lie in one text."""
    m = len(w.text) - n + 1
    return w.text[:m] == w.text[n - 1 :] if m > 0 else np.empty(0, dtype=bool)


def per_text(values: np.ndarray, w: Words) -> np.ndarray:
    """Sums of a value of each word, by text."""
    total = np.concatenate([[0], np.cumsum(values)])
    return total[w.first[1:]] - total[w.first[:-1]]


def settled(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Smallest member of each of 0..n-1's component under links a[i]-b[i]."""
    label = np.arange(n)
    while len(a):
        la, lb = label[a], label[b]
        open_ = la != lb
        if not open_.any():
            break
        a, b, la, lb = a[open_], b[open_], la[open_], lb[open_]
        low = np.minimum(la, lb)
        np.minimum.at(label, la, low)
        np.minimum.at(label, lb, low)
        while not np.array_equal(label, hop := label[label]):
            label = hop
    return label


def passages(w: Words, first: np.ndarray, end: np.ndarray) -> pa.Array:
    """The bytes of words first to end of each pair, with what lies between them, or one space if that is long."""
    a, b = w.start[first], w.end[end - 1]
    length = np.concatenate([[0], np.cumsum(w.end - w.start)])
    if len(first) and int((b - a - (length[end] - length[first]) - (end - first)).max()) > 64:
        return pa.array([b" ".join(w.data[w.start[k] : w.end[k]].tobytes() for k in range(i, j)) for i, j in zip(first.tolist(), end.tolist(), strict=True)], pa.binary())
    offsets = np.concatenate([[0], np.cumsum(b - a)])
    where = np.arange(int(offsets[-1])) - np.repeat(offsets[:-1] - a, b - a)
    return pa.Array.from_buffers(pa.binary(), len(first), [None, pa.py_buffer(offsets.astype(np.int32)), pa.py_buffer(w.data[where])])


def distinct_hashes(w: Words) -> np.ndarray:
    """Hashes of words, equal only for words of equal bytes: where that fails, words are numbered instead."""
    h = word_hashes(w)
    if len(h) < 2:
        return h
    order = np.argsort(h, kind="stable")
    length = w.end - w.start
    same = np.flatnonzero(h[order[1:]] == h[order[:-1]])
    a, b = order[same], order[same + 1]
    fine = bool((length[a] == length[b]).all())
    step = 1 << 18
    for k in range(0, len(a) if fine else 0, step):
        x, y, n = w.start[a[k : k + step]], w.start[b[k : k + step]], length[a[k : k + step]]
        inside = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
        if not np.array_equal(w.data[np.repeat(x, n) + inside], w.data[np.repeat(y, n) + inside]):
            fine = False
            break
    if fine:
        return h
    known: dict[bytes, int] = {}
    return np.array([known.setdefault(w.data[s:e].tobytes(), len(known) + 1) for s, e in zip(w.start, w.end, strict=True)], dtype=U)

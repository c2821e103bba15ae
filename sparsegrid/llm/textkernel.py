"""Vectorised word hashing over Arrow string batches.

Every operator of this subpackage that has to look at all words of all texts
shares this kernel.  A batch is processed in slices of about one megabyte of
text, so the working memory is bounded however long the batch is; a text that
is longer than a slice is hashed piece by piece, cut only between words, so
whole texts are always covered.

The hash of a word is a polynomial over randomly tabulated bytes, taken as the
difference of two running sums modulo 2**64 and then mixed: one pass of array
operations, no Python work per word.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

SLICE_BYTES = 1 << 20
_BASE = 0x9E3779B97F4A7C15 | 1
_INVERSE = pow(_BASE, -1, 1 << 64)


def _byte_values() -> np.ndarray:
    return mix64(np.arange(1, 257, dtype=np.uint64) * np.uint64(0xD1342543DE82EF95))


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser on 64-bit words (xor-shift and multiply)."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _fold_table() -> np.ndarray:
    t = np.arange(256, dtype=np.uint8)
    t[65:91] += 32
    return t


FOLD = _fold_table()
_VALUES = _byte_values()

#: Bytes that belong to a word when words are separated by ASCII white space.
SPACED = np.ones(256, dtype=bool)
SPACED[[0x20, *range(0x09, 0x0E)]] = False
#: Bytes that belong to a word made of digits, letters and everything beyond ASCII.
ALNUM = np.zeros(256, dtype=bool)
ALNUM[0x30:0x3A] = ALNUM[0x61:0x7B] = ALNUM[0x80:] = True

_powers: list[np.ndarray] = []


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse, for at least n positions."""
    if not _powers or len(_powers[0]) < n:
        size = max(n, SLICE_BYTES + 1)
        _powers[:] = []
        for b in (_BASE, _INVERSE):
            p = np.full(size, np.uint64(b), dtype=np.uint64)
            p[0] = 1
            _powers.append(np.cumprod(p, dtype=np.uint64))
    return _powers[0], _powers[1]


def hash_words(data: np.ndarray, starts_at: np.ndarray, letters: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hashes, first bytes and ends of all words of the byte array ``data``.

    ``starts_at`` holds positions at which a new text begins: no word crosses them.
    A-Z are lower-cased first.
    """
    n = len(data)
    folded = FOLD[data]
    inside = letters[folded]
    first = inside.copy()
    first[1:] &= ~inside[:-1]
    cut = starts_at[(starts_at > 0) & (starts_at < n)]
    first[cut] = inside[cut]
    last = inside.copy()
    last[:-1] &= ~inside[1:]
    last[cut - 1] = inside[cut - 1]
    s = np.flatnonzero(first)
    e = np.flatnonzero(last) + 1
    up, down = _power_tables(n + 1)
    run = np.empty(n + 1, dtype=np.uint64)
    run[0] = 0
    np.cumsum(_VALUES[folded] * up[:n], dtype=np.uint64, out=run[1:])
    h = mix64((run[e] - run[s]) * down[s] + (e - s).astype(np.uint64))
    return h, s, e


def _buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Offsets (one more than texts, nulls empty) and bytes of a string column."""
    column = column.cast(pa.large_binary()) if not pa.types.is_large_binary(column.type) else column
    if column.null_count:
        column = column.fill_null(b"")
    _, off, body = column.buffers()
    offsets = np.frombuffer(off, dtype=np.int64)[column.offset : column.offset + len(column) + 1]
    return offsets, np.frombuffer(body, dtype=np.uint8) if body is not None and body.size else np.zeros(0, np.uint8)


def _pieces(data: np.ndarray, a: int, b: int, letters: np.ndarray) -> Iterator[tuple[int, int]]:
    """Cuts the bytes a..b between words into pieces of about one slice."""
    while b - a > SLICE_BYTES:
        cut = a + SLICE_BYTES
        while cut < b:
            gaps = np.flatnonzero(~letters[FOLD[data[cut : cut + 65536]]])
            if len(gaps):
                cut = min(b, cut + int(gaps[0]))
                break
            cut = min(b, cut + 65536)
        yield a, cut
        a = cut
    yield a, b


def words_of(column: pa.Array, letters: np.ndarray) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """Yields (index of the first text, word bounds per text, word hashes) slice by slice.

    ``bounds`` has one entry more than the slice has texts; text i of the slice
    owns ``hashes[bounds[i]:bounds[i + 1]]``.  Null texts have no words.
    """
    offsets, data = _buffers(column)
    i, n = 0, len(offsets) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + SLICE_BYTES, side="right")) - 1)
        a, b = int(offsets[i]), int(offsets[j])
        if j == i + 1 and b - a > SLICE_BYTES:
            parts = [hash_words(data[x:y], np.zeros(0, np.int64), letters)[0] for x, y in _pieces(data, a, b, letters)]
            h = np.concatenate(parts)
            yield i, np.array([0, len(h)]), h
        else:
            h, s, _ = hash_words(data[a:b], offsets[i:j] - a, letters)
            yield i, np.searchsorted(s, offsets[i : j + 1] - a), h
        i = j

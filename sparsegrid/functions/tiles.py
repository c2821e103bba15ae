"""Blocks of a product in Arrow batches: dense tiles where blocks are small and nearly full, strips of rows elsewhere."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from sparsegrid.model import SparseMatrix

_DENSE = 1 << 21  # places of a dense tile
_STRIP = 1 << 19  # elementary products that a strip of several rows makes


def _dense(rows: np.ndarray, pages: np.ndarray, x: np.ndarray, cols: np.ndarray, back: np.ndarray, y: np.ndarray, shape: tuple[int, int, int]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """One tile: (row, col, val) of the product of two dense arrays."""
    left, right = np.zeros((shape[0], shape[1])), np.zeros((shape[1], shape[2]))
    np.add.at(left, (rows, pages), x)
    np.add.at(right, (back, cols), y)
    p = np.rint(left @ right).astype(np.int64)
    r, c = np.nonzero(p)
    yield r, c, p[r, c]


def _strips(rows: np.ndarray, pages: np.ndarray, x: np.ndarray, cols: np.ndarray, back: np.ndarray, y: np.ndarray, shape: tuple[int, int, int], times: Callable, plus: np.ufunc) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """The same from the entries alone, some rows at a time: what is in memory is the block's entries and one strip's products.

    A strip ends before the row that would take it beyond ``_STRIP`` products; a
    row of more, at most the entries of the right factor's block, is one strip.
    """
    order, held = np.argsort(rows, kind="stable"), np.argsort(back, kind="stable")
    rows, pages, x, cols, y = rows[order], pages[order], x[order], cols[held], y[held]
    ends = np.cumsum(np.bincount(back, minlength=shape[1]))
    many = np.bincount(back, minlength=shape[1])
    count, first = many[pages], (ends - many)[pages]
    made = np.concatenate(([0], np.cumsum(count)))
    bounds = np.flatnonzero(np.diff(rows, prepend=-1, append=shape[0]))  # the first entry of each row, and the end
    a = 0
    while a < len(bounds) - 1:
        b = max(a + 1, int(np.searchsorted(made[bounds], made[bounds[a]] + _STRIP, side="right")) - 1)
        i, j = bounds[a], bounds[b]
        a, n = b, made[j] - made[i]
        if not n:
            continue
        of = count[i:j]
        at = np.arange(n) + np.repeat(first[i:j] - (made[i:j] - made[i]), of)
        key = np.repeat(rows[i:j], of).astype(np.int64) * shape[2] + cols[at]
        val = times(np.repeat(x[i:j], of), y[at])
        place = np.argsort(key, kind="stable")
        key = key[place]
        starts = np.flatnonzero(np.diff(key, prepend=-1))
        yield key[starts] // shape[2], key[starts] % shape[2], plus.reduceat(val[place], starts)


def _block(table: pa.Table, times: Callable, fold: Callable | None, zero: object) -> Iterator[pa.RecordBatch]:
    """The product of one (block row, block column): S and T entries told apart by ``side``."""
    side, i, k, v = (table.column(c).to_numpy() for c in ("side", "outer", "page", "val"))
    shared = np.intersect1d(k[side == 0], k[side == 1])
    ids, place, page, val = [], [], [], []
    for s in (0, 1):
        mine = np.flatnonzero(side == s)
        at = np.searchsorted(shared, k[mine])
        met = np.flatnonzero(shared[np.minimum(at, max(len(shared) - 1, 0))] == k[mine]) if len(shared) else mine[:0]
        u, p = np.unique(i[mine][met], return_inverse=True)
        ids, place, page, val = [*ids, u], [*place, p], [*page, at[met]], [*val, v[mine][met]]
    if not len(shared):
        return
    del table, side, i, k, v, mine, at, met, u, p  # the strips need the entries only once
    shape = len(ids[0]), len(shared), len(ids[1])
    most = int(np.abs(val[0]).max()) * int(np.abs(val[1]).max())
    if fold is None and most * len(shared) < 1 << 53 and max(shape[0] * shape[1], shape[1] * shape[2], shape[0] * shape[2]) <= _DENSE:
        found = _dense(place[0], page[0], val[0], place[1], page[1], val[1], shape)
    else:
        if fold is not None or most * len(shared) >= 1 << 63:  # Python's numbers do not overflow
            val = [x.astype(object) for x in val] if most >= 1 << 63 or fold is None else val
        plus = np.add if fold is None else np.frompyfunc(fold, 2, 1)
        found = _strips(place[0], page[0], val[0], place[1], page[1], val[1], shape, times, plus)
    for r, c, p in found:
        kept = np.flatnonzero(p != zero)
        for a in range(0, len(kept), 1 << 16):
            part = kept[a : a + (1 << 16)]
            yield pa.RecordBatch.from_arrays([pa.array(ids[0][r[part]]), pa.array(ids[1][c[part]]), pa.array(p[part], pa.int64())], ["row", "col", "val"])


def _packed(key: np.ndarray, val: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Keys in order and the sums of their values, without sums of zero."""
    place = np.argsort(key, kind="stable")
    key = key[place]
    starts = np.flatnonzero(np.diff(key, prepend=-1))
    val = np.add.reduceat(val[place], starts) if len(starts) else val
    kept = np.flatnonzero(val != 0)
    return key[starts][kept], val[kept]


def _bilinear_block(table: pa.Table, scheme: list) -> Iterator[pa.RecordBatch]:
    """One block of the seven-product scheme: the signed factors, their products and the signed sums of those, some pairs of rows at a time.

    A strip of pairs of rows takes all its products before it is left, so no
    product is ever stored.  Where products are many for the places of the
    strip they are summed in dense arrays, elsewhere by sorting.
    """
    side, outer, page, val = (table.column(c).to_numpy() for c in ("side", "outer", "page", "val"))
    del table
    half, odd, ids = outer >> 1, (outer & 1).astype(np.int8), []
    shared, place = np.unique(page >> 1, return_inverse=True)
    odd_page, mine = (page & 1).astype(np.int8), [np.flatnonzero(side == s) for s in (0, 1)]
    if not len(mine[0]) or not len(mine[1]):
        return
    at = []
    for m in mine:
        u, k = np.unique(half[m], return_inverse=True)
        ids, at = [*ids, u], [*at, k]
    most = (2 * int(np.abs(val[mine[0]]).max())) * (2 * int(np.abs(val[mine[1]]).max())) * len(shared) * len(scheme)
    val = val.astype(object) if most >= 1 << 63 else val  # Python's numbers do not overflow
    wide, pages = len(ids[1]), len(shared)
    left, right = [], []
    for ps, pt, _ in scheme:
        for out, parts, m, place_of, s in ((left, ps, mine[0], at[0], 0), (right, pt, mine[1], at[1], 1)):
            keys, vals = [], []
            for i, j, sign in parts:  # a block of T has its pages as rows
                met = np.flatnonzero((odd[m] == (j if s else i)) & (odd_page[m] == (i if s else j)))
                keys.append(place[m][met] * wide + place_of[met] if s else place_of[met] * pages + place[m][met])
                vals.append(sign * val[m][met])
            out.append(_packed(np.concatenate(keys), np.concatenate(vals)))
    right = [(key % wide, y, np.concatenate(([0], np.cumsum(np.bincount(key // wide, minlength=pages))))) for key, y in right]
    left = [(key // pages, key % pages, x) for key, x in left]
    count = [ends[k + 1] - ends[k] for (_, k, _), (_, _, ends) in zip(left, right, strict=True)]
    made = np.concatenate(([0], np.cumsum(sum(np.bincount(r, of, len(ids[0])) for (r, _, _), of in zip(left, count, strict=True)))))
    del side, outer, page, half, odd, place, odd_page, mine, at, val
    dense = most < 1 << 53 and made[-1] * 16 >= len(ids[0]) * wide
    a = 0
    while a < len(ids[0]):
        b = max(a + 1, int(np.searchsorted(made, made[a] + _STRIP, side="right")) - 1)
        b = min(b, a + max(1, _DENSE // 4 // wide)) if dense else b
        start, rows = a, b - a
        a = b
        if made[b] == made[start]:
            continue
        four = [np.zeros(rows * wide) for _ in range(4)] if dense else None
        keys, vals = [], []
        for (r, k, x), (c, y, ends), of, (_, _, goes) in zip(left, right, count, scheme, strict=True):
            i, j = np.searchsorted(r, (start, b))
            n = of[i:j]
            if not n.sum():
                continue
            before = np.cumsum(n) - n
            where = np.arange(n.sum()) + np.repeat(ends[k[i:j]] - before, n)
            key = np.repeat((r[i:j] - start) * wide, n) + c[where]
            product = np.repeat(x[i:j], n) * y[where]
            if dense:
                made_here = np.bincount(key, product, rows * wide)
            else:
                key, product = _packed(key, product)
            for gi, gj, sign in goes:
                if dense:
                    np.add(four[2 * gi + gj], sign * made_here, out=four[2 * gi + gj])
                else:
                    keys.append(4 * key + 2 * gi + gj)
                    vals.append(sign * product)
        if dense:
            found = [(4 * (f := np.flatnonzero(four[q])) + q, four[q][f].astype(np.int64)) for q in range(4)]
        else:
            found = [_packed(np.concatenate(keys), np.concatenate(vals))] if keys else []
        for key, total in found:
            for i in range(0, len(key), 1 << 16):
                at_key, part = key[i : i + (1 << 16)], total[i : i + (1 << 16)]
                row = 2 * ids[0][start + at_key // 4 // wide] + at_key % 4 // 2
                yield pa.RecordBatch.from_arrays([pa.array(row), pa.array(2 * ids[1][at_key // 4 % wide] + at_key % 2), pa.array(part, pa.int64())], ["row", "col", "val"])


def bilinear_multiply(s: SparseMatrix, t: SparseMatrix, scheme: list, side: int | None = None) -> SparseMatrix:
    """S T by a scheme of signed products on 2 x 2 blocks of odd and even ids, in ``side`` ** 2 blocks that each make their part of the result alone.

    A pair of rows 2 r and 2 r + 1 goes to one block row, a pair of columns to
    one block column, so all products that a place of the result sums are made
    in one task and none is exchanged.  By default a block takes about two
    million entries.
    """
    side = side or max(4, -(-(s.nnz() + t.nnz()) >> 21))
    hand = lambda c: F.pmod(F.xxhash64(F.shiftright(c, 1)), F.lit(side)).cast("int")
    free = F.explode(F.sequence(F.lit(0), F.lit(side - 1)))
    left = s.df.select(hand("row").alias("bi"), free.alias("bj"), F.lit(0).cast("byte").alias("side"), F.col("row").alias("outer"), F.col("col").alias("page"), "val")
    right = t.df.select(free.alias("bi"), hand("col").alias("bj"), F.lit(1).cast("byte").alias("side"), F.col("col").alias("outer"), F.col("row").alias("page"), "val")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from _bilinear_block(pa.Table.from_batches([b.select(["side", "outer", "page", "val"]) for b in batches]), scheme)

    out = left.unionByName(right).groupBy("bi", "bj").applyInArrow(run, "row bigint, col bigint, val bigint")
    return SparseMatrix(out, s.n_rows, t.n_cols, s.semiring)


def block_multiply(s: SparseMatrix, t: SparseMatrix, side: int) -> SparseMatrix:
    """S T of integers, in ``side`` ** 2 blocks that each make their part of the result alone.

    Plus is the sum, or the semiring's ``fold`` of two values; times has to work
    on arrays.  A block's entries live in one task, its results pass through it
    in batches.  A block that is small is a dense tile, any other is walked in
    strips of rows, so sparse blocks cost what their products cost.
    """
    ring = s.semiring
    if ring.fold is None and ring.name != "plus_times":
        raise ValueError("blocks need the sum of integers or a semiring with a fold")
    hand = lambda c: F.pmod(F.xxhash64(c), F.lit(side)).cast("int")
    free = F.explode(F.sequence(F.lit(0), F.lit(side - 1)))
    left = s.df.select(hand("row").alias("bi"), free.alias("bj"), F.lit(0).cast("byte").alias("side"), F.col("row").alias("outer"), F.col("col").alias("page"), "val")
    right = t.df.select(free.alias("bi"), hand("col").alias("bj"), F.lit(1).cast("byte").alias("side"), F.col("col").alias("outer"), F.col("row").alias("page"), "val")
    times, fold, zero = ring.times, ring.fold, ring.zero

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from _block(pa.Table.from_batches([b.select(["side", "outer", "page", "val"]) for b in batches]), times, fold, zero)

    out = left.unionByName(right).groupBy("bi", "bj").applyInArrow(run, "row bigint, col bigint, val bigint")
    return SparseMatrix(out, s.n_rows, t.n_cols, ring)

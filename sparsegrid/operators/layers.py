"""Counting triangles of undirected graphs by layers from packed lines: first edges and paths meet in the task of their pair of parts.

As in the listing, vertices are dealt to parts by degree, a worker learns the
edges between two parts and, of its share of third vertices, the edges from both
parts.  Workers of the pairs (q, r) and (r, q) learn the same paths; they share
a task, so every list goes once to each part that its own is paired with.
Paths are packed, a list for each part and range of lines, and wedges are
closed where they are made.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsegrid.operators.gram import Lines, _number, _pick, _ranked, _sorted, pack, unpack

_STRIP = 1 << 19  # wedges that are closed at once
_TABLE = 1 << 25  # places of first edges that are an array
_MARKS = 24  # bits of the numbers that mark first edges where they are no array


@dataclass(frozen=True)
class Parts:
    """Vertices dealt to parts by degree: ``part`` and ``place`` (among the part's ids) by the order of ``ids``."""

    ids: np.ndarray
    part: np.ndarray
    place: np.ndarray

    @classmethod
    def dealt(cls, ids: np.ndarray, degree: np.ndarray, p: int) -> Parts:
        part = np.zeros(len(ids), np.uint16)
        part[np.argsort(degree, kind="stable")] = (np.arange(len(ids)) + -len(ids) % p) % p
        return cls.told(ids, part)

    @classmethod
    def told(cls, ids: np.ndarray, part: np.ndarray) -> Parts:
        order = np.argsort(part, kind="stable")
        first = np.searchsorted(part[order], np.arange(int(part.max(initial=0)) + 1))
        place = np.zeros(len(ids), np.int64)
        place[order] = np.arange(len(ids)) - first[part[order]]
        return cls(ids, part, place)

    def at(self) -> Callable:
        """Where ids, which all are vertices, stand among ``ids``."""
        low, span = int(self.ids[0]), int(self.ids[-1]) - int(self.ids[0]) + 1
        if span > 4 * len(self.ids):
            return lambda x: np.searchsorted(self.ids, x)
        table = np.zeros(span, np.int32)
        table[self.ids - low] = np.arange(len(self.ids))
        return lambda x: table[x - low]


def _opened(row: dict, parts: Parts, at: Callable) -> tuple[np.ndarray, ...]:
    """(places of a range's lines among all, line, place among all of the neighbour) of the edges to smaller ids."""
    own, sizes, near = unpack(row["ids"]), unpack(row["sizes"]), unpack(row["near"])
    line = np.repeat(np.arange(len(own)), sizes)
    low = np.flatnonzero(near < own[line])
    return at(own), line[low], at(near[low])


def _pair(q: np.ndarray, r: np.ndarray, p: int) -> np.ndarray:
    """The number of an unordered pair of parts."""
    return np.minimum(q, r).astype(np.int64) * p + np.maximum(q, r)


def _wedges(size_i, size_j, same: bool) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Strips of (entries of the first list, how many each meets, entries of the second that they meet), line by line."""
    n = int(size_i.sum())
    if same:
        first = np.arange(1, n + 1)
        count = np.repeat(np.cumsum(size_i), size_i) - first
    else:
        first, count = np.repeat(np.cumsum(size_j) - size_j, size_i), np.repeat(size_j, size_i)
    made, a = np.concatenate(([0], np.cumsum(count))), 0
    while a < n:
        b = max(a + 1, int(np.searchsorted(made, made[a] + _STRIP, "right")) - 1)
        if made[b] > made[a]:
            yield slice(a, b), count[a:b], _pick(first[a:b], count[a:b])
        a = b


def _closed(e: tuple[np.ndarray, np.ndarray], size_i, x, size_j, y, most: int = _TABLE) -> int:
    """How many wedges of the lists x and y (one and the same where y is None) of the same lines are closed by first edges ``e``, which are in order."""
    same = y is None
    if same:
        size_j, y = size_i, x
    i, j = np.searchsorted(e[0], (x.min(), x.max() + 1)) if len(x) and len(y) else (0, 0)
    if i == j:
        return 0
    closed, a, b = 0, e[0][i:j], e[1][i:j]
    ids_r, r = _ranked(x)
    ids_c, c = (ids_r, r) if same else _ranked(y)
    wide = len(ids_c)
    k, m = np.searchsorted(ids_r, a).clip(max=len(ids_r) - 1), np.searchsorted(ids_c, b).clip(max=wide - 1)
    there = np.flatnonzero((ids_r[k] == a) & (ids_c[m] == b))
    key = k[there] * wide + m[there]
    if len(ids_r) * wide <= most:
        table = np.zeros(len(ids_r) * wide, bool)
        table[key] = True
        for of, count, met in _wedges(size_i, size_j, same):
            closed += int(np.count_nonzero(table[np.repeat(r[of] * wide, count) + c[met]]))
        return closed
    # few numbers share a mark, so few wedges are looked for among the edges
    odd, shift = np.uint64(0x9E3779B97F4A7C15), np.uint64(64 - _MARKS)
    marks = np.zeros(1 << _MARKS, bool)
    marks[(key.view(np.uint64) * odd) >> shift] = True
    for of, count, met in _wedges(size_i, size_j, same):
        w = np.repeat(r[of] * wide, count) + c[met]
        w = w[marks[(w.view(np.uint64) * odd) >> shift]]
        closed += int(np.count_nonzero(key[np.searchsorted(key, w).clip(max=len(key) - 1)] == w)) if len(key) else 0
    return closed


def count_by_layers(lines: Lines, ids: np.ndarray, degree: np.ndarray, p: int) -> DataFrame:
    """One row (triangles), with the lines' ids and degrees known: every triangle is counted at the pair of parts of its two smaller vertices.

    A pair with more than twice the mean's first edges is cut into sets of them,
    and where pairs are fewer than the session's shuffle partitions, ranges of
    third vertices are dealt to several tasks.
    """
    spark, n, m = lines.df.sparkSession, len(ids), int(degree.sum()) // 2
    if not n:
        return spark.range(1).select(F.lit(0).cast("bigint").alias("triangles"))
    told = spark.sparkContext.broadcast((pack(ids), Parts.dealt(ids, degree, p).part.tobytes()))
    seen: list = []

    def parts():
        if not seen:
            known = Parts.told(unpack(told.value[0]), np.frombuffer(told.value[1], np.uint16))
            seen.extend((known, known.at()))
        return seen

    def between(batches):
        for batch in batches:
            for row in batch.to_pylist():
                known, at = parts()
                own, line, near = _opened(row, known, at)
                made = np.bincount(_pair(known.part[own[line]], known.part[near], p), minlength=p * p)
                yield pa.RecordBatch.from_arrays([pa.array([pack(made)])], ["m"])

    edges = sum(unpack(r["m"]) for r in lines.df.mapInArrow(between, "m binary").collect())
    sets = -(-edges * (p * p) // (4 * m))
    used = int(np.count_nonzero(edges))
    hands = min(p, max(1, int(spark.conf.get("spark.sql.shuffle.partitions")) // used))
    begin = (np.cumsum(sets) - sets) * hands

    def sent(batches):
        names = ["slot", "kind", "si", "xi", "sj", "xj"]

        def out(slot, kind, *cells):
            return pa.RecordBatch.from_arrays([pa.array([slot], pa.int32()), pa.array([kind], pa.int32()), *(pa.array([c], pa.binary()) for c in cells)], names)

        for batch in batches:
            for row in batch.to_pylist():
                known, at = parts()
                own, line, near = _opened(row, known, at)
                q, x, mine = known.part[near], known.place[near], known.part[own[line]]
                order = np.argsort(q, kind="stable")
                ends, lists = np.searchsorted(q[order], np.arange(p + 1)), {}
                for k in range(p):
                    of = order[ends[k] : ends[k + 1]]
                    if len(of):
                        lists[k] = (pack(np.bincount(line[of], minlength=len(own))), pack(x[of]))
                hand = int(own[0]) * hands // n
                for i in lists:
                    for j in lists:
                        pair = i * p + j
                        for s in range(sets[pair] if i <= j else 0):
                            yield out(begin[pair] + s * hands + hand, 1, *lists[i], *(lists[j] if i < j else (b"", b"")))
                # first edges, by pairs of parts
                pair, y = _pair(q, mine, p), known.place[own[line]]
                order = np.argsort(pair, kind="stable")
                first = np.flatnonzero(np.diff(pair[order], prepend=-1))
                for of in np.split(order, first[1:]) if len(order) else []:
                    k = int(pair[of[0]])
                    turn = q[of] > mine[of]
                    a, b, dealt = np.where(turn, y[of], x[of]), np.where(turn, x[of], y[of]), np.zeros(len(of), np.int64)
                    if sets[k] > 1:
                        count = np.bincount(line[of], minlength=len(own))
                        place = np.empty(len(own), np.int64)
                        place[np.argsort(-count, kind="stable")] = np.arange(len(own))
                        dealt = place[line[of]] % sets[k]
                    for s in np.unique(dealt):
                        c, d, _ = _sorted(a[dealt == s], b[dealt == s], None)
                        c, d = pack(c), pack(d)
                        for h in range(hands):
                            yield out(begin[k] + s * hands + h, 0, c, d, b"", b"")

    def met(batches):
        first, paths = [], []
        for batch in batches:
            for row in batch.to_pylist():
                if row["kind"]:
                    paths.append([row[c] for c in ("si", "xi", "sj", "xj")])
                else:
                    first.append((unpack(row["si"]), unpack(row["xi"])))
        if first and paths:
            a, b, _ = _sorted(*(np.concatenate(g) for g in zip(*first, strict=True)), None)
            for cells in paths:
                yield _number(_closed((a, b), *(unpack(c) if c else None for c in cells)))

    kinds = "slot int, kind int, si binary, xi binary, sj binary, xj binary"
    closed = lines.df.mapInArrow(sent, kinds).repartitionById(int(sets.sum()) * hands, F.col("slot")).mapInArrow(met, "v0 decimal(38,0)")
    return closed.agg(F.coalesce(F.sum("v0"), F.lit(0)).cast("bigint").alias("triangles"))

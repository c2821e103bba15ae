"""Best paths of graphs that come in parts: a part that no edge leaves is solved whole in one task.

A sequence within groups makes such a graph: its groups are the parts.  Whether
they are is checked, and parts that share a vertex or have more vertices than a
task takes are left to the general methods of ``paths``.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsegrid.functions.semiring import MAX_MIN
from sparsegrid.model import Graph, SparseMatrix
from sparsegrid.operators.paths import closure, shortest_paths
from sparsegrid.plans.lineage import cut_and_release, cut_lineage

_MOST = 256  # links of a part that is solved as a dense array
_PLACES = 1 << 19  # places of the arrays that are solved together
_FAR = 1 << 61


def apart(links: DataFrame, most: int = _MOST) -> tuple[DataFrame, DataFrame | None]:
    """Links (part, ...) of the parts that a task solves, and those of all others, None where there are none."""
    ends = links.select("part", F.explode(F.array("src", "dst")).alias("v"))
    shared = ends.groupBy("v").agg(F.min("part").alias("a"), F.max("part").alias("b")).where("a <> b").select("v")
    large = links.groupBy("part").agg(F.count("*").alias("c")).where(F.col("c") > most).select("part")
    rest = cut_and_release(large.union(ends.join(shared, "v", "left_semi").select("part")).distinct(), rounds=3)  # the files of the check go before the links are dealt
    if rest.isEmpty():
        return links, None
    return links.join(rest, "part", "left_anti"), cut_lineage(links.join(rest, "part", "left_semi"))


def _whole(batches: Iterator[pa.RecordBatch]) -> Iterator[list[np.ndarray]]:
    """The columns of batches sorted by part (the first column), cut between parts only."""
    held: list[list[np.ndarray]] = []
    for batch in batches:
        cols = [c.to_numpy() for c in batch.columns]
        if not len(cols[0]):
            continue
        last = int(np.searchsorted(cols[0], cols[0][-1]))
        if last or (held and held[-1][0][-1] != cols[0][0]):
            yield [np.concatenate(c) for c in zip(*held, [x[:last] for x in cols], strict=True)]
            held = []
        held.append([x[last:] for x in cols])
    if held:
        yield [np.concatenate(c) for c in zip(*held, strict=True)]


def _arrays(part: np.ndarray, src: np.ndarray, dst: np.ndarray, val: np.ndarray, none: int, plus: np.ufunc) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(ids, values) of parts of about one size: vertices in order, and a square array for each part, ``none`` where nothing is held."""
    names, where = np.unique(np.concatenate([src, dst]), return_inverse=True)
    of = np.zeros(len(names), part.dtype)
    of[where] = np.concatenate([part, part])
    order = np.argsort(of, kind="stable")  # vertices by part, in their own order within
    parts, first, size = np.unique(of[order], return_index=True, return_counts=True)
    local = np.empty(len(names), np.int64)
    local[order] = np.arange(len(names)) - np.repeat(first, size)
    x, y, mine = local[where[: len(src)]], local[where[len(src) :]], np.searchsorted(parts, part)
    for n in np.unique(size):
        same = np.flatnonzero(size == n)
        step = max(1, _PLACES // int(n * n))
        for a in range(0, len(same), step):
            these = same[a : a + step]
            ids = names[order[first[these][:, None] + np.arange(n)]]
            place = np.full(len(parts), -1)
            place[these] = np.arange(len(these))
            at = np.flatnonzero(place[mine] >= 0)
            d = np.full((len(these), n, n), none, np.int64)
            for i, j in ((x, y), (y, x)):
                plus.at(d, (place[mine[at]], i[at], j[at]), val[at])
            yield ids, d


def _best(d: np.ndarray, plus: np.ufunc, times: np.ufunc) -> np.ndarray:
    """The best over all walks, by allowing one more vertex between the ends at a time."""
    for k in range(d.shape[1]):
        plus(d, times(d[:, :, k, None], d[:, None, k, :]), out=d)
    return d


def _solved_paths(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for part, src, dst, w in _whole(batches):
        if len(w) and int(np.abs(w).max()) * len(w) >= _FAR:
            raise OverflowError("distances leave BIGINT")
        for ids, edges in _arrays(part, src, dst, w, _FAR, np.minimum):
            n = ids.shape[1]
            d = edges.copy()
            d[:, np.arange(n), np.arange(n)] = 0
            d = _best(d, np.minimum, np.add)
            via = np.zeros(d.shape, np.int64)
            for k in range(n - 1, -1, -1):  # the smallest of equals comes last
                np.copyto(via, ids[:, k, None, None], where=d[:, :, k, None] + edges[:, None, k, :] == d)
            p, i, j = np.nonzero((d < _FAR) & ~np.eye(n, dtype=bool))
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in (ids[p, i], ids[p, j], d[p, i, j], via[p, i, j])], ["src", "dst", "dist", "via"])


def _dealt(links: DataFrame, value: str) -> DataFrame:
    return links.select("part", "src", "dst", F.col(value).cast("bigint").alias("v")).repartition("part").sortWithinPartitions("part")


def _both(links: DataFrame, value: str) -> DataFrame:
    one = links.select("src", "dst", F.col(value).cast("bigint").alias("v"))
    return one.union(one.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "v"))


def shortest_paths_of_parts(links: DataFrame, n: int, most: int = _MOST) -> DataFrame:
    """(src, dst, dist, via) as of ``shortest_paths``, from links (part, src, dst, w) that hold both ways."""
    links = links.where("src <> dst AND w IS NOT NULL")
    mine, rest = apart(links, most)
    out = _dealt(mine, "w").mapInArrow(_solved_paths, "src bigint, dst bigint, dist bigint, via bigint")
    if rest is None:
        return out
    w = cut_lineage(_both(rest, "w").groupBy("src", "dst").agg(F.min("v").alias("w")))
    return out.union(shortest_paths(Graph(w.select("src", "dst"), n, False), w))


def _solved_closure(none: int, plus: np.ufunc, times: np.ufunc) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, src, dst, val in _whole(batches):
            for ids, d in _arrays(part, src, dst, val, none, plus):
                d = _best(d, plus, times)
                p, i, j = np.nonzero(d != none)
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in (ids[p, i], ids[p, j], d[p, i, j])], ["row", "col", "val"])

    return run


def bottleneck_of_parts(links: DataFrame, n: int, most: int = _MOST) -> SparseMatrix:
    """``closure`` over max-min, from links (part, src, dst, w) that hold both ways: the best smallest value on a walk."""
    links = links.where("src <> dst AND w IS NOT NULL")
    mine, rest = apart(links, most)
    none = int(np.iinfo(np.int64).min)  # no sum of a table's hundredths is that low
    out = _dealt(mine, "w").mapInArrow(_solved_closure(none, np.maximum, np.minimum), "row bigint, col bigint, val bigint")
    if rest is not None:
        held = _both(rest, "w").groupBy(F.col("src").alias("row"), F.col("dst").alias("col")).agg(F.max("v").alias("val"))
        out = out.union(closure(SparseMatrix(held, n, n, MAX_MIN)).df.select("row", "col", "val"))
    return SparseMatrix(out, n, n, MAX_MIN)

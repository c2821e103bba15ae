"""Counting short cycles of undirected graphs by traces."""

from __future__ import annotations

from decimal import Decimal

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsegrid.model import Graph, SparseMatrix
from sparsegrid.operators.algebra import diagonal, row_sums, trace_of_square_symmetric
from sparsegrid.operators.gram import lines_of, size_of_gram, turning_walks
from sparsegrid.operators.multiply import sparse_multiply
from sparsegrid.operators.twins import merge_twins
from sparsegrid.plans.lineage import release


def count_four_cycles(g: Graph, multiply=sparse_multiply) -> DataFrame:
    """One row (trace, walks, four_cycles): closed 4-walks, those that turn back, and 4-cycles.

    The square of the adjacency matrix is symmetric, so its own trace product is
    a sum of squares and the square is never written.
    """
    a = g.matrix()
    trace = trace_of_square_symmetric(multiply(a, a))
    d = F.col("d_out").cast("bigint")
    back = g.degrees().agg(F.coalesce(F.sum(2 * d * d - d), F.lit(0)).cast("bigint").alias("walks"))
    return trace.crossJoin(back).select("trace", "walks", F.floor((F.col("trace") - F.col("walks")) / 8).alias("four_cycles"))


def count_four_cycles_of_lines(g: Graph) -> DataFrame:
    """The same from packed lines: the squares of a block of the square are summed in the task that makes the block, and nothing of it is exchanged."""
    lines = lines_of(g)
    trace = size_of_gram(lines).select(F.coalesce("squares", F.lit(0)).cast("bigint").alias("trace"))
    return trace.crossJoin(turning_walks(lines)).select("trace", "walks", F.floor((F.col("trace") - F.col("walks")) / 8).alias("four_cycles"))


_WEDGES = 1 << 24  # wedges of a task
_CHUNK = 1 << 21  # wedges that are counted together
_DENSE = 1 << 23  # places of a task's counts in an array


def _counted_pairs(batches):
    """(a, b, c): the pairs a < b of the lists of a partition and the number of lists that hold both."""
    lists = [b.column(0) for b in batches]
    size = np.concatenate([np.diff(x.offsets.to_numpy()) for x in lists] or [np.zeros(0, np.int64)]).astype(np.int64)
    ids, held = np.unique(np.concatenate([x.flatten().to_numpy() for x in lists] or [np.zeros(0, np.int64)]), return_inverse=True)
    del lists
    wide = len(ids)
    first = np.repeat(np.cumsum(size) - size, size)
    before = np.arange(len(held)) - first  # the elements of its list that an element follows
    made = np.concatenate(([0], np.cumsum(before)))
    dense = np.zeros(wide * wide, np.int64) if wide * wide <= _DENSE else None

    def rows(key, count):
        for i in range(0, len(key), 1 << 16):
            k = key[i : i + (1 << 16)]
            yield pa.RecordBatch.from_arrays([pa.array(ids[k // wide]), pa.array(ids[k % wide]), pa.array(count[i : i + (1 << 16)], pa.int64())], ["a", "b", "c"])

    i = 0
    while i < len(held):
        j = max(i + 1, int(np.searchsorted(made, made[i] + _CHUNK, side="right")) - 1)
        n = before[i:j]
        at = np.arange(n.sum()) + np.repeat(first[i:j] - (np.cumsum(n) - n), n)
        key = held[at] * wide + np.repeat(held[i:j], n)
        i = j
        if dense is None:
            yield from rows(*np.unique(key, return_counts=True))
        else:
            dense += np.bincount(key, minlength=wide * wide)
    if dense is not None:
        key = np.flatnonzero(dense)
        yield from rows(key, dense[key])


def count_four_cycles_bipartite(s: SparseMatrix) -> DataFrame:
    """One row (four_cycles) of the bipartite graph whose two kinds of vertices are the rows and the columns of S.

    Two vertices of one kind with k common neighbours are on k (k - 1) / 2 cycles
    together, and every cycle has one such pair of either kind: the pairs of
    that kind are counted which have fewer wedges between them.  The middles of
    wedges are dealt by ranges, and a task counts its pairs before they are
    exchanged.
    """
    pairs = s.df.select("row", "col").distinct()
    wedges = lambda axis: pairs.groupBy(axis).agg(F.count("*").alias("d")).agg(F.coalesce(F.sum(F.col("d") * (F.col("d") - 1) / 2), F.lit(0)).alias("w")).select(F.lit(axis).alias("axis"), "w")
    most = {r["axis"]: int(r["w"]) for r in wedges("row").union(wedges("col")).collect()}
    release(s.df.sparkSession, rounds=3)  # the files of the counts
    middle, end = ("row", "col") if most["row"] <= most["col"] else ("col", "row")
    tasks = max(int(s.df.sparkSession.conf.get("spark.sql.shuffle.partitions")) // 4, most[middle] // _WEDGES, 1)
    near = s.df.select(middle, end).repartitionByRange(tasks, middle).groupBy(middle).agg(F.array_sort(F.collect_set(end)).alias("ends"))
    counted = near.select("ends").mapInArrow(_counted_pairs, "a bigint, b bigint, c bigint").groupBy("a", "b").agg(F.sum("c").alias("k"))
    return counted.agg(F.coalesce(F.sum(F.expr("k * (k - 1) div 2")), F.lit(0)).cast("bigint").alias("four_cycles"))


def _rows_of_powers(a: SparseMatrix, sizes: DataFrame) -> DataFrame:
    """(t5, t3, hung) of 64 rows each: their shares of the traces of the fifth and third power, and of the triangles' hanging edges.

    ``a`` holds the size of its column's class wherever two classes are joined.
    With E for its places and S for the sizes, row i of E S E and of E S E S E
    give the diagonals of both powers at i, as the two are symmetric.
    """
    spark = a.df.sparkSession
    held, of = a.df.select("row", "col").toArrow(), sizes.toArrow()
    row, col = held["row"].to_numpy(), held["col"].to_numpy()
    ids = np.unique(row)  # edges go both ways
    order = np.argsort(row, kind="stable")
    ends = np.concatenate(([0], np.cumsum(np.bincount(np.searchsorted(ids, row), minlength=len(ids)))))
    known = np.argsort(of["rep"].to_numpy(), kind="stable")
    size = of["size"].to_numpy()[known][np.searchsorted(of["rep"].to_numpy()[known], ids)].astype(np.float64)
    told = spark.sparkContext.broadcast((ends, np.searchsorted(ids, col[order]).astype(np.int32), size))

    def run(batches):
        ends, to, size = told.value
        degree = np.diff(ends)

        def spread(v, x):
            """The row vector with x at v, times E."""
            n = degree[v]
            at = np.arange(n.sum()) + np.repeat(ends[v] - (np.cumsum(n) - n), n)
            return np.bincount(to[at], np.repeat(x, n), len(size))

        for batch in batches:
            t5, t3, hung = 0, 0, 0
            for block in batch.column(0).to_pylist():
                for i in range(64 * block, min(64 * block + 64, len(size))):
                    near = to[ends[i] : ends[i + 1]]
                    two = spread(near, size[near])
                    far = np.flatnonzero(two)
                    three = spread(far, two[far] * size[far])
                    five = float(two[far] * size[far] @ three[far]) * float(size[i])
                    if five < 1 << 53 and three.max(initial=0) < 1 << 53:  # sums of whole numbers, so none has been rounded
                        five = int(five)
                        three_i = int(three[i])
                    else:  # Python's numbers are not rounded
                        exact: dict = {}
                        paths = {j: 0 for j in far.tolist()}
                        for j in near.tolist():
                            for k in to[ends[j] : ends[j + 1]].tolist():
                                paths[k] += int(size[j])
                        for j, x in paths.items():
                            for k in to[ends[j] : ends[j + 1]].tolist():
                                exact[k] = exact.get(k, 0) + x * int(size[j])
                        five = int(size[i]) * sum(x * int(size[j]) * exact.get(j, 0) for j, x in paths.items())
                        three_i = exact.get(i, 0)
                    closed = int(size[i]) * three_i
                    t5, t3, hung = t5 + five, t3 + closed, hung + (int(size[near].sum()) - 2) * closed
            yield pa.RecordBatch.from_arrays([pa.array([Decimal(x)], pa.decimal128(38, 0)) for x in (t5, t3, hung)], ["t5", "t3", "hung"])

    blocks = -(-len(ids) // 64)
    tasks = max(1, min(blocks, int(spark.conf.get("spark.sql.shuffle.partitions"))))
    return spark.range(0, blocks, 1, tasks).mapInArrow(run, "t5 decimal(38,0), t3 decimal(38,0), hung decimal(38,0)")


def count_five_cycles(g: Graph, multiply=sparse_multiply, most: int = 4_000_000) -> DataFrame:
    """One row (five_cycles), from the traces of the third and fifth power and the triangles at each vertex.

    Vertices with the same neighbours are one line of the matrix, whose entries
    hold the sizes of the classes they lead to: the traces of its powers are
    those of the whole matrix, and a hub with many leaves has one neighbour in it.
    Of at most ``most`` entries every task is told the matrix, and makes the rows
    of the powers that the traces need one after another; nothing of them is
    exchanged or written.
    """
    t = merge_twins(g)
    a = t.matrix().cut()
    if multiply is sparse_multiply and a.df.limit(most + 1).count() <= most:
        sums = _rows_of_powers(a, t.sizes).agg(*[F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in ("t5", "t3", "hung")])
        return sums.select(F.floor((F.col("t5") - 5 * F.col("t3") - 5 * F.col("hung")) / 10).cast("bigint").alias("five_cycles"))
    square = multiply(a, a).cut()
    cube = multiply(square, a).cut()
    fifth = square.df.select("row", "col", F.col("val").alias("x")).join(cube.df.select(F.col("col").alias("row"), F.col("row").alias("col"), F.col("val").alias("y")), ["row", "col"]).agg(F.coalesce(F.sum(F.col("x") * F.col("y")), F.lit(0)).alias("t5"))
    at = diagonal(cube).join(row_sums(a).select("id", F.col("val").alias("d")), "id")
    third = at.agg(F.coalesce(F.sum("val"), F.lit(0)).alias("t3"), F.coalesce(F.sum((F.col("d") - 2) * F.col("val")), F.lit(0)).alias("hung"))
    return fifth.crossJoin(third).select(F.floor((F.col("t5") - 5 * F.col("t3") - 5 * F.col("hung")) / 10).cast("bigint").alias("five_cycles"))

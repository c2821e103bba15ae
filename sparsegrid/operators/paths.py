"""Distances: breadth-first levels, all-pairs hops by sparse powers, closures of other semirings."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsegrid.functions.semiring import MIN_PLUS
from sparsegrid.model import Graph, SparseMatrix
from sparsegrid.operators.algebra import add, with_identity
from sparsegrid.operators.multiply import sparse_multiply
from sparsegrid.operators.stats import totals
from sparsegrid.operators.twins import merge_twins
from sparsegrid.plans.lineage import cut_lineage


def vertices(g: Graph) -> DataFrame:
    return g.edges.select(F.explode(F.array("src", "dst")).alias("id")).distinct()


def bfs_levels(g: Graph, root: int, most: int = 1 << 20) -> DataFrame:
    """(v, level): hops from the root; one join with the edges and one anti join for each level."""
    spark = g.edges.sparkSession
    seen = front = cut_lineage(spark.range(1).select(F.lit(root).cast("bigint").alias("v"), F.lit(0).cast("bigint").alias("level")))
    for level in range(1, most):
        reached = front.join(g.edges, front["v"] == g.edges["src"]).select(F.col("dst").alias("v")).distinct()
        front = cut_lineage(reached.join(seen, "v", "left_anti").select("v", F.lit(level).cast("bigint").alias("level")))
        if front.isEmpty():
            break
        seen = cut_lineage(seen.union(front))
    return seen


def diameter_bounds(g: Graph, root: int) -> DataFrame:
    """One row (low, high): the root's eccentricity e in its component, and 2 e; the diameter there lies between."""
    return bfs_levels(g, root).agg(F.max("level").alias("low"), (2 * F.max("level")).alias("high"))


def all_pairs_hops(g: Graph, bound: str | int = "fixpoint", root: int | None = None, mode: str = "delta", multiply=sparse_multiply) -> DataFrame:
    """(src, dst, dist) of every pair that is connected, a vertex to itself included.

    Powers over min-plus, raised by the sparse adjacency matrix with the planned
    product.  ``bound`` is the power to reach: a number, ``bfs`` for twice the
    eccentricity of ``root``, or ``fixpoint`` to stop when nothing changes.  Hops
    are final when first found, so ``delta`` multiplies only what the last step
    has added; ``full`` multiplies the whole power.
    """
    if bound == "bfs":
        limit = int(diameter_bounds(g, root).first()["high"] or 0)
    else:
        limit = bound if isinstance(bound, int) else 1 << 20
    if mode == "full":
        step = with_identity(g.matrix(MIN_PLUS, 1), vertices(g)).cut()
        power, size = step, -1
        for _ in range(limit - 1):
            power = multiply(power, step).cut()
            count = power.nnz()
            if count == size and bound == "fixpoint":
                break
            size = count
        return power.df.select(F.col("row").alias("src"), F.col("col").alias("dst"), F.col("val").alias("dist"))
    edges = g.matrix(MIN_PLUS, 1)
    own = vertices(g).select(F.col("id").alias("row"), F.col("id").alias("col"), F.lit(0).cast("bigint").alias("val"))
    front = edges.with_df(cut_lineage(own))
    known = front.df
    for dist in range(1, limit + 1):
        seen = totals(front, edges)
        if not seen.products:
            break
        met = multiply(front, edges, seen=seen) if multiply is sparse_multiply else multiply(front, edges)
        front = edges.with_df(cut_lineage(met.df.join(known.select("row", "col"), ["row", "col"], "left_anti").select("row", "col", "val")))
        known = cut_lineage(known.union(front.df)) if dist % 4 == 0 else known.union(front.df)
    return known.select(F.col("row").alias("src"), F.col("col").alias("dst"), F.col("val").alias("dist"))


def all_pairs_announced(g: Graph, most: int = 2_000_000) -> DataFrame:
    """The same as ``all_pairs_hops`` for a graph of at most ``most`` edges, which every task is told; a larger one is left to the full powers.

    A task raises the power for 64 rows at a time, held as the bits of one word
    for each vertex: a step is one bitwise sum over the edges.  Rows are
    independent, so no power is exchanged or written.
    """
    spark = g.edges.sparkSession
    if g.edges.limit(most + 1).count() > most:
        return all_pairs_hops(g, mode="full")
    held = g.edges.select("src", "dst").toArrow()
    src, dst = held["src"].to_numpy(), held["dst"].to_numpy()
    ids = np.unique(np.concatenate([src, dst]))
    order = np.argsort(dst, kind="stable")
    ends, starts = np.unique(np.searchsorted(ids, dst[order]), return_index=True)
    told = spark.sparkContext.broadcast((ids, np.searchsorted(ids, src[order]), ends, starts))

    def run(batches):
        names, before, into, first = told.value
        for batch in batches:
            for block in batch.column(0).to_pylist():
                own = np.arange(64 * block, min(64 * block + 64, len(names)))
                front = np.zeros(len(names), np.uint64)
                front[own] = np.uint64(1) << (own - 64 * block).astype(np.uint64)
                seen, dist = front.copy(), 0
                while front.any():
                    at, bit = np.nonzero(np.unpackbits(front.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little"))
                    for a in range(0, len(at), 1 << 17):
                        x, y = names[64 * block + bit[a : a + (1 << 17)]], names[at[a : a + (1 << 17)]]
                        yield pa.RecordBatch.from_arrays([pa.array(x), pa.array(y), pa.array(np.full(len(x), dist, np.int64))], ["src", "dst", "dist"])
                    reached = np.zeros(len(names), np.uint64)
                    if len(into):
                        reached[into] = np.bitwise_or.reduceat(front[before], first)
                    front, dist = reached & ~seen, dist + 1
                    seen |= front

    tasks = max(1, min(-(-len(ids) // 64), int(spark.conf.get("spark.sql.shuffle.partitions"))))
    return spark.range(0, -(-len(ids) // 64), 1, tasks).mapInArrow(run, "src bigint, dst bigint, dist bigint")


def all_pairs_by_squaring(g: Graph, multiply=sparse_multiply) -> DataFrame:
    """Baseline: squares of ever denser powers until nothing changes."""
    power = with_identity(g.matrix(MIN_PLUS, 1), vertices(g)).cut()
    size = -1
    while (count := power.nnz()) != size:
        size, power = count, multiply(power, power).cut()
    return power.df.select(F.col("row").alias("src"), F.col("col").alias("dst"), F.col("val").alias("dist"))


def hops_summary(g: Graph, hops=all_pairs_hops, root: int | None = None) -> DataFrame:
    """One row (pairs, longest, total): the connected pairs of an undirected graph, a vertex with itself included, and their hops.

    ``hops`` runs on the classes of vertices with the same neighbours.  Members
    of two classes are as far apart as their representatives, two of one class
    two hops, so each pair of classes stands for the product of their sizes.
    ``root`` is passed on as its class.
    """
    t = merge_twins(g)
    if root is not None:
        own = t.members.where(F.col("v") == root).first()
        found = hops(t.graph, root=own["rep"] if own else root)
    else:
        found = hops(t.graph)
    size = lambda end, name: t.sizes.select(F.col("rep").alias(end), F.col("size").alias(name))
    told = found.join(size("src", "m"), "src").join(size("dst", "k"), "dst")
    twins = F.when(F.col("src") == F.col("dst"), F.col("m") * (F.col("m") - 1)).otherwise(0)
    total = F.when(F.col("src") == F.col("dst"), 2 * twins).otherwise(F.col("m") * F.col("k") * F.col("dist"))
    pairs = F.when(F.col("src") == F.col("dst"), F.col("m") + twins).otherwise(F.col("m") * F.col("k"))
    return told.agg(F.coalesce(F.sum(pairs), F.lit(0)).alias("pairs"), F.max(F.greatest("dist", F.when(twins > 0, 2).otherwise(0))).cast("bigint").alias("longest"), F.sum(total).alias("total"))


def closure(a: SparseMatrix, most: int = 1 << 20, multiply=sparse_multiply) -> SparseMatrix:
    """The best value over all walks of one step or more, for an idempotent plus; only changed entries go on."""
    best = front = a.cut()
    for _ in range(most):
        made = multiply(front, a)
        merged = add(best, made).cut()
        old = best.df.select("row", "col", F.col("val").alias("old"))
        changed = cut_lineage(merged.df.join(old, ["row", "col"], "left").where(~F.col("val").eqNullSafe(F.col("old"))).select("row", "col", "val"))
        best, front = merged, merged.with_df(changed)
        if changed.isEmpty():
            break
    return best


def shortest_paths(g: Graph, weights: DataFrame, most: int = 1 << 20) -> DataFrame:
    """(src, dst, dist, via): shortest distances with positive weights (src, dst, w), and the vertex before the last, the smallest of equals.

    Min-plus products that keep a witness: each step extends what the last has
    improved by one edge, and the best of each pair is a minimum of (dist, via).
    """
    edges = g.edges.join(weights, ["src", "dst"]).select(F.col("src").alias("via"), F.col("dst").alias("end"), F.col("w").cast("bigint").alias("w"))
    front = best = cut_lineage(edges.select(F.col("via").alias("src"), F.col("end").alias("dst"), F.col("w").alias("dist"), "via"))
    for _ in range(most):
        made = front.select("src", F.col("dst").alias("via"), "dist").join(edges, "via").where("src <> end").select("src", F.col("end").alias("dst"), (F.col("dist") + F.col("w")).alias("dist"), "via")
        offered = made.union(best).groupBy("src", "dst").agg(F.min(F.struct("dist", "via")).alias("b"))
        merged = cut_lineage(offered.select("src", "dst", "b.dist", "b.via"))
        old = best.select("src", "dst", F.col("dist").alias("old"))
        front = cut_lineage(merged.join(old, ["src", "dst"], "left").where("old IS NULL OR dist < old").select("src", "dst", "dist"))
        best = merged
        if front.isEmpty():
            break
    return best


def without_ends(g: Graph, share: float = 0.1) -> Graph:
    """An undirected graph without vertices of one neighbour, again and again: they lie on no cycle.

    It ends when a round takes fewer than ``share`` of the vertices that are
    left; what then remains holds all cycles, and ends that cost little.
    """
    edges = cut_lineage(g.edges)
    while True:
        degrees = cut_lineage(edges.groupBy("src").agg(F.count("*").alias("d")))
        n, ends = degrees.agg(F.count("*"), F.count(F.when(F.col("d") == 1, 1))).first()
        if not ends or ends < share * n:
            return Graph(edges, g.n, g.directed)
        kept = degrees.where("d > 1")
        edges = cut_lineage(edges.join(kept.select("src"), "src", "left_semi").join(kept.select(F.col("src").alias("dst")), "dst", "left_semi").select("src", "dst"))


def girth_upto(g: Graph, most: int = 8) -> int | None:
    """The length of a shortest cycle of an undirected graph: 3 or 4 from counts, longer ones from two walks that meet; None beyond ``most``."""
    from sparsegrid.operators.cycles import count_four_cycles
    from sparsegrid.operators.triangles import triangles_two_hop

    g = without_ends(g)
    if not triangles_two_hop(g).isEmpty():
        return 3
    if count_four_cycles(g).first()["four_cycles"]:
        return 4
    walks = cut_lineage(g.edges.select(F.col("src").alias("root"), F.col("dst").alias("v"), F.col("src").alias("before")))
    seen = cut_lineage(vertices(g).select(F.col("id").alias("root"), F.col("id").alias("v")).union(walks.select("root", "v")))
    for level in range(1, most // 2 + 1):
        # an edge between two vertices of one level closes an odd cycle, a vertex reached twice an even one
        same = walks.select("root", "v").join(g.edges, F.col("v") == F.col("src")).join(walks.select("root", F.col("v").alias("dst")), ["root", "dst"], "left_semi")
        if not same.isEmpty() and 2 * level + 1 <= most:
            return 2 * level + 1
        step = walks.select("root", F.col("v").alias("before")).distinct().join(g.edges, F.col("before") == F.col("src")).select("root", F.col("dst").alias("v"), "before")
        walks = cut_lineage(step.join(seen, ["root", "v"], "left_anti"))
        if not walks.groupBy("root", "v").count().where("count > 1").isEmpty() and 2 * level + 2 <= most:
            return 2 * level + 2
        if walks.isEmpty():
            return None
        seen = cut_lineage(seen.union(walks.select("root", "v").distinct()))
    return None

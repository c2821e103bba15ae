"""Vertices with the same neighbours as one: what is asked of a graph is asked of its classes."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsegrid.functions.semiring import PLUS_TIMES
from sparsegrid.model import Graph, SparseMatrix
from sparsegrid.plans.lineage import cut_lineage


@dataclass(frozen=True)
class Twins:
    """``graph``: the edges between representatives; ``members``: (v, rep) of every vertex with an edge; ``sizes``: (rep, size)."""

    graph: Graph
    members: DataFrame
    sizes: DataFrame

    def matrix(self) -> SparseMatrix:
        """Edges between classes, each holding the number of vertices of the class it leads to: walks in it are counted as in the whole graph."""
        told = self.graph.edges.join(self.sizes.select(F.col("rep").alias("dst"), F.col("size").alias("val")), "dst")
        return SparseMatrix(told.select(F.col("src").alias("row"), F.col("dst").alias("col"), "val"), self.graph.n, self.graph.n, PLUS_TIMES)


def merge_twins(g: Graph) -> Twins:
    """The classes of vertices that have the same neighbours, of an undirected graph.

    Classes are made by a hash of the neighbours and then verified: every
    neighbour of a class has to be one of all its members.  A class that is not
    confirmed falls apart into single vertices, so nothing rests on the hash.
    There are no edges within a class, and either all or none between two.
    """
    mark = lambda seed: F.bit_xor(F.xxhash64("dst", F.lit(seed)))
    lines = g.edges.groupBy("src").agg(F.count("*").alias("d"), mark(1).alias("h"), mark(2).alias("i"))
    first = lines.groupBy("d", "h", "i").agg(F.min("src").alias("rep"), F.count("*").alias("size"))
    supposed = cut_lineage(lines.join(first, ["d", "h", "i"]).select(F.col("src").alias("v"), "rep", "size"))
    many = supposed.where("size > 1")
    shared = g.edges.join(many, F.col("src") == F.col("v")).groupBy("rep", "size", "dst").agg(F.count("*").alias("c"))
    apart = shared.where("c <> size").select("rep").distinct().withColumn("apart", F.lit(True))
    members = cut_lineage(supposed.join(apart, "rep", "left").select("v", F.when(F.col("apart"), F.col("v")).otherwise(F.col("rep")).alias("rep")))
    sizes = cut_lineage(members.groupBy("rep").agg(F.count("*").alias("size")))
    to = lambda end: sizes.select(F.col("rep").alias(end))
    return Twins(Graph(cut_lineage(g.edges.join(to("src"), "src", "left_semi").join(to("dst"), "dst", "left_semi").select("src", "dst")), g.n, g.directed), members, sizes)

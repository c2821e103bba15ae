"""Matrices and graphs as coordinate tables."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sparsegrid.functions.semiring import PLUS_TIMES, Semiring
from sparsegrid.plans.lineage import cut_lineage


@dataclass(frozen=True)
class SparseMatrix:
    """Entries (row, col, val), one for each place that holds something.

    ``n_rows`` and ``n_cols`` enter cost formulas only; ids may be any BIGINT.
    ``wide`` says that ids are spread over all of BIGINT, as hashes are.
    """

    df: DataFrame
    n_rows: int
    n_cols: int
    semiring: Semiring = PLUS_TIMES
    wide: bool = False

    @property
    def n(self) -> int:
        return max(self.n_rows, self.n_cols, 1)

    @classmethod
    def of(cls, df: DataFrame, n_rows: int, n_cols: int, semiring: Semiring = PLUS_TIMES) -> SparseMatrix:
        """From (row, col, val): ids are cast, suppressed and unknown values left out."""
        value = F.col("val").cast(semiring.kind)
        typed = df.where("row IS NOT NULL AND col IS NOT NULL").select(F.col("row").cast("bigint").alias("row"), F.col("col").cast("bigint").alias("col"), value.alias("val"))
        return cls(typed.where(semiring.present(F.col("val"))), n_rows, n_cols, semiring)

    def with_df(self, df: DataFrame) -> SparseMatrix:
        return replace(self, df=df)

    def cut(self) -> SparseMatrix:
        return self.with_df(cut_lineage(self.df))

    def transpose(self) -> SparseMatrix:
        """Swaps names; orientation is a matter of partitioning, not of storage."""
        return replace(self, df=self.df.select(F.col("col").alias("row"), F.col("row").alias("col"), "val"), n_rows=self.n_cols, n_cols=self.n_rows)

    def map_values(self, value: Column) -> SparseMatrix:
        return self.with_df(self.df.withColumn("val", value).where(self.semiring.present(F.col("val"))))

    def nnz(self) -> int:
        return self.df.count()


@dataclass(frozen=True)
class Graph:
    """Directed edges (src, dst), distinct and without loops; an undirected graph holds both directions.

    ``pairs``: those that an undirected graph was made of, one way and perhaps repeated, until its edges are written.
    """

    edges: DataFrame
    n: int
    directed: bool
    pairs: DataFrame | None = None

    @classmethod
    def of(cls, pairs: DataFrame, n: int, directed: bool) -> Graph:
        """From (src, dst) pairs: loops and repeats go, an undirected graph gets both directions."""
        one = pairs.select(F.col("src").cast("bigint").alias("src"), F.col("dst").cast("bigint").alias("dst")).where("src <> dst")
        both = one if directed else one.union(one.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
        return cls(both.distinct(), n, directed, None if directed else one)

    def cut(self) -> Graph:
        return replace(self, edges=cut_lineage(self.edges), pairs=None)

    def matrix(self, semiring: Semiring = PLUS_TIMES, value: object = None) -> SparseMatrix:
        """The adjacency matrix, every edge holding ``value`` (the semiring's one if None)."""
        held = semiring.one if value is None else value
        return SparseMatrix(self.edges.select(F.col("src").alias("row"), F.col("dst").alias("col"), F.lit(held).cast(semiring.kind).alias("val")), self.n, self.n, semiring)

    def degrees(self) -> DataFrame:
        """(v, d_out, d_in) of every vertex with an edge; partial counts before the exchange."""
        ends = self.edges.select(F.explode(F.array(F.struct(F.col("src").alias("v"), F.lit(1).alias("o"), F.lit(0).alias("i")), F.struct(F.col("dst").alias("v"), F.lit(0).alias("o"), F.lit(1).alias("i")))).alias("e"))
        return ends.groupBy("e.v").agg(F.sum("e.o").alias("d_out"), F.sum("e.i").alias("d_in"))

"""The engine from SQL: views over the given tables, and products of views."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from sparsegrid.functions.semiring import SEMIRINGS
from sparsegrid.functions.table_functions import _DivisorGrid
from sparsegrid.model import Graph, SparseMatrix
from sparsegrid.operators.multiply import sparse_multiply
from sparsegrid.operators.triangles import list_triangles
from sparsegrid.sources import tables


def register(spark: SparkSession, folder: str) -> list[str]:
    """Temporary views of all matrices and graphs (row, col, val or src, dst), and the table function ``divisor_grid``."""
    from pyspark.sql.functions import udtf

    made = []
    for name in ("co_order", "handoff", "forest", "order_chain", "supply", "quantities", "cust_supp", "doc_term"):
        held = getattr(tables, name)(spark, folder)
        (held.df if isinstance(held, SparseMatrix) else held.edges).createOrReplaceTempView(name)
        made.append(name)
    spark.udtf.register("divisor_grid", udtf(_DivisorGrid, returnType="a int, b int, c int"))
    return made


def multiply_views(spark: SparkSession, left: str, right: str, semiring: str = "plus_times", into: str | None = None) -> DataFrame:
    """The product of two views (row, col, val), itself made a view where ``into`` names one."""
    ring = SEMIRINGS[semiring]
    s, t = (SparseMatrix.of(spark.table(v), 1, 1, ring) for v in (left, right))
    out = sparse_multiply(s, t).df.select("row", "col", "val")
    if into:
        out.createOrReplaceTempView(into)
    return out


def triangles_of_view(spark: SparkSession, view: str, directed: bool, workers: int = 27, into: str | None = None) -> DataFrame:
    """The triangles of a view (src, dst)."""
    out = list_triangles(Graph.of(spark.table(view), workers, directed))
    if into:
        out.createOrReplaceTempView(into)
    return out

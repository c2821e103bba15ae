"""Where the non-zeros are: profiles, totals and the number of elementary products."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsegrid.model import SparseMatrix


def nnz_profile(a: SparseMatrix, axis: str) -> DataFrame:
    """(id, nz) of the lines along ``axis`` ('row' or 'col') that hold something; counted before the exchange."""
    return a.df.groupBy(F.col(axis).alias("id")).agg(F.count("*").alias("nz"))


@dataclass(frozen=True)
class Totals:
    """Entries of both factors, elementary products, pages in use and the longest page of each factor."""

    nz_s: int
    nz_t: int
    products: int
    pages_s: int = 0
    pages_t: int = 0
    longest_s: int = 0
    longest_t: int = 0


def totals(s: SparseMatrix, t: SparseMatrix) -> Totals:
    """What the planner needs to know of the factors of S T: a few scalars in one job."""
    cols, rows = nnz_profile(s, "col"), nnz_profile(t, "row")
    both = cols.select("id", F.col("nz").alias("s")).join(rows.select("id", F.col("nz").alias("t")), "id", "full")
    r = both.agg(F.sum("s"), F.sum("t"), F.sum(F.col("s").cast("decimal(38,0)") * F.col("t")), F.count("s"), F.count("t"), F.max("s"), F.max("t")).first()
    return Totals(*(int(x or 0) for x in r))

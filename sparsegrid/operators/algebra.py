"""Element-wise operations, reductions, traces, powers and chains."""

from __future__ import annotations

from collections.abc import Callable, Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from sparsegrid.model import SparseMatrix
from sparsegrid.operators.multiply import sparse_multiply
from sparsegrid.plans.lineage import cut_lineage


def add(a: SparseMatrix, b: SparseMatrix) -> SparseMatrix:
    """Element-wise plus of the semiring."""
    out = a.df.select("row", "col", "val").union(b.df.select("row", "col", "val")).groupBy("row", "col").agg(a.semiring.plus(F.col("val")).alias("val"))
    return a.with_df(out.where(a.semiring.present(F.col("val"))))


def subtract(a: SparseMatrix, b: SparseMatrix) -> SparseMatrix:
    """Element-wise difference of numbers; places that cancel are not stored."""
    return add(a, b.with_df(b.df.withColumn("val", -F.col("val"))))


def hadamard(a: SparseMatrix, b: SparseMatrix) -> SparseMatrix:
    """Element-wise times of the semiring."""
    both = a.df.select("row", "col", F.col("val").alias("x")).join(b.df.select("row", "col", F.col("val").alias("y")), ["row", "col"])
    out = both.select("row", "col", a.semiring.times(F.col("x"), F.col("y")).alias("val"))
    return a.with_df(out.where(a.semiring.present(F.col("val"))))


def kron(a: SparseMatrix, b: SparseMatrix) -> SparseMatrix:
    """Kronecker product with the small matrix ``b``, whose entries travel as one array column."""
    inner = b.df.agg(F.collect_list(F.struct("row", "col", "val")).alias("inner"))
    out = a.df.crossJoin(F.broadcast(inner)).select("row", "col", "val", F.explode("inner").alias("i"))
    out = out.select((F.col("row") * b.n_rows + F.col("i.row")).alias("row"), (F.col("col") * b.n_cols + F.col("i.col")).alias("col"), a.semiring.times(F.col("val"), F.col("i.val")).alias("val"))
    return SparseMatrix(out, a.n_rows * b.n_rows, a.n_cols * b.n_cols, a.semiring)


def scale(a: SparseMatrix, factor: Column) -> SparseMatrix:
    return a.map_values(a.semiring.times(F.col("val"), factor))


def prune(a: SparseMatrix, predicate: Column) -> SparseMatrix:
    return a.with_df(a.df.where(predicate))


def submatrix(a: SparseMatrix, rows: tuple[int, int], cols: tuple[int, int]) -> SparseMatrix:
    """Entries with ids in two half-open ranges."""
    inside = F.col("row").between(rows[0], rows[1] - 1) & F.col("col").between(cols[0], cols[1] - 1)
    return SparseMatrix(a.df.where(inside), rows[1] - rows[0], cols[1] - cols[0], a.semiring)


def diagonal(a: SparseMatrix) -> DataFrame:
    return a.df.where("row = col").select(F.col("row").alias("id"), "val")


def upper(a: SparseMatrix) -> SparseMatrix:
    return a.with_df(a.df.where("row < col"))


def row_sums(a: SparseMatrix, axis: str = "row") -> DataFrame:
    """(id, val): plus over each line."""
    return a.df.groupBy(F.col(axis).alias("id")).agg(a.semiring.plus(F.col("val")).alias("val"))


def column_of_ones(a: SparseMatrix) -> SparseMatrix:
    """The column (col 0) of the semiring's ones at the columns of A that hold something: A times it holds A's row sums."""
    one = F.lit(a.semiring.one).cast(a.semiring.kind).alias("val")
    return SparseMatrix(a.df.select(F.col("col").alias("row"), F.lit(0).cast("bigint").alias("col"), one).distinct(), a.n_cols, 1, a.semiring, a.wide)


def trace_of_product(a: SparseMatrix, b: SparseMatrix) -> DataFrame:
    """One row: the trace of A B, from the entries that face each other; the product is never formed."""
    x, y = a.df.select("row", "col", F.col("val").alias("x")), b.df.select(F.col("col").alias("row"), F.col("row").alias("col"), F.col("val").alias("y"))
    return x.join(y, ["row", "col"]).agg(F.coalesce(F.sum(F.col("x") * F.col("y")), F.lit(0)).cast("bigint").alias("trace"))


def trace_of_square_symmetric(a: SparseMatrix) -> DataFrame:
    """The same for a symmetric A with itself: a sum of squares, without any join."""
    return a.df.agg(F.coalesce(F.sum(F.col("val") * F.col("val")), F.lit(0)).cast("bigint").alias("trace"))


def power(a: SparseMatrix, q: int, multiply=sparse_multiply) -> SparseMatrix:
    """A to the q-th, raised by one sparse factor at a time; every step is cut in the checkpoint folder."""
    if q < 1:
        raise ValueError("the exponent is at least 1")
    out = a
    for _ in range(q - 1):
        out = multiply(out, a).cut()
    return out


def multiply_chain(factors: Sequence[SparseMatrix], multiply=sparse_multiply) -> SparseMatrix:
    """The product of several matrices, associated so that the cheaper neighbours meet first by their profiles."""
    from sparsegrid.operators.stats import totals

    left = list(factors)
    while len(left) > 1:
        k = min(range(len(left) - 1), key=lambda i: totals(left[i], left[i + 1]).products) if len(left) > 2 else 0
        left[k : k + 2] = [multiply(left[k], left[k + 1]).cut() if len(left) > 2 else multiply(left[k], left[k + 1])]
    return left[0]


def top_k(df: DataFrame, by: str, k: int, per: str | None = None, ties: Sequence[str] = ()) -> DataFrame:
    """The k rows with the largest ``by`` (for each value of ``per``), ties in the order of other columns."""
    order = [F.col(by).desc(), *map(F.col, ties)]
    if per is None:
        return df.orderBy(*order).limit(k)
    return df.withColumn("k_", F.row_number().over(Window.partitionBy(per).orderBy(*order))).where(F.col("k_") <= k).drop("k_")


def top_products(lengths_s: DataFrame, lengths_t: DataFrame, product: Callable[[DataFrame, DataFrame], DataFrame], k: int, ties: Sequence[str] = ("row", "col")) -> DataFrame:
    """The k largest entries of a product of matrices without negative entries, exactly, from as few lines as can hold them.

    ``lengths_s`` and ``lengths_t`` are (id, length): at least the Euclidean
    length of each row of S and column of T, whose product no entry exceeds.
    ``product`` makes the entries (row, col, val) of the lines (id) given.  The
    longest lines are multiplied first; their k-th largest entry bars the lines
    that cannot reach it with the longest of the other side.  Lines that can are
    all multiplied, so equals of that entry are among them.
    """
    s, t = cut_lineage(lengths_s), cut_lineage(lengths_t)
    longest = lambda x: x.orderBy(F.col("length").desc(), "id").limit(4 * k)
    first = product(cut_lineage(longest(s)), cut_lineage(longest(t))).select("val").orderBy(F.col("val").desc()).limit(k).collect()
    bar = first[-1]["val"] if len(first) == k else 0
    most_s, most_t = (float(x.agg(F.max("length")).first()[0] or 0) for x in (s, t))
    reach = lambda x, most: x.where(F.col("length") * most * (1 + 1e-9) >= float(bar))
    return top_k(product(reach(s, most_t), reach(t, most_s)), "val", k, ties=ties)


def compact_ids(df: DataFrame, key: str) -> DataFrame:
    """(id, pos): the distinct values of a BIGINT column numbered from 0 in their order."""
    from sparsegrid.operators.ranking import ranked

    ids = df.select(F.col(key).alias("id")).distinct().withColumn("one", F.lit(1))
    return ranked(ids, "id", "one").select("id", F.col("rank").alias("pos"))


def with_identity(a: SparseMatrix, ids: DataFrame) -> SparseMatrix:
    """A with the semiring's one on the diagonal of the ids (id) given."""
    own = ids.select(F.col("id").alias("row"), F.col("id").alias("col"), F.lit(a.semiring.one).cast(a.semiring.kind).alias("val"))
    return add(a, a.with_df(own))


def compare(a: SparseMatrix, b: SparseMatrix) -> DataFrame:
    """(row, col, x, y): the places where two matrices differ."""
    both = a.df.select("row", "col", F.col("val").alias("x")).join(b.df.select("row", "col", F.col("val").alias("y")), ["row", "col"], "full")
    return both.where(~F.col("x").eqNullSafe(F.col("y")))


def stored(a: SparseMatrix) -> SparseMatrix:
    return a.with_df(cut_lineage(a.df))

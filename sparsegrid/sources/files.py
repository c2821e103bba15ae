"""Reading and writing matrices and edge lists as files."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sparsegrid.functions.semiring import PLUS_TIMES, Semiring
from sparsegrid.model import SparseMatrix

_SCHEMA = "src bigint, dst bigint, w double"


def read_edges(spark: SparkSession, path: str, fmt: str) -> DataFrame:
    """(src, dst, w) from csv, json, orc, parquet or Matrix Market coordinate text (ids there count from 1)."""
    if fmt == "csv":
        return spark.read.csv(path, schema=_SCHEMA)
    if fmt == "json":
        return spark.read.json(path, schema=_SCHEMA)
    if fmt in ("orc", "parquet"):
        return spark.read.format(fmt).load(path).select("src", "dst", "w")
    if fmt == "mtx":
        lines = spark.read.text(path).where("NOT value LIKE '\\%%' AND trim(value) <> ''")
        part = F.split(F.trim("value"), r"\s+")
        body = lines.select(part[0].cast("bigint").alias("a"), part[1].cast("bigint").alias("b"), F.try_element_at(part, F.lit(3)).alias("c"))
        # the size line comes first; it is the only one whose third field counts entries, so it is told by its place
        size = spark.read.text(path, wholetext=False).where("NOT value LIKE '\\%%'").limit(1)
        first = size.select(F.split(F.trim("value"), r"\s+").alias("s")).first()["s"]
        rows = body.withColumn("is_size", (F.col("a") == int(first[0])) & (F.col("b") == int(first[1])) & (F.col("c") == first[2]))
        return rows.where("NOT is_size").select((F.col("a") - 1).alias("src"), (F.col("b") - 1).alias("dst"), F.coalesce(F.col("c").cast("double"), F.lit(1.0)).alias("w"))
    raise ValueError(f"unknown format {fmt}")


def write_matrix(a: SparseMatrix, path: str, bands: int | None = None) -> None:
    """Parquet, by default as it is; with ``bands`` partitioned by row band, so readers of a band skip the rest."""
    if bands:
        a.df.withColumn("band", F.pmod("row", F.lit(bands))).write.mode("overwrite").partitionBy("band").parquet(path)
    else:
        a.df.write.mode("overwrite").parquet(path)


def read_matrix(spark: SparkSession, path: str, n_rows: int, n_cols: int, semiring: Semiring = PLUS_TIMES) -> SparseMatrix:
    return SparseMatrix.of(spark.read.parquet(path).select("row", "col", "val"), n_rows, n_cols, semiring)


def save_bucketed(a: SparseMatrix, table: str, buckets: int, axis: str = "row") -> None:
    """A table bucketed by one axis: products on it need no exchange of this side."""
    a.df.write.mode("overwrite").bucketBy(buckets, axis).sortBy(axis).saveAsTable(table)


def row_vectors(a: SparseMatrix) -> DataFrame:
    """(row, entries): each row as a map from column to value."""
    return a.df.groupBy("row").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("col", "val")))).alias("entries"))


def generate(spark: SparkSession, kind: str, n: int, density: float = 0.1, seed: int = 1) -> DataFrame:
    """(src, dst) of a star, path, complete graph, band matrix or seeded random matrix, made on the executors."""
    if kind == "star":
        return spark.range(1, n + 1).select(F.lit(0).cast("bigint").alias("src"), F.col("id").alias("dst"))
    if kind == "path":
        return spark.range(n - 1).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"))
    cells = spark.range(n * n).select(F.floor(F.col("id") / n).alias("src"), (F.col("id") % n).alias("dst"))
    if kind == "complete":
        return cells.where("src <> dst")
    if kind == "band":
        return cells.where("abs(src - dst) <= 1")
    if kind == "random":
        return cells.where(F.pmod(F.xxhash64("src", "dst", F.lit(seed)), F.lit(1_000_000)) < int(density * 1_000_000))
    raise ValueError(f"unknown kind {kind}")

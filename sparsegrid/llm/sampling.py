"""Bounded, reproducible samples of labelled texts for fitting a classifier."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def training_labels(labels: DataFrame, label: str, fold: tuple[int, int]) -> DataFrame:
    """(doc_id, label): one label, 0 or 1, for each id outside the held-out fold.

    The fold holds the ids whose ``crc32(doc_id as text) mod fold[0]`` is
    ``fold[1]``.  Unknown ids and labels are passed over; an id that is labelled
    differently has the larger label.
    """
    key = labels.where(F.col("doc_id").isNotNull() & F.col(label).isin(0, 1)).select(F.col("doc_id").cast("long").alias("doc_id"), F.col(label).cast("int").alias("label"))
    return key.where(F.crc32(F.col("doc_id").cast("string")) % fold[0] != fold[1]).groupBy("doc_id").agg(F.max("label").alias("label"))


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, fold: tuple[int, int], max_rows: int, max_bytes: int, seed: int) -> DataFrame:
    """(doc_id, label, text) of labelled rows outside the held-out fold, bounded in rows and bytes.

    Each class has half of ``max_rows`` and half of ``max_bytes``.  Its ids are
    taken in the order of a seeded hash, so the sample does not depend on
    partitions; texts of more than a 32nd of the class's bytes come after all
    others, the shorter first, so a very long text cannot use up the budget; the
    first text of a class is taken whatever its length, so no class is lost.
    Texts are measured before any is moved.  Of rows that share an id the
    shortest text is used, of equally long ones the first in order; ids without
    text are passed over.
    """
    known = training_labels(labels, label, fold)
    halves = [known.where(F.col("label") == v).orderBy(F.xxhash64("doc_id", F.lit(seed)), "doc_id").limit(max_rows // 2) for v in (0, 1)]
    wanted = F.broadcast(halves[0].union(halves[1]))  # at most max_rows ids and labels
    text = docs.where(F.col("text").isNotNull()).select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    sized = text.select("doc_id", F.octet_length("text").alias("size")).join(wanted, "doc_id").groupBy("doc_id", "label").agg(F.min("size").alias("size"))
    budget = max_bytes // 2
    long = F.col("size") > budget // 32
    order = Window.partitionBy("label").orderBy(long, F.when(long, F.col("size")), F.xxhash64("doc_id", F.lit(seed)), "doc_id")  # at most max_rows small rows
    placed = sized.withColumn("run", F.sum("size").over(order.rowsBetween(Window.unboundedPreceding, 0))).withColumn("place", F.row_number().over(order))
    chosen = F.broadcast(placed.where((F.col("run") <= budget) | (F.col("place") == 1)).select("doc_id", "label", "size"))
    return text.join(chosen, "doc_id").where(F.octet_length("text") == F.col("size")).groupBy("doc_id", "label").agg(F.min("text").alias("text"))


def class_shares(labels: DataFrame, label: str, fold: tuple[int, int]) -> tuple[int, int]:
    """How many training ids are labelled 0 and 1."""
    row = training_labels(labels, label, fold).agg(F.count(F.when(F.col("label") == 0, 1)), F.count(F.when(F.col("label") == 1, 1))).first()
    return int(row[0]), int(row[1])

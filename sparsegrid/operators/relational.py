"""Operators around the methods: subgraphs, edge sets, and joins on time."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from sparsegrid.model import Graph


def induced(g: Graph, ids: DataFrame) -> Graph:
    """The edges with both ends among ``ids`` (v)."""
    one = g.edges.join(ids.select(F.col("v").alias("src")), "src", "left_semi")
    return replace(g, edges=one.join(ids.select(F.col("v").alias("dst")), "dst", "left_semi").select("src", "dst"))


def common_edges(a: Graph, b: Graph) -> DataFrame:
    return a.edges.join(b.edges, ["src", "dst"], "left_semi")


def missing_edges(a: Graph, b: Graph) -> DataFrame:
    """Edges of ``a`` that ``b`` lacks."""
    return a.edges.join(b.edges, ["src", "dst"], "left_anti")


def union_edges(a: Graph, b: Graph) -> DataFrame:
    return a.edges.union(b.edges).distinct()


def seconds(ts: str):
    """Whole seconds since 1970 of a timestamp without zone, whatever the session's zone."""
    return F.expr(f"timestampdiff(SECOND, TIMESTAMP_NTZ '1970-01-01 00:00:00', {ts})")


def range_counts(left: DataFrame, right: DataFrame, key: str, width: int) -> DataFrame:
    """``left`` (event_id, ts, key) with ``n``: rows of ``right`` of the same key in the ``width`` seconds before.

    Both sides carry the number of their time bucket of that width; a left row
    can only meet rows of its own bucket and the one before, so the join is an
    equi-join with a filter behind it.
    """
    a = left.select("event_id", F.col(key).alias("k"), "ts", F.explode(F.array(F.floor(seconds("ts") / width), F.floor(seconds("ts") / width) - 1)).alias("b"))
    b = right.select(F.col(key).alias("k"), F.col("ts").alias("t"), F.floor(seconds("ts") / width).alias("b"))
    met = a.join(b, ["k", "b"]).where(f"t < ts AND t >= ts - INTERVAL '{width}' SECOND").groupBy("event_id").agg(F.count("*").alias("n"))
    return left.join(met, "event_id", "left").select("event_id", F.coalesce("n", F.lit(0)).alias("n"))


def asof(left: DataFrame, right: DataFrame, key: str) -> DataFrame:
    """``left`` (event_id, ts, key) with ``before``: the id of the last row of ``right`` strictly before it, the largest of equals.

    One union sorted by key and time; the last right row is carried forward, so
    no row meets more than its predecessor.
    """
    both = left.select(F.col(key).alias("k"), "ts", F.col("event_id").alias("id"), F.lit(0).alias("side")).union(right.select(F.col(key).alias("k"), "ts", F.col("event_id").alias("id"), F.lit(1).alias("side")))
    # at one time left rows come first, so they see strictly earlier ones
    w = Window.partitionBy("k").orderBy("ts", "side", "id").rowsBetween(Window.unboundedPreceding, 0)
    carried = both.withColumn("before", F.last(F.when(F.col("side") == 1, F.col("id")), ignorenulls=True).over(w))
    return carried.where("side = 0").select(F.col("id").alias("event_id"), "before")

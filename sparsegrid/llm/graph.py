"""Connected components of a link table, by union-find in the partitions and an exchange by child.

An edge is (child, parent) with the parent the smaller.  Every round deals the
edges by child, and each partition joins what its edges connect: every vertex it
holds is then an edge to the smallest of its part.  A child gets at most one edge
from each partition, so a hub is no hot key; parents are never a key.  When no
partition has joined two parents any more, every vertex has one parent, and
pointers are doubled until they end at the roots.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsegrid.plans.lineage import cut_and_release

EDGES = "child long, parent long"


def local_roots(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The distinct vertices of the edges (a, b) and the smallest vertex that each is connected with."""
    ids, place = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = place[: len(a)], place[len(a) :]
    root = np.arange(len(ids))
    while True:
        low, high = np.minimum(root[x], root[y]), np.maximum(root[x], root[y])
        apart = low != high
        if not apart.any():
            return ids, ids[root]
        np.minimum.at(root, high[apart], low[apart])
        while (root[root] != root).any():
            root = root[root]


def forest_of(a: np.ndarray, b: np.ndarray) -> pa.RecordBatch:
    """The edges (child, parent) that connect the same vertices as (a, b), one for each vertex but the roots."""
    ids, root = local_roots(a, b)
    below = ids != root
    return pa.RecordBatch.from_arrays([pa.array(ids[below]), pa.array(root[below])], ["child", "parent"])


def _held(batches) -> tuple[np.ndarray, np.ndarray]:
    parts = [(b.column(0).to_numpy(), b.column(1).to_numpy()) for b in batches]
    return tuple(np.concatenate([p[k] for p in parts] or [np.zeros(0, np.int64)]) for k in (0, 1))


def local_forest(batches):
    """An edge (child, parent) for every vertex of a partition's links but the roots."""
    yield forest_of(*_held(batches))


def _joined(batches):
    """The same, with ``open`` for edges whose child was no child in this partition."""
    child, parent = _held(batches)
    out = forest_of(child, parent)
    new = ~np.isin(out.column(0).to_numpy(), child)
    yield pa.RecordBatch.from_arrays([*out.columns, pa.array(new)], ["child", "parent", "open"])


def components_of(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(vertex, label) from edges (child, parent): the smallest vertex that can be reached; roots do not appear."""
    for _ in range(max_rounds):
        edges = cut_and_release(edges.select("child", "parent").repartition("child").mapInArrow(_joined, f"{EDGES}, open boolean"))
        if edges.where("open").isEmpty():
            break
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    up = edges.select("child", "parent")
    for _ in range(max_rounds):
        above = up.select(F.col("child").alias("parent"), F.col("parent").alias("root"))
        up = cut_and_release(up.join(above.hint("merge"), "parent", "left").select("child", F.coalesce("root", "parent").alias("parent"), F.col("root").isNotNull().alias("moved")))
        if up.where("moved").isEmpty():
            return up.select(F.col("child").alias("vertex"), F.col("parent").alias("label"))
        up = up.select("child", "parent")
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")


def components(links: DataFrame) -> DataFrame:
    """(vertex, label) of all vertices with links (a, b: BIGINT, no nulls), roots included."""
    edges = links.where("a <> b").select("a", "b").mapInArrow(local_forest, EDGES)
    found = components_of(edges)
    return found.union(found.select(F.col("label").alias("vertex"), "label").distinct())

"""Triangles of similar vectors, counted from tiles of the similarities; no pair is ever stored."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

_SIDE = 1024  # vectors of a side of a tile


def _linked(x: np.ndarray, y: np.ndarray, size_x: np.ndarray, size_y: np.ndarray, least: float) -> np.ndarray:
    """A tile of ones where the inner product reaches ``least`` times both lengths; products close to that are summed in order of the places."""
    inner, bar = x @ y.T, least * size_x[:, None] * size_y[None, :]
    i, j = np.nonzero(np.abs(inner - bar) <= 1e-9 * size_x[:, None] * size_y[None, :])
    if len(i):
        inner[i, j] = np.cumsum(x[i] * y[j], axis=1)[:, -1]
    return (~(inner < bar)).astype(np.float32)


def _triangles(vectors: np.ndarray, band: int, least: float, side: int) -> int:
    """Triangles whose first vector lies in a band of ``side`` vectors, in their order."""
    size = np.sqrt(np.cumsum(vectors * vectors, axis=1)[:, -1])
    cut = [slice(a, min(a + side, len(vectors))) for a in range(0, len(vectors), side)]

    def tile(a: int, b: int) -> np.ndarray:
        one = _linked(vectors[cut[a]], vectors[cut[b]], size[cut[a]], size[cut[b]], least)
        return np.triu(one, 1) if a == b else one

    total = 0
    line = [tile(band, b) for b in range(band, len(cut))]
    for j in range(band, len(cut)):
        for k in range(j, len(cut)):
            # a float of 32 bits holds a tile's counts of paths exactly
            total += int(np.sum((line[j - band] @ tile(j, k)) * line[k - band], dtype=np.float64))
    return total


def similar_triangles(df: DataFrame, label: str, key: str, vector: str, least: float, side: int = _SIDE) -> DataFrame:
    """(label, triangles): the sets of three vectors of a label that are similar in pairs; labels without any are left out.

    Keys are unique.  A label's vectors go to a task for each ``side`` of them,
    which counts the triangles that begin there.  Vectors that hold a null, and
    pairs of different lengths, are not similar.
    """
    whole = df.where(F.col(label).isNotNull() & F.col(key).isNotNull() & F.forall(vector, lambda x: x.isNotNull()) & (F.size(vector) > 0))
    held = whole.select(F.col(label).alias("label"), F.size(vector).alias("width"), F.col(key).cast("bigint").alias("key"), F.col(vector).alias("vector"))
    counts = held.groupBy("label", "width").agg(F.count("*").alias("n"))
    bands = counts.select("label", "width", F.explode(F.sequence(F.lit(0), (F.ceil(F.col("n") / side) - 1).cast("int"))).alias("band"))
    dealt = held.join(F.broadcast(bands), ["label", "width"])
    kind = held.schema["label"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = pa.Table.from_batches(list(batches))
        order = np.argsort(table["key"].to_numpy(), kind="stable")
        vectors = table["vector"].combine_chunks().flatten().to_numpy().astype(np.float64).reshape(len(order), -1)[order]
        found = _triangles(vectors, table["band"][0].as_py(), least, side)
        yield pa.RecordBatch.from_arrays([table["label"].slice(0, 1).combine_chunks(), pa.array([found], pa.int64())], ["label", "triangles"])

    each = dealt.groupBy("label", "width", "band").applyInArrow(run, f"label {kind}, triangles bigint")
    return each.groupBy("label").agg(F.sum("triangles").alias("triangles")).where("triangles > 0")

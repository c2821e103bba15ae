"""What workers take in of a matrix's product with its transpose, counted from packed lines.

A line is a page of the product, and the ids it holds are dealt to bands, the
same for rows and columns.  A page is its counts by bands; as those of blocks
(i, j) and (j, i) are the same, blocks on and above the diagonal are weighed.
Ranks come from histograms of the weights in each range of pages, so pages are
dealt where they lie, and only histograms are exchanged.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsegrid.operators.gram import Lines, _quantiles, pack, unpack
from sparsegrid.plans.lineage import cut_and_release, cut_lineage

BANDS = ("stride", "adjacent")
PAGES = ("stride", "ranges")


def held_by(lines: Lines) -> tuple[np.ndarray, np.ndarray]:
    """(ids, counts) of what lines hold, in order of the ids, on the driver; counts are summed by ranges of ids before."""
    spark = lines.df.sparkSession
    cuts = _quantiles(*lines.near, int(spark.conf.get("spark.sql.shuffle.partitions")))
    names = ["band", "ids", "counts"]

    def row(band, ids, counts):
        return pa.RecordBatch.from_arrays([pa.array([band], pa.int32()), pa.array([pack(ids)]), pa.array([pack(counts)])], names)

    def counted(batches):
        for batch in batches:
            for near in batch.column(0).to_pylist():
                ids, counts = np.unique(unpack(near), return_counts=True)
                ends = [0, *np.searchsorted(ids, cuts).tolist(), len(ids)]
                for k in range(len(ends) - 1):
                    if ends[k] < ends[k + 1]:
                        yield row(k, ids[ends[k] : ends[k + 1]], counts[ends[k] : ends[k + 1]])

    def summed(batches):
        got = [(unpack(i), unpack(c)) for batch in batches for i, c in zip(*(batch.column(k).to_pylist() for k in (1, 2)), strict=True)]
        if got:
            ids, at = np.unique(np.concatenate([i for i, _ in got]), return_inverse=True)
            counts = np.zeros(len(ids), np.int64)
            np.add.at(counts, at, np.concatenate([c for _, c in got]))
            yield row(0, ids, counts)

    schema = "band int, ids binary, counts binary"
    found = lines.df.select("near").mapInArrow(counted, schema).repartitionById(len(cuts) + 1, F.col("band")).mapInArrow(summed, schema).collect()
    ids, counts = (np.concatenate([unpack(r[c]) for r in found] or [np.zeros(0, np.int64)]) for c in ("ids", "counts"))
    order = np.argsort(ids, kind="stable")
    return ids[order], counts[order]


def bands_of(counts: np.ndarray, side: int) -> list[np.ndarray]:
    """The bands of ids, which are in order, by each way of ``BANDS``: dealt in the order of counts, or equally many adjacent ids."""
    n = len(counts)
    dealt = np.zeros(n, np.uint8)
    dealt[np.argsort(counts, kind="stable")] = (np.arange(n) + -n % side) % side
    return [dealt, (np.arange(n) * side // max(n, 1)).astype(np.uint8)]


def loads_by_dealing(lines: Lines, side: int, most: int = 1 << 24) -> DataFrame | None:
    """(bands, pages, bi, bj, slot, w, p): entries that each worker of a cube of ``side`` bands and hands receives, and its products, by each way to deal bands and pages.

    Blocks with bi > bj are left out.  Tasks are told the bands of at most
    ``most`` ids; of more None is returned.
    """
    spark = lines.df.sparkSession
    ids, counts = held_by(lines)
    if len(ids) > most:
        return None
    told = spark.sparkContext.broadcast((pack(ids), [b.tobytes() for b in bands_of(counts, side)]))
    seen: list = []
    blocks = [(i, j) for i in range(side) for j in range(i, side)]

    def first_ids(batches):
        for batch in batches:
            for cell in batch.column(0).to_pylist():
                yield pa.RecordBatch.from_arrays([pa.array(unpack(cell)[:1])], ["first"])

    starts = np.array(sorted(r["first"] for r in lines.df.select("ids").mapInArrow(first_ids, "first bigint").collect()), np.int64)

    def by_bands(batches):
        if not seen:
            seen.extend((unpack(told.value[0]), [np.frombuffer(b, np.uint8) for b in told.value[1]]))
        known, bands = seen
        for batch in batches:
            for row in batch.to_pylist():
                sizes, at = unpack(row["sizes"]), np.searchsorted(known, unpack(row["near"]))
                line, piece = np.repeat(np.arange(len(sizes)) * side, sizes), int(np.searchsorted(starts, unpack(row["ids"])[0]))
                for k, band in enumerate(bands):
                    c = np.bincount(line + band[at], minlength=len(sizes) * side).reshape(-1, side).T
                    yield pa.RecordBatch.from_arrays([pa.array([piece], pa.int32()), pa.array([k], pa.int32()), pa.array([pack(c.ravel())])], ["piece", "kind", "c"])

    pages = cut_and_release(lines.df.mapInArrow(by_bands, "piece int, kind int, c binary"), rounds=3)

    def weighed(c, i, j):
        """The pages that a block receives, and their weights."""
        c = unpack(c).reshape(side, -1)
        w = c[i] + c[j]
        at = np.flatnonzero(w)
        return w[at], c[i][at] * c[j][at]

    def histograms(batches):
        for batch in batches:
            for row in batch.to_pylist():
                for b, (i, j) in enumerate(blocks):
                    u, k = np.unique(weighed(row["c"], i, j)[0], return_counts=True)
                    yield pa.RecordBatch.from_arrays([pa.array([row["kind"] * len(blocks) + b], pa.int32()), pa.array([row["piece"]], pa.int32()), pa.array([pack(u)]), pa.array([pack(k)])], ["block", "piece", "u", "k"])

    def ranks(batches):
        got = sorted(((r["piece"], r["block"], unpack(r["u"]), unpack(r["k"])) for batch in batches for r in batch.to_pylist()), key=lambda r: r[0])
        if not got:
            return
        weights = np.unique(np.concatenate([u for _, _, u, _ in got]))
        number = np.zeros(len(weights), np.int64)
        for _, _, u, k in got:
            number[np.searchsorted(weights, u)] += k
        n, before = int(number.sum()), 0
        rank = np.cumsum(number) - number
        for piece, block, u, k in got:
            at = np.searchsorted(weights, u)
            cells = [pa.array([piece], pa.int32()), pa.array([block], pa.int32()), pa.array([pack(u)]), pa.array([pack(rank[at])]), pa.array([before]), pa.array([n])]
            yield pa.RecordBatch.from_arrays(cells, ["piece", "kind", "c", "rank", "before", "n"])
            rank[at] += k
            before += int(k.sum())

    def dealt(batches):
        tables, told_ranks = [], []
        for batch in batches:
            for row in batch.to_pylist():
                (tables if row["rank"] is None else told_ranks).append(row)
        own = {row["kind"]: row["c"] for row in tables}
        for row in told_ranks:
            kind, (i, j) = row["kind"] // len(blocks), blocks[row["kind"] % len(blocks)]
            w, p = weighed(own[kind], i, j)
            order = np.argsort(w, kind="stable")
            u, k = np.unique(w, return_counts=True)
            rank = np.empty(len(w), np.int64)
            rank[order] = np.arange(len(w)) + np.repeat(unpack(row["rank"]) - (np.cumsum(k) - k), k)
            n, out = row["n"], []
            for way, slot in zip(PAGES, ((rank + -n % side) % side, (row["before"] + np.arange(len(w))) * side // max(n, 1)), strict=True):
                for s in range(side):
                    at = slot == s
                    out.append({"bands": BANDS[kind], "pages": way, "bi": i, "bj": j, "slot": s, "w": int(w[at].sum()), "p": int(p[at].sum())})
            yield pa.RecordBatch.from_pylist(out)

    counted = pages.mapInArrow(histograms, "block int, piece int, u binary, k binary").repartitionById(len(BANDS) * len(blocks), F.col("block"))
    wide = "piece int, kind int, c binary, rank binary, before bigint, n bigint"
    ranked = counted.mapInArrow(ranks, wide)
    met = pages.selectExpr("piece", "kind", "c", "CAST(NULL AS BINARY) AS rank", "CAST(NULL AS BIGINT) AS before", "CAST(NULL AS BIGINT) AS n").union(ranked)
    loads = met.repartitionById(max(len(starts), 1), F.col("piece")).mapInArrow(dealt, "bands string, pages string, bi bigint, bj bigint, slot bigint, w bigint, p bigint")
    return cut_lineage(loads.groupBy("bands", "pages", "bi", "bj", "slot").agg(F.sum("w").alias("w"), F.sum("p").alias("p")))

"""Products of a matrix's transpose with itself from packed lines, in blocks of the result that each stay in one task.

A line is a page of the product: the places of a block get something from it
where it holds ids of both the block's bands.  Bands are ranges of ids, so lines
whose ids are near to each other go to few blocks.  Lines travel and are stored
as differences of their ids, compressed; results are summed, counted or told
where they are made, and are never exchanged.  For the matrix of an undirected
graph the product is its square.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass
from decimal import Decimal

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsegrid.model import Graph, SparseMatrix
from sparsegrid.plans.lineage import cut_and_release, release

_PACKED = 1 << 21  # entries that are packed together
_BAND = 1 << 20  # entries of a band of lines
_TASK = 1 << 22  # entries of a list that a block takes, if its lines allow it
_STRIP = 1 << 19  # elementary products that a strip of several rows makes
_PLACES = 1 << 20  # places of a strip that is an array
_SAMPLE = 1 << 10  # ids of a packet that tell where bands begin
_SIDES = (4, 16, 64)  # numbers of bands that are weighed


def pack(a: np.ndarray) -> bytes:
    """Integers as compressed differences; any BIGINT comes back, as sums wrap where differences did."""
    d = np.diff(np.asarray(a, np.int64), prepend=np.int64(0))
    z = ((d << 1) ^ (d >> 63)).view(np.uint64)
    most = int(z.max(initial=0))
    width = next(w for w in (1, 2, 4, 8) if most < 1 << (8 * w))
    planes = np.ascontiguousarray(z.astype(f"<u{width}").view(np.uint8).reshape(-1, width).T)
    return bytes([width]) + len(z).to_bytes(8, "little") + pa.compress(planes.tobytes(), codec="zstd", asbytes=True)


def unpack(b: bytes) -> np.ndarray:
    width, n = b[0], int.from_bytes(b[1:9], "little")
    planes = np.frombuffer(pa.decompress(b[9:], decompressed_size=n * width, codec="zstd"), np.uint8)
    z = np.ascontiguousarray(planes.reshape(width, n).T).view(f"<u{width}").ravel().astype(np.uint64)
    return np.cumsum((z >> np.uint64(1)).view(np.int64) ^ -(z & np.uint64(1)).view(np.int64))


def _sorted(a: np.ndarray, b: np.ndarray, x: np.ndarray | None) -> tuple[np.ndarray, np.ndarray, np.ndarray | None]:
    """Pairs in order; without values each once."""
    if not len(a):
        return a, b, x
    low_a, low_b = int(a.min()), int(b.min())
    bits = (int(b.max()) - low_b).bit_length()
    if (int(a.max()) - low_a).bit_length() + bits < 63:
        key = ((a - low_a) << bits) | (b - low_b)
        if x is None:
            key = np.sort(key)
            key = key[np.concatenate(([True], key[1:] != key[:-1]))]
        else:
            order = np.argsort(key, kind="stable")
            key, x = key[order], x[order]
        return (key >> bits) + low_a, (key & ((1 << bits) - 1)) + low_b, x
    order = np.lexsort((b, a))
    a, b = a[order], b[order]
    if x is not None:
        return a, b, x[order]
    kept = np.flatnonzero(np.concatenate(([True], (np.diff(a) != 0) | (np.diff(b) != 0))))
    return a[kept], b[kept], None


def _quantiles(ids: np.ndarray, weights: np.ndarray, count: int) -> np.ndarray:
    """At most ``count`` - 1 ids at which ranges of about equal weight begin."""
    order = np.argsort(ids, kind="stable")
    ids, at = ids[order], np.cumsum(weights[order])
    return np.unique(ids[np.searchsorted(at, at[-1] * np.arange(1, count) / count).clip(0, len(ids) - 1)]) if len(ids) else ids


def _ranked(ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The distinct ids in order, and the place of each among them."""
    low = int(ids.min())
    span = int(ids.max()) - low + 1
    if span > 4 * len(ids):
        return np.unique(ids, return_inverse=True)
    there = np.zeros(span, bool)
    there[ids - low] = True
    return np.flatnonzero(there) + low, (np.cumsum(there) - 1)[ids - low]


def _pick(start: np.ndarray, size: np.ndarray) -> np.ndarray:
    """The places of runs one after another."""
    return np.arange(size.sum()) + np.repeat(start - (np.cumsum(size) - size), size)


@dataclass(frozen=True)
class Lines:
    """``df``: (ids, sizes, near, vals), one row for each range of lines, all packed; ``near``: sampled ids that lines hold and their weights."""

    df: DataFrame
    near: tuple[np.ndarray, np.ndarray]
    both: bool
    held: bool

    @classmethod
    def of(cls, pairs: DataFrame, both: bool, held: bool = False) -> Lines:
        """From (line, near), or (line, near, val) if values are ``held``; with ``both`` every pair also the other way, repeats once, none from an id to itself."""
        spark = pairs.sparkSession

        def packed(batches):
            def row(got):
                a, b = (np.concatenate([g.column(i).to_numpy() for g in got]) for i in (0, 1))
                x = np.concatenate([g.column(2).to_numpy() for g in got]) if held else None
                if both:
                    a, b = np.minimum(a, b), np.maximum(a, b)
                    a, b = a[a != b], b[a != b]
                a, b, x = _sorted(a, b, x)
                some = np.linspace(0, len(a) - 1, min(len(a), _SAMPLE)).astype(np.int64)
                cells = [len(a), pack(a[some]), pack(np.sort(b)[some]), pack(a), pack(b), pack(x) if held else b""]
                return pa.RecordBatch.from_arrays([pa.array([c]) for c in cells], ["n", "s", "t", "a", "b", "x"])

            got = []
            for batch in batches:
                got.append(batch)
                if sum(map(len, got)) >= _PACKED:
                    yield row(got)
                    got = []
            if got:
                yield row(got)

        kept = cut_and_release(pairs.mapInArrow(packed, "n bigint, s binary, t binary, a binary, b binary, x binary"), rounds=3)
        told = [r for r in kept.select("n", "s", "t").collect() if r["n"]]
        weights = np.concatenate([np.full(min(r["n"], _SAMPLE), r["n"] / min(r["n"], _SAMPLE)) for r in told] or [np.zeros(0)])
        s, t = (np.concatenate([unpack(r[c]) for r in told] or [np.zeros(0, np.int64)]) for c in ("s", "t"))
        total = sum(r["n"] for r in told) * (2 if both else 1)
        if both:
            s = t = np.concatenate([s, t])
            weights = np.concatenate([weights, weights])
        count = max(int(spark.conf.get("spark.sql.shuffle.partitions")), total // _BAND)
        bounds = _quantiles(s, weights, count)

        def dealt(batches):
            for batch in batches:
                for a, b, x in zip(*(batch.column(c).to_pylist() for c in ("a", "b", "x")), strict=True):
                    a, b, x = unpack(a), unpack(b), unpack(x) if held else None
                    if both:
                        a, b, x = _sorted(np.concatenate([a, b]), np.concatenate([b, a]), None)
                    ends = [0, *np.searchsorted(a, bounds).tolist(), len(a)]
                    for k in range(len(ends) - 1):
                        i, j = ends[k], ends[k + 1]
                        if i < j:
                            yield pa.RecordBatch.from_arrays([pa.array([k], pa.int32()), *(pa.array([c]) for c in (pack(a[i:j]), pack(b[i:j]), pack(x[i:j]) if held else b""))], ["band", "a", "b", "x"])

        def merged(batches):
            got = [tuple(unpack(c) for c in (a, b, *([x] if held else []))) for batch in batches for a, b, x in zip(*(batch.column(c).to_pylist() for c in ("a", "b", "x")), strict=True)]
            if got:
                a, b = (np.concatenate([g[i] for g in got]) for i in (0, 1))
                a, b, x = _sorted(a, b, np.concatenate([g[2] for g in got]) if held else None)
                begin = np.flatnonzero(np.concatenate((np.ones(min(len(a), 1), bool), a[1:] != a[:-1])))
                ids, sizes = a[begin], np.diff(begin, append=len(a))
                yield pa.RecordBatch.from_arrays([pa.array([c]) for c in (pack(ids), pack(sizes), pack(b), pack(x) if held else b"")], ["ids", "sizes", "near", "vals"])

        spread = kept.select("a", "b", "x").mapInArrow(dealt, "band int, a binary, b binary, x binary").repartitionById(len(bounds) + 1, F.col("band"))
        lines = cut_and_release(spread.select("a", "b", "x").mapInArrow(merged, "ids binary, sizes binary, near binary, vals binary"), rounds=3)
        del kept, spread
        release(spark, rounds=3)
        return cls(lines, (t, weights), both, held)

    def known(self) -> tuple[np.ndarray, np.ndarray]:
        """(ids, sizes) of all lines, in order of the ids, on the driver."""
        rows = [(unpack(r["ids"]), unpack(r["sizes"])) for r in self.df.select("ids", "sizes").collect()]
        ids, sizes = (np.concatenate([r[i] for r in rows] or [np.zeros(0, np.int64)]) for i in (0, 1))
        order = np.argsort(ids, kind="stable")
        return ids[order], sizes[order]


def _opened(row: dict, held: bool, keep: Callable | None) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray | None]:
    """(ids, line of each entry, near, vals) of a range of lines, of which ``keep`` (ids, lines, near) tells the entries that count."""
    ids, sizes, near = unpack(row["ids"]), unpack(row["sizes"]), unpack(row["near"])
    line, x = np.repeat(np.arange(len(ids)), sizes), unpack(row["vals"]) if held else None
    if keep is not None:
        kept = keep(ids, line, near)
        line, near = line[kept], near[kept]
    return ids, line, near, x


def _runs(line: np.ndarray, near: np.ndarray, cuts: np.ndarray) -> tuple[np.ndarray, ...]:
    """(start, size, line, band) of the runs of entries of one line and one band."""
    band = np.searchsorted(cuts, near, "right")
    start = np.flatnonzero(np.diff(line * (len(cuts) + 1) + band, prepend=-1))
    return start, np.diff(start, append=len(line)), line[start], band[start]


def _met(line: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs of runs of one line, the earlier or the same one first."""
    for k in range(len(line)):
        i = np.flatnonzero(line[: len(line) - k] == line[k:])
        if not len(i):
            return
        yield i, i + k


def _weighed(lines: Lines, cuts: dict[int, np.ndarray], keep: Callable | None) -> dict[int, dict[int, tuple[int, int]]]:
    """For each number of bands its blocks that hold something, by number: entries taken and elementary products."""
    held = lines.held

    def run(batches):
        for batch in batches:
            for row in batch.to_pylist():
                _, line, near, _ = _opened(row, held, keep)
                for side, at in cuts.items():
                    _, size, of, band = _runs(line, near, at)
                    wide = len(at) + 1
                    taken, made = np.zeros(wide * wide, np.int64), np.zeros(wide * wide, np.int64)
                    for i, j in _met(of):
                        block = band[i] * wide + band[j]
                        np.add.at(taken, block, size[i] + size[j])
                        np.add.at(made, block, size[i] * size[j])
                    block = np.flatnonzero(made)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(block), side)), pa.array(block), pa.array(taken[block]), pa.array(made[block])], ["side", "block", "taken", "made"])

    out: dict[int, dict[int, tuple[int, int]]] = {side: {} for side in cuts}
    for r in lines.df.mapInArrow(run, "side bigint, block bigint, taken bigint, made bigint").groupBy("side", "block").agg(F.sum("taken"), F.sum("made")).collect():
        out[r[0]][r[1]] = (r[2], r[3])
    return out


def _strips(size_i, near_i, x, size_j, near_j, y) -> tuple[np.ndarray, np.ndarray, Iterator]:
    """(row ids, column ids, strips) of a block from its lists by pages; a strip is (first row, array of its places) or (keys, values) of those that hold something."""
    ids_r, r = _ranked(near_i)
    ids_c, c = (ids_r, r) if near_j is near_i else _ranked(near_j)
    order = np.argsort(r, kind="stable")
    page = np.repeat(np.arange(len(size_i)), size_i)[order]
    ends = np.searchsorted(r[order], np.arange(len(ids_r) + 1))
    count, first = size_j[page], (np.cumsum(size_j) - size_j)[page]
    made = np.concatenate(([0], np.cumsum(count)))
    x = None if x is None else x[order]
    wide, most = len(ids_c), 1
    if x is not None:
        most = int(np.abs(x).max(initial=0)) * int(np.abs(y).max(initial=0)) * len(size_i)
        if most >= 1 << 63:  # Python's numbers do not overflow
            x, y = x.astype(object), y.astype(object)
    dense = most < 1 << 53 and made[-1] * 8 >= len(ids_r) * wide
    del r, order

    def strips():
        a = 0
        while a < len(ids_r):
            b = max(a + 1, int(np.searchsorted(made[ends], made[ends[a]] + _STRIP, "right")) - 1)
            b = min(b, a + max(1, _PLACES // wide)) if dense else b
            i, j, start = ends[a], ends[b], a
            of = count[i:j]
            at = _pick(first[i:j], of)
            key = np.repeat(np.repeat(np.arange(start if not dense else 0, b - (start if dense else 0)), np.diff(ends[a : b + 1])) * wide, of) + c[at]
            value = None if x is None else np.repeat(x[i:j], of) * y[at]
            a = b
            if dense:
                yield start, np.bincount(key, value, (b - start) * wide)
            elif value is None:
                yield np.unique(key, return_counts=True)
            else:
                place = np.argsort(key, kind="stable")
                key = key[place]
                begin = np.flatnonzero(np.diff(key, prepend=-1))
                yield key[begin], np.add.reduceat(value[place], begin) if len(begin) else value
    return ids_r, ids_c, strips(), dense


def gram(lines: Lines, make: Callable, schema: str, keep: Callable | None = None, masked: bool = False, cuts: np.ndarray | None = None) -> DataFrame:
    """What ``make`` (blocks) yields, as Arrow batches of ``schema``, of each block of the product of the lines' transpose with the lines.

    The product is symmetric: blocks on and above its diagonal are made.  A
    block is (row ids, column ids, strips, dense, whether it is on the diagonal,
    mask); with ``masked`` the mask holds the places (row id, column id), smaller
    id first, of the entries of all lines, whether or not ``keep`` lets them count.
    ``cuts`` are the ids at which bands begin; by default as many bands as leave
    no block too many entries, and more where that sends lines to few more blocks.
    """
    spark, held = lines.df.sparkSession, lines.held
    if cuts is None:
        tried = {side: _quantiles(*lines.near, side) for side in _SIDES}
        found = _weighed(lines, tried, keep)
        sent = {side: sum(t for t, _ in found[side].values()) for side in _SIDES}
        largest = {side: max((t for t, _ in found[side].values()), default=0) for side in _SIDES}
        fit = next((side for side in _SIDES if largest[side] <= 2 * _TASK), _SIDES[-1])
        side = max((side for side in _SIDES if side >= fit and sent[side] <= 2 * sent[fit]), default=fit)
        cuts, blocks = tried[side], found[side]
    else:
        blocks = _weighed(lines, {0: cuts}, keep)[0]
    wide = len(cuts) + 1
    if not blocks:
        return spark.createDataFrame([], schema)
    ordered = sorted(blocks, key=lambda b: (-blocks[b][1], b))  # the heaviest first
    slot = np.full(wide * wide, -1, np.int64)
    slot[ordered] = np.arange(len(ordered))

    def sent_lines(batches):
        names = ["slot", "kind", "si", "ni", "xi", "sj", "nj", "xj"]

        def out(block, kind, *cells):
            return pa.RecordBatch.from_arrays([pa.array([slot[block]], pa.int32()), pa.array([kind], pa.int32()), *(pa.array([c], pa.binary()) for c in cells)], names)

        for batch in batches:
            for row in batch.to_pylist():
                ids, line, near, x = _opened(row, held, keep)
                start, size, of, band = _runs(line, near, cuts)
                i, j = (np.concatenate(p) for p in zip(*_met(of), strict=True)) if len(of) else (of, of)
                block = band[i] * wide + band[j]
                order = np.argsort(block, kind="stable")
                i, j, block = i[order], j[order], block[order]
                begin = np.flatnonzero(np.diff(block, prepend=-1))
                for p, q in zip(begin, np.append(begin[1:], len(block)), strict=True):
                    cells = []
                    for run in (i[p:q], j[p:q]):
                        at = _pick(start[run], size[run])
                        cells += [pack(size[run]), pack(near[at]), pack(x[at]) if held else b""]
                        if block[p] // wide == block[p] % wide:
                            cells += [b"", b"", b""]
                            break
                    yield out(block[p], 0, *cells)
                if masked:
                    ids, line, near, _ = _opened(row, held, None)
                    up = np.flatnonzero(near > ids[line])
                    a, b = ids[line[up]], near[up]
                    block = np.searchsorted(cuts, a, "right") * wide + np.searchsorted(cuts, b, "right")
                    for k in np.unique(block):
                        if slot[k] >= 0:
                            m = block == k
                            yield out(k, 1, pack(a[m]), pack(b[m]), b"", b"", b"", b"")

    def made(batches):
        lists, mask, own = [], [], True
        for batch in batches:
            for row in batch.to_pylist():
                if row["kind"]:
                    mask.append((unpack(row["si"]), unpack(row["ni"])))
                    continue
                own = not row["sj"]
                lists.append([unpack(row[c]) if row[c] else None for c in ("si", "ni", "xi", "sj", "nj", "xj")])
        if not lists:
            return
        whole = [None if g[0] is None else np.concatenate(g) for g in zip(*lists, strict=True)]
        lists.clear()
        if own:
            whole[3:] = whole[:3]
        places = tuple(np.concatenate(g) for g in zip(*mask, strict=True)) if mask else (np.zeros(0, np.int64),) * 2
        yield from make(*_strips(*whole), own, places)

    kinds = "slot int, kind int, si binary, ni binary, xi binary, sj binary, nj binary, xj binary"
    return lines.df.mapInArrow(sent_lines, kinds).repartitionById(len(ordered), F.col("slot")).mapInArrow(made, schema)


def _number(*values: int) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([Decimal(v)], pa.decimal128(38, 0)) for v in values], [f"v{i}" for i in range(len(values))])


def size_of_gram(lines: Lines, cuts: np.ndarray | None = None) -> DataFrame:
    """One row (nz, total, squares): how many places of the product hold something, their sum and that of their squares."""

    def make(ids_r, ids_c, strips, dense, own, mask):
        nz = total = squares = 0
        for _, c in strips:
            nz += int(np.count_nonzero(c))
            total += int(c.sum())
            squares += int(c @ c)
        twice = 1 if own else 2
        yield _number(twice * nz, twice * total, twice * squares)

    found = gram(lines, make, "v0 decimal(38,0), v1 decimal(38,0), v2 decimal(38,0)", cuts=cuts)
    return found.agg(*[F.sum(f"v{i}").cast("bigint").alias(n) for i, n in enumerate(("nz", "total", "squares"))]).fillna(0, ["nz"])


def count_closed_wedges(lines: Lines, keep: Callable) -> DataFrame:
    """One row (triangles): the pairs of ``keep``'s entries of a line that are an entry of the matrix themselves."""

    def make(ids_r, ids_c, strips, dense, own, mask):
        r, c = np.searchsorted(ids_r, mask[0]), np.searchsorted(ids_c, mask[1])
        there = np.flatnonzero((ids_r[r.clip(max=len(ids_r) - 1)] == mask[0]) & (ids_c[c.clip(max=len(ids_c) - 1)] == mask[1]))
        key, closed = np.sort(r[there] * len(ids_c) + c[there]), 0
        for k, v in strips:
            if dense:
                i, j = np.searchsorted(key, (k * len(ids_c), k * len(ids_c) + len(v)))
                closed += int(v[key[i:j] - k * len(ids_c)].sum())
            elif len(k):
                i, j = np.searchsorted(key, (k[0], k[-1] + 1))
                at = np.searchsorted(k, key[i:j]).clip(max=len(k) - 1)
                closed += int(v[at][k[at] == key[i:j]].sum())
        yield _number(closed)

    return gram(lines, make, "v0 decimal(38,0)", keep, masked=True).agg(F.coalesce(F.sum("v0"), F.lit(0)).cast("bigint").alias("triangles"))


def gram_multiply(a: SparseMatrix) -> SparseMatrix:
    """The transpose of A times A, of whole numbers: exact sums of the semiring's kind, BIGINT or DECIMAL."""
    ring = a.semiring
    if ring.name not in ("plus_times", "decimal_plus_times"):
        raise ValueError("blocks need the sum of whole numbers")
    kind = pa.int64() if ring.kind == "bigint" else pa.decimal128(38, 0)

    def make(ids_r, ids_c, strips, dense, own, mask):
        wide = len(ids_c)
        for k, v in strips:
            at = np.flatnonzero(v)
            key, v = (k * wide + at if dense else k[at]), v[at]
            for i in range(0, len(key), 1 << 16):
                r, c, x = ids_r[key[i : i + (1 << 16)] // wide], ids_c[key[i : i + (1 << 16)] % wide], v[i : i + (1 << 16)]
                x = pa.array([int(q) for q in x], kind) if x.dtype == object and kind == pa.int64() else pa.array([Decimal(q) for q in x], kind) if x.dtype == object else pa.array(x.astype(np.int64)).cast(kind)
                yield pa.RecordBatch.from_arrays([pa.array(r), pa.array(c), x], ["row", "col", "val"])
                if not own:
                    yield pa.RecordBatch.from_arrays([pa.array(c), pa.array(r), x], ["row", "col", "val"])

    lines = Lines.of(a.df.select("row", "col", F.col("val").cast("bigint")), both=False, held=True)
    out = gram(lines, make, f"row bigint, col bigint, val {ring.kind}")
    return SparseMatrix(out, a.n_cols, a.n_cols, ring)


def even_cuts(lines: Lines, bands: int) -> np.ndarray:
    """The ids at which ``bands`` bands of equally many adjacent lines begin."""
    ids, _ = lines.known()
    return np.unique(ids[[-(-k * len(ids) // bands) for k in range(1, bands)]]) if len(ids) else ids


def turning_walks(lines: Lines) -> DataFrame:
    """One row (walks): 2 d^2 - d summed over the lengths d of the lines."""

    def run(batches):
        for batch in batches:
            for sizes in batch.column(0).to_pylist():
                d = unpack(sizes)
                yield _number(int((2 * d * d - d).sum()))

    return lines.df.select("sizes").mapInArrow(run, "v0 decimal(38,0)").agg(F.coalesce(F.sum("v0"), F.lit(0)).cast("bigint").alias("walks"))


def lines_of(g: Graph) -> Lines:
    """The lines of an undirected graph, from the pairs that it was made of where it has not been written since."""
    return Lines.of((g.edges if g.pairs is None else g.pairs).select("src", "dst"), both=True)

"""Products of sparse matrices over semirings.

The planned product deals rows of S and columns of T to bands by their counts,
deals the pages of every block (a page is a column of S and the row of T with
its number) to workers by weight, and sends each entry to the workers that
need it.  A worker is one partition: placement is exact (``repartitionById``),
so the balance of the plan is the balance of the tasks.  Only counters and
assignment tables are moved before the entries are.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, replace
from math import gcd

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsegrid.functions.tiles import bilinear_multiply
from sparsegrid.model import SparseMatrix
from sparsegrid.operators.ranking import deal, ranked, running_sum
from sparsegrid.operators.stats import Totals, nnz_profile, totals
from sparsegrid.plans.lineage import cut_lineage
from sparsegrid.plans.planner import Grid, choose_split


def own_by(a: SparseMatrix, axis: str, partitions: int) -> DataFrame:
    """Entries dealt so that each line along ``axis`` lies in one partition."""
    return a.df.repartition(partitions, axis)


def bands(a: SparseMatrix, axis: str, count: int, mode: str = "stride") -> DataFrame:
    """(id, nz, band): the lines of a matrix dealt to bands by their numbers of entries."""
    if mode == "random":
        return nnz_profile(a, axis).withColumn("band", F.pmod(F.xxhash64("id", F.lit(42)), F.lit(count)).cast("int"))
    if mode == "adjacent":
        profile = nnz_profile(a, axis).withColumn("one", F.lit(1))
        return deal(profile, "id", "one", count, mode="ranges", wide=a.wide).drop("one")
    return deal(nnz_profile(a, axis), "id", "nz", count, mode=mode, wide=a.wide)


def permute(a: SparseMatrix, rows: DataFrame, cols: DataFrame) -> SparseMatrix:
    """Renames rows and columns by maps (id, pos); both must cover the ids in use."""
    r = rows.select(F.col("id").alias("row"), F.col("pos").alias("new_row"))
    c = cols.select(F.col("id").alias("col"), F.col("pos").alias("new_col"))
    return a.with_df(a.df.join(r, "row").join(c, "col").select(F.col("new_row").alias("row"), F.col("new_col").alias("col"), "val"))


def unpermute(a: SparseMatrix, rows: DataFrame, cols: DataFrame) -> SparseMatrix:
    """Undoes ``permute`` with the same maps."""
    swap = lambda m: m.select(F.col("pos").alias("id"), F.col("id").alias("pos"))
    return permute(a, swap(rows), swap(cols))


def band_positions(banded: DataFrame) -> DataFrame:
    """(id, pos): positions that put the lines of a band next to each other, bands in order."""
    return ranked(banded, "id", "band").select("id", F.col("rank").alias("pos"))


def slice_lines(a: SparseMatrix, axis: str, chunk: int) -> DataFrame:
    """Entries with ``piece``: every line cut into pieces of at most ``chunk`` entries.

    The place in the line is a distributed rank, so a hot line is cut by many tasks.
    """
    return _cut_lines(a.df, axis, chunk, a.wide)


def _cut_lines(df: DataFrame, axis: str, chunk: int, wide: bool) -> DataFrame:
    other = "row" if axis == "col" else "col"
    even = df.withColumn("one_", F.lit(1))
    return ranked(even, other, "one_", [axis], wide).withColumn("piece", F.floor(F.col("rank") / chunk).cast("int")).drop("rank", "count", "one_")


def piece_table(profile: DataFrame, chunk: int, wide: bool = False) -> DataFrame:
    """(id, piece, size, owner): the pieces of all lines and their owners, two pieces to an owner."""
    lines = profile.withColumn("pieces", F.ceil(F.col("nz") / chunk)).withColumn("one", F.lit(1))
    numbered = running_sum(lines, "id", "pieces", "first", wide)
    cut = numbered.select("id", "nz", "first", "pieces", F.explode(F.sequence(F.lit(0).cast("long"), F.col("pieces") - 1)).alias("piece"))
    size = F.least(F.lit(chunk), F.col("nz") - F.col("piece") * chunk)
    return cut.select("id", F.col("piece").cast("int").alias("piece"), size.cast("bigint").alias("size"), F.floor((F.col("first") + F.col("piece")) / 2).alias("owner"))


_FEW = 1 << 24  # elementary products that are summed in less time than bands and pages are dealt
_PLACES = 1 << 22  # results that a worker sums
_LINES = 1 << 16  # long lines that a chunk may leave
_HOT = 1 << 12  # entries of a line that one task takes without being cut


def chunk_of(nz: int, lines: int) -> int:
    """The length of pieces: the mean line and one, but not so short that tasks notice, nor so that more than ``_LINES`` lines are longer."""
    return max(-(-nz // max(lines, 1)) + 1, -(-nz // _LINES), _HOT)


@dataclass(frozen=True)
class Slices:
    """One factor's entries with ``piece``, and ``long``: (id, pieces) of the lines of more than one piece, None where there are none."""

    entries: DataFrame
    long: DataFrame | None

    def asked(self, need: DataFrame, line: str) -> DataFrame:
        """Requests for lines as requests for all their pieces."""
        if self.long is None:
            return need.withColumn("piece", F.lit(0))
        told = need.join(F.broadcast(self.long.withColumnRenamed("id", line)), line, "left")
        return told.withColumn("piece", F.explode(F.sequence(F.lit(0), F.coalesce("pieces", F.lit(1)) - 1))).drop("pieces")


def sliced(a: SparseMatrix, axis: str, chunk: int | None, nz: int, lines: int, longest: int) -> Slices:
    """The lines of more than ``chunk`` entries cut into pieces of that size; ``nz``, ``lines`` and ``longest`` are the matrix's totals along ``axis``.

    There are at most nz / chunk such lines (65,536 with the default chunk), so
    their table travels to the entries; only their entries are ranked.
    """
    size = chunk or chunk_of(nz, lines)
    if longest <= size:
        return Slices(a.df.withColumn("piece", F.lit(0)), None)
    long = cut_lineage(nnz_profile(a, axis).where(F.col("nz") > size).select("id", F.ceil(F.col("nz") / size).cast("int").alias("pieces")))
    told = F.broadcast(long.select(F.col("id").alias(axis)))
    short = a.df.join(told, axis, "left_anti").select("row", "col", "val", F.lit(0).alias("piece"))
    return Slices(short.union(_cut_lines(a.df.join(told, axis, "left_semi").select("row", "col", "val"), axis, size, a.wide).select("row", "col", "val", "piece")), long)


def page_weights(s: SparseMatrix, t: SparseMatrix, bands_s: DataFrame, bands_t: DataFrame, keep_idle: Grid | None = None) -> DataFrame:
    """(bi, bj, page, ws, wt, w): for every block the pages that hold entries of both factors.

    With ``keep_idle`` (the grid) pages with entries of one factor only stay as
    well: the message model delivers them, though they make no product.
    """
    left = s.df.join(bands_s.select(F.col("id").alias("row"), F.col("band").alias("bi")), "row").groupBy("bi", F.col("col").alias("page")).agg(F.count("*").alias("ws"))
    right = t.df.join(bands_t.select(F.col("id").alias("col"), F.col("band").alias("bj")), "col").groupBy("bj", F.col("row").alias("page")).agg(F.count("*").alias("wt"))
    if keep_idle is None:
        met = left.join(right, "page")
    else:
        every = lambda k, name: F.explode(F.sequence(F.lit(0), F.lit(k - 1))).alias(name)
        met = left.select("*", every(keep_idle.b, "bj")).join(right.select("*", every(keep_idle.a, "bi")), ["bi", "bj", "page"], "full").fillna(0, ["ws", "wt"])
    return met.select("bi", "bj", "page", "ws", "wt", (F.col("ws") + F.col("wt")).alias("w"))


def assign_pages(pages: DataFrame, grid: Grid, mode: str = "stride", weight: str = "messages", wide: bool = False) -> DataFrame:
    """Adds ``slot`` and ``worker``: the pages of each block dealt to its c workers.

    ``products`` deals by elementary products instead of entries received;
    ``ranges`` gives every worker consecutive pages (a baseline).
    """
    weighed = pages.withColumn("w_", F.col("ws") * F.col("wt") if weight == "products" else F.col("w") if mode != "ranges" else F.lit(1).cast("bigint"))
    dealt = deal(weighed, "page", "w_", grid.c, within=["bi", "bj"], mode=mode, name="slot", wide=wide).drop("w_")
    return dealt.withColumn("worker", ((F.col("bi") * grid.b + F.col("bj")) * grid.c + F.col("slot")).cast("int"))


@dataclass(frozen=True)
class Plan:
    """Everything that is decided before entries move."""

    s: SparseMatrix
    t: SparseMatrix
    grid: Grid
    bands_s: DataFrame
    bands_t: DataFrame
    pages: DataFrame


def plan_product(s: SparseMatrix, t: SparseMatrix, grid: Grid, band_mode: str = "stride", page_mode: str = "stride", weight: str = "messages", cut: bool = True, keep_idle: bool = False) -> Plan:
    """Bands, page weights and page assignment for a grid; their lineage is cut, as several joins read them."""
    held = cut_lineage if cut else (lambda x: x)
    bands_s, bands_t = held(bands(s, "row", grid.a, band_mode)), held(bands(t, "col", grid.b, band_mode))
    pages = held(assign_pages(page_weights(s, t, bands_s, bands_t, grid if keep_idle else None), grid, page_mode, weight, s.wide or t.wide))
    return Plan(s, t, grid, bands_s, bands_t, pages)


def reindexed(plan: Plan, step: int) -> Plan:
    """The same plan with workers under other numbers: number x becomes step * x + 1 modulo their count, one to one where both have no common divisor."""
    k = plan.grid.workers
    if gcd(step, k) != 1:
        raise ValueError("the numbering is not one to one")
    return replace(plan, pages=plan.pages.withColumn("worker", F.pmod(F.col("worker") * step + 1, F.lit(k))))


def route_entries(plan: Plan, chunk: int | None = None, seen: Totals | None = None, whole: bool = False) -> tuple[DataFrame, DataFrame]:
    """Both factors' entries with the workers that need them: (worker, page, row, val) and (worker, page, col, val).

    A page's entries are held in pieces of at most ``chunk`` (by default
    ``chunk_of`` the factor's totals ``seen``, which are counted where they are
    not given); workers ask for each piece of their pages in the band that they
    need, so the join's key is (band, page, piece) and a hot page is many keys.
    ``whole`` leaves lines uncut (a baseline).
    """
    seen = seen or (Totals(0, 0, 0) if whole else totals(plan.s, plan.t))
    left, right = sliced(plan.s, "col", chunk, seen.nz_s, seen.pages_s, seen.longest_s), sliced(plan.t, "row", chunk, seen.nz_t, seen.pages_t, seen.longest_t)
    need = plan.pages.select("bi", "bj", "page", "worker")
    held_s = left.entries.join(plan.bands_s.select(F.col("id").alias("row"), F.col("band").alias("bi")), "row")
    held_t = right.entries.join(plan.bands_t.select(F.col("id").alias("col"), F.col("band").alias("bj")), "col")
    ask_s, ask_t = left.asked(need.select("bi", F.col("page").alias("col"), "worker"), "col"), right.asked(need.select("bj", F.col("page").alias("row"), "worker"), "row")
    sent_s = held_s.join(ask_s, ["bi", "col", "piece"]).select("worker", F.col("col").alias("page"), "row", F.col("val").alias("x"))
    sent_t = held_t.join(ask_t, ["bj", "row", "piece"]).select("worker", F.col("row").alias("page"), "col", F.col("val").alias("y"))
    return sent_s, sent_t


def local_products(plan: Plan, sent_s: DataFrame, sent_t: DataFrame) -> DataFrame:
    """(worker, row, col, val): each worker's sums over its own pages; nothing moves after the placement."""
    k, ring = plan.grid.workers, plan.s.semiring
    left = sent_s.repartitionById(k, F.col("worker"))
    right = sent_t.repartitionById(k, F.col("worker"))
    met = left.join(right.hint("shuffle_hash"), ["worker", "page"])
    return met.groupBy("worker", "row", "col").agg(ring.plus(ring.times(F.col("x"), F.col("y"))).alias("val"))


def assemble(plan: Plan, partial: DataFrame) -> SparseMatrix:
    """Sums of the partial results by place; with one worker to a block there is nothing to sum."""
    ring = plan.s.semiring
    if plan.grid.c > 1:
        partial = partial.groupBy("row", "col").agg(ring.plus(F.col("val")).alias("val"))
    whole = partial.select("row", "col", F.col("val").cast(ring.kind).alias("val")).where(ring.present(F.col("val")))
    return SparseMatrix(whole, plan.s.n_rows, plan.t.n_cols, ring)


def balanced_multiply(s: SparseMatrix, t: SparseMatrix, grid: Grid, band_mode: str = "stride", page_mode: str = "stride", weight: str = "messages", chunk: int | None = None, seen: Totals | None = None, whole: bool = False) -> SparseMatrix:
    """S T on a given grid."""
    plan = plan_product(s, t, grid, band_mode, page_mode, weight)
    return assemble(plan, local_products(plan, *route_entries(plan, chunk, seen, whole)))


def sparse_multiply(s: SparseMatrix, t: SparseMatrix, workers: int | None = None, split: str | tuple[int, int] = "exact", objective: str = "bytes", chunk: int | None = None, seen: Totals | None = None, least: int = _FEW) -> SparseMatrix:
    """S T with the grid chosen from the factors' profiles (``seen``, where they are known already).

    ``workers`` defaults to a power of two, so grids can be near to square: eight
    for each of the session's shuffle partitions, and so many that a worker sums
    at most about four million places, which stay in a task's hash table.  Where the best grid is (1, 1,
    workers), pages alone are dealt, and the product is the plain join on pages
    with summation; so it is, with the objective ``bytes``, for fewer than
    ``least`` elementary products, which are made sooner than a plan.
    """
    spark = s.df.sparkSession
    seen = seen or totals(s, t)
    wanted = max(8 * int(spark.conf.get("spark.sql.shuffle.partitions")), min(seen.products, s.n_rows * t.n_cols) // _PLACES)
    k = workers or 1 << (wanted - 1).bit_length()
    if isinstance(split, tuple):
        return balanced_multiply(s, t, Grid(*split, k // (split[0] * split[1])), chunk=chunk, seen=seen)
    if not seen.products or (objective == "bytes" and seen.products < least):
        return join_multiply(s, t)
    grid = choose_split(max(s.n, t.n), seen.nz_s, seen.nz_t, k, objective, s.n_rows, t.n_cols, seen.products, split)
    if (grid.a, grid.b) == (1, 1) and objective == "bytes":
        return join_multiply(s, t)
    return balanced_multiply(s, t, grid, chunk=chunk, seen=seen)


def join_multiply(s: SparseMatrix, t: SparseMatrix) -> SparseMatrix:
    """The definition: join on pages, sum by place.  What a user of Spark writes first, and the exact reference."""
    ring = s.semiring
    left = s.df.select("row", F.col("col").alias("page"), F.col("val").alias("x"))
    right = t.df.select(F.col("row").alias("page"), "col", F.col("val").alias("y"))
    out = left.join(right, "page").groupBy("row", "col").agg(ring.plus(ring.times(F.col("x"), F.col("y"))).cast(ring.kind).alias("val"))
    return SparseMatrix(out.where(ring.present(F.col("val"))), s.n_rows, t.n_cols, ring)


def announce(df: DataFrame, most: int = 1_000_000) -> DataFrame:
    """A table told to every task, if it has at most ``most`` rows (counted first); a larger one is left to be joined by exchange."""
    return F.broadcast(df) if df.limit(most + 1).count() <= most else df


def broadcast_multiply(s: SparseMatrix, t: SparseMatrix, most: int = 1_000_000) -> SparseMatrix:
    """S T with T announced to every task, where it is small."""
    return join_multiply(s, t.with_df(announce(t.df, most)))


def multiply_fixed_cube(s: SparseMatrix, t: SparseMatrix, workers: int) -> SparseMatrix:
    """Baseline: a cube of equal sides, lines and pages in stored order, whatever the sparsity."""
    side = max(1, round(workers ** (1 / 3)))
    return balanced_multiply(s, t, Grid(side, side, side), "adjacent", "ranges", whole=True)


def multiply_random(s: SparseMatrix, t: SparseMatrix, grid: Grid) -> SparseMatrix:
    """Baseline: bands by a seeded hash of the ids."""
    return balanced_multiply(s, t, grid, "random", "ranges", whole=True)


def multiply_many(pairs: Sequence[tuple[SparseMatrix, SparseMatrix]]) -> DataFrame:
    """(instance, row, col, val) of many products over one semiring, as one join."""
    ring = pairs[0][0].semiring
    left = right = None
    for k, (s, t) in enumerate(pairs):
        x = s.df.select(F.lit(k).alias("instance"), "row", F.col("col").alias("page"), F.col("val").alias("x"))
        y = t.df.select(F.lit(k).alias("instance"), F.col("row").alias("page"), "col", F.col("val").alias("y"))
        left, right = (x, y) if left is None else (left.union(x), right.union(y))
    out = left.join(right, ["instance", "page"]).groupBy("instance", "row", "col").agg(ring.plus(ring.times(F.col("x"), F.col("y"))).alias("val"))
    return out.where(ring.present(F.col("val")))


def masked_multiply(s: SparseMatrix, t: SparseMatrix, mask: SparseMatrix) -> SparseMatrix:
    """The entries of S T at the places of ``mask`` only; others are dropped before they are exchanged for summing."""
    ring = s.semiring
    left = s.df.select("row", F.col("col").alias("page"), F.col("val").alias("x"))
    right = t.df.select(F.col("row").alias("page"), "col", F.col("val").alias("y"))
    met = left.join(right, "page").join(mask.df.select("row", "col"), ["row", "col"], "left_semi")
    out = met.groupBy("row", "col").agg(ring.plus(ring.times(F.col("x"), F.col("y"))).alias("val"))
    return SparseMatrix(out.where(ring.present(F.col("val"))), s.n_rows, t.n_cols, ring)


def multiply_bilinear(s: SparseMatrix, t: SparseMatrix) -> SparseMatrix:
    """Baseline for rings: one level of the seven-product scheme on 2 x 2 blocks of odd and even ids.

    Needs subtraction, so only numbers.  Each of the seven left and right
    factors is a signed sum of blocks; each product goes to blocks of the result
    with a sign, within the task that made it.
    """
    # The seven products of the scheme, as signed blocks (row, column, sign) of S, of T and of the result.
    scheme = [
        ([(0, 0, 1), (1, 1, 1)], [(0, 0, 1), (1, 1, 1)], [(0, 0, 1), (1, 1, 1)]),
        ([(1, 0, 1), (1, 1, 1)], [(0, 0, 1)], [(1, 0, 1), (1, 1, -1)]),
        ([(0, 0, 1)], [(0, 1, 1), (1, 1, -1)], [(0, 1, 1), (1, 1, 1)]),
        ([(1, 1, 1)], [(1, 0, 1), (0, 0, -1)], [(0, 0, 1), (1, 0, 1)]),
        ([(0, 0, 1), (0, 1, 1)], [(1, 1, 1)], [(0, 0, -1), (0, 1, 1)]),
        ([(1, 0, 1), (0, 0, -1)], [(0, 0, 1), (0, 1, 1)], [(1, 1, 1)]),
        ([(0, 1, 1), (1, 1, -1)], [(1, 0, 1), (1, 1, 1)], [(0, 0, 1)]),
    ]
    return bilinear_multiply(s, t, scheme)

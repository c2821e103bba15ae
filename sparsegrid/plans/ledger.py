"""Message ledgers: what every worker sends and receives, counted from assignment tables only."""

from __future__ import annotations

from math import ceil

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsegrid.model import SparseMatrix
from sparsegrid.operators.multiply import Plan, local_products, piece_table, route_entries, slice_lines
from sparsegrid.operators.ranking import ranked
from sparsegrid.operators.stats import nnz_profile
from sparsegrid.operators.triangles import Layers, packets
from sparsegrid.plans.cost import band_bound, intake_bound, listing_alpha, listing_beta
from sparsegrid.plans.planner import Grid


def balance_check(plan: Plan, nz_s: int, nz_t: int) -> DataFrame:
    """(side, band, nz, bound, ok): every band against the mean and one longest line."""
    sides = []
    for side, banded, nz, count, n in (("S", plan.bands_s, nz_s, plan.grid.a, plan.s.n), ("T", plan.bands_t, nz_t, plan.grid.b, plan.t.n)):
        sums = banded.groupBy("band").agg(F.sum("nz").alias("nz"))
        sides.append(sums.select(F.lit(side).alias("side"), "band", "nz", F.lit(band_bound(nz, count, n)).alias("bound")))
    return sides[0].union(sides[1]).withColumn("ok", F.col("nz") <= F.col("bound"))


def page_loads(plan: Plan) -> DataFrame:
    """(bi, bj, slot, pages, received, products, bound, ok): the entries each worker receives against its block's share and two longest lines."""
    load = plan.pages.groupBy("bi", "bj", "slot").agg(F.count("*").alias("pages"), F.sum("w").alias("received"), F.sum(F.col("ws") * F.col("wt")).alias("products"))
    block = load.groupBy("bi", "bj").agg(F.sum("received").alias("all_"))
    out = load.join(block, ["bi", "bj"]).withColumn("bound", F.col("all_") / F.lit(float(plan.grid.c)) + 2.0 * max(plan.s.n, plan.t.n)).drop("all_")
    return out.withColumn("ok", F.col("received") <= F.col("bound"))


def block_intake(plan: Plan, nz_s: int, nz_t: int) -> DataFrame:
    """(bi, bj, received, bound, ok): what the workers of each block receive together, against both bands and two longest lines."""
    block = plan.pages.groupBy("bi", "bj").agg(F.sum("w").alias("received"))
    bound = nz_s / plan.grid.a + nz_t / plan.grid.b + 2 * max(plan.s.n, plan.t.n)
    return block.withColumn("bound", F.lit(float(bound))).withColumn("ok", F.col("received") <= F.col("bound"))


def product_ledger(plan: Plan, nz_s: int, nz_t: int) -> DataFrame:
    """(phase, worker, received): what each worker receives of both factors and of page counters, and asks for.

    Every entry of S is received once in each column band that needs its page,
    every entry of T once in each row band.
    """
    of = plan.pages.groupBy("worker").agg(F.sum("ws").alias("s"), F.sum("wt").alias("t"), F.count("*").alias("pages"))
    stacked = of.select("worker", F.explode(F.array(*[F.struct(F.lit(p).alias("phase"), F.col(c).cast("bigint").alias("received")) for p, c in (("requests", "pages"), ("deliver_s", "s"), ("deliver_t", "t"))])).alias("x"))
    return stacked.select("x.phase", "worker", "x.received")


def message_ledger(plan: Plan, chunk: int) -> DataFrame:
    """(phase, worker, sent, received): the messages of the phases in which entries move, by sender and by receiver.

    Lines are held in pieces of ``chunk`` entries, two to an owner, owners in
    turn over the workers.  A worker asks the owner of every piece of its pages
    (``requests``); owners send each entry to the worker of its page in its band
    (``deliver_s``, ``deliver_t``); workers send their partial results to the
    owner of the row, that is its id modulo the workers (``assemble``).
    Messages of a worker to itself are counted.
    """
    k = plan.grid.workers
    need = plan.pages.select("bi", "bj", "page", "worker")
    out = []
    for phase, a, line, other, bands, band in (("deliver_s", plan.s, "col", "row", plan.bands_s, "bi"), ("deliver_t", plan.t, "row", "col", plan.bands_t, "bj")):
        pieces = piece_table(nnz_profile(a, line), chunk, a.wide).select(F.col("id").alias("page"), "piece", F.pmod("owner", F.lit(k)).alias("owner"))
        held = slice_lines(a, line, chunk).join(bands.select(F.col("id").alias(other), F.col("band").alias(band)), other)
        counts = held.groupBy(band, F.col(line).alias("page"), "piece").agg(F.count("*").alias("m")).join(pieces, ["page", "piece"])
        asked = need.join(pieces, "page").select(F.lit("requests").alias("phase"), F.col("worker").alias("from_"), F.col("owner").alias("to_"), F.lit(1).cast("bigint").alias("m"))
        out += [counts.join(need, [band, "page"]).select(F.lit(phase).alias("phase"), F.col("owner").alias("from_"), F.col("worker").alias("to_"), "m"), asked]
    partial = local_products(plan, *route_entries(plan, whole=True))
    out.append(partial.select(F.lit("assemble").alias("phase"), F.col("worker").alias("from_"), F.pmod("row", F.lit(k)).alias("to_"), F.lit(1).cast("bigint").alias("m")))
    moves = out[0]
    for o in out[1:]:
        moves = moves.union(o)
    ends = moves.select("phase", F.explode(F.array(F.struct(F.col("from_").cast("int").alias("worker"), F.col("m").alias("sent"), F.lit(0).cast("bigint").alias("received")), F.struct(F.col("to_").cast("int").alias("worker"), F.lit(0).cast("bigint").alias("sent"), F.col("m").alias("received")))).alias("e"))
    return ends.groupBy("phase", "e.worker").agg(F.sum("e.sent").alias("sent"), F.sum("e.received").alias("received"))


def phase_rounds(ledger: DataFrame, workers: int) -> DataFrame:
    """(phase, most_sent, most_received, rounds): rounds that deliver each phase when everyone sends and takes ``workers`` - 1 messages in each."""
    most = ledger.groupBy("phase").agg(F.max("sent").alias("most_sent"), F.max("received").alias("most_received"))
    return most.withColumn("rounds", F.ceil(F.greatest("most_sent", "most_received") / F.lit(max(workers - 1, 1))))


def sender_loads(s: SparseMatrix, t: SparseMatrix, grid: Grid, chunk: int | None) -> DataFrame:
    """(worker, sent): entries that each worker has to send when every page is asked for in all bands.

    With ``chunk`` lines are held in pieces of that size; without it (a baseline)
    the owner of a line, in the order of ids, sends all of it.
    """
    k, loads = grid.workers, None
    for a, axis, copies in ((s, "col", grid.b), (t, "row", grid.a)):
        profile = nnz_profile(a, axis)
        if chunk:
            held = piece_table(profile, chunk, a.wide).select("owner", "size")
        else:
            held = ranked(profile.withColumn("one", F.lit(1)), "id", "one", wide=a.wide).select(F.col("rank").alias("owner"), F.col("nz").alias("size"))
        sent = held.groupBy(F.pmod("owner", F.lit(k)).cast("int").alias("worker")).agg((F.sum("size") * copies).alias("sent"))
        loads = sent if loads is None else loads.union(sent)
    return loads.groupBy("worker").agg(F.sum("sent").alias("sent"))


def fixed_phases(n: int, nz_s: int, nz_t: int, grid_ab: int) -> list[tuple[str, int, float]]:
    """(phase, messages, rounds) of the phases whose volume follows from totals alone."""
    return [
        ("transpose_t", nz_t, 1.0),
        ("announce_nz", 2 * n * (n - 1), 2.0),
        ("permute", nz_s + 2 * nz_t, 2.0),
        ("columns_s", nz_s, 1.0),
        ("announce_lines", 2 * n * (n - 1), 2.0),
        ("slices", nz_s + nz_t, 6.0),
        ("band_counts", 4 * n * n, 4.0),
        ("assemble_bound", n * n * n // max(grid_ab, 1), n / max(grid_ab, 1) + 1),
    ]


def rounds(received: list[int], n: int) -> int:
    """Rounds that deliver the given loads when everyone may take n - 1 messages in each."""
    return ceil(max(received, default=0) / max(n - 1, 1))


def intake_report(plan: Plan, nz_s: int, nz_t: int) -> DataFrame:
    """One row: the largest and mean intake of the workers, and the proved bound."""
    of = plan.pages.groupBy("worker").agg(F.sum("w").alias("w"))
    bound = intake_bound(max(plan.s.n, plan.t.n), nz_s, nz_t, plan.grid.a, plan.grid.b, plan.grid.workers)
    return of.agg(F.max("w").alias("most"), (F.sum("w") / plan.grid.workers).alias("mean")).withColumn("bound", F.lit(bound)).withColumn("ok", F.col("most") <= F.col("bound"))


def listing_report(x: Layers) -> DataFrame:
    """(measure, most, bound, ok) of the layered triangle method, with n rounded up to a cube."""
    n, p = x.p**3, x.p
    alpha, beta = listing_alpha(n, x.m), listing_beta(n, x.m)
    out = [
        x.parts.groupBy("part").agg(F.sum("d").alias("w")).agg(F.max("w").alias("most")).select(F.lit("part degrees").alias("measure"), "most", F.lit(2 * alpha).alias("bound")),
        x.cells.agg(F.max("edges").alias("most")).select(F.lit("set edges").alias("measure"), "most", F.lit(beta).alias("bound")),
        x.cells.agg(F.count("*").alias("most")).select(F.lit("sets").alias("measure"), "most", F.lit(2.0 * p * p).alias("bound")),
        x.third.groupBy("pi", "pj", "d").agg(F.sum("w").alias("w")).agg(F.max("w").alias("most")).select(F.lit("third part edges").alias("measure"), "most", F.lit(4 * beta).alias("bound")),
        packets(x, n).groupBy("holder").agg(F.count("*").alias("c")).agg(F.max("c").alias("most")).select(F.lit("packets").alias("measure"), "most", F.lit(x.m / n + 1).alias("bound")),
    ]
    joined = out[0]
    for o in out[1:]:
        joined = joined.union(o)
    return joined.withColumn("ok", F.col("most") <= F.col("bound"))

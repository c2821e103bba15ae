"""Routing by pieces, ranks of hashed ids, ledgers, packets, peeling and weighted paths."""

from __future__ import annotations

import random

import pytest
from pyspark.sql import functions as F

from sparsegrid.model import Graph, SparseMatrix
from sparsegrid.operators import multiply as mu
from sparsegrid.operators import paths
from sparsegrid.operators import triangles as tri
from sparsegrid.operators.algebra import power
from sparsegrid.operators.ranking import ranked, running_sum
from sparsegrid.operators.stats import totals
from sparsegrid.plans import ledger, lineage
from sparsegrid.plans.planner import Grid


def skewed(spark, n=400, hot=300):
    """A matrix in which one column holds most entries, and one row of its transpose."""
    rng = random.Random(1)
    cells = {(r, 0) for r in range(hot)} | {(rng.randrange(n), rng.randrange(1, n)) for _ in range(300)}
    df = spark.createDataFrame([(r, c, 1 + (r + c) % 3) for r, c in cells], "row bigint, col bigint, val bigint")
    return SparseMatrix.of(df, n, n).cut()


def cells(a):
    return {(r.row, r.col): r.val for r in a.df.collect()}


def test_a_hot_page_is_many_keys(spark):
    a = skewed(spark)
    b = a.transpose()
    seen = totals(a, b)
    assert seen.longest_s == seen.longest_t == 300
    held = mu.sliced(a, "col", 25, seen.nz_s, seen.pages_s, seen.longest_s)
    sizes = {(r.col, r.piece): r["count"] for r in held.entries.groupBy("col", "piece").count().collect()}
    assert max(sizes.values()) <= 25 and sum(sizes.values()) == seen.nz_s and sum(c == 0 for c, _ in sizes) == 12
    assert {r.id: r.pieces for r in held.long.collect()} == {0: 12}
    want = cells(mu.join_multiply(a, b))
    assert cells(mu.balanced_multiply(a, b, Grid(2, 3, 2), chunk=25)) == want == cells(mu.balanced_multiply(a, b, Grid(2, 3, 2)))


def test_the_largest_request_of_a_hot_page_is_bounded(spark):
    """Rows that meet under one key of the routing join: with whole lines the hot page's entries, with pieces a chunk."""
    a = skewed(spark)
    plan = mu.plan_product(a, a.transpose(), Grid(2, 2, 3))
    seen = totals(a, a.transpose())

    def most(slices):
        return slices.entries.join(plan.bands_s.select(F.col("id").alias("row"), "band"), "row").groupBy("band", "col", "piece").count().agg(F.max("count")).first()[0]

    assert most(mu.sliced(a, "col", 20, seen.nz_s, seen.pages_s, seen.longest_s)) <= 20 < 100 < most(mu.sliced(a, "col", 1000, seen.nz_s, seen.pages_s, seen.longest_s))


def test_default_pieces_leave_few_long_lines():
    for nz, lines in [(10, 5), (10**6, 10**6), (10**12, 10**4), (10**12, 10**11)]:
        assert nz / mu.chunk_of(nz, lines) <= 1 << 16 and mu.chunk_of(nz, lines) >= nz / lines


def test_workers_under_other_numbers(spark):
    a = skewed(spark)
    plan = mu.plan_product(a, a, Grid(2, 2, 3))
    other = mu.reindexed(plan, 5)
    assert cells(mu.assemble(other, mu.local_products(other, *mu.route_entries(other)))) == cells(mu.join_multiply(a, a))
    with pytest.raises(ValueError):
        mu.reindexed(plan, 6)


def test_ranks_of_hashed_ids(spark):
    rng = random.Random(2)
    ids = [rng.randrange(1 << 62) for _ in range(300)] + list(range(20)) + [1 << 40, (1 << 40) + 1]
    rows = [(i % 2, k, rng.randrange(3)) for i, k in enumerate(ids)]
    df = spark.createDataFrame(rows, "g int, id bigint, w int")
    for wide in (False, True):
        got = {(r.g, r.id): r["rank"] for r in ranked(df, "id", "w", ["g"], wide).collect()}
        for g in (0, 1):
            order = sorted((w, k) for h, k, w in rows if h == g)
            assert [got[g, k] for _, k in order] == list(range(len(order)))
        sums = {r.id: r.s for r in running_sum(df, "id", "w", "s", wide).collect()}
        run = 0
        for _, k, w in sorted(rows, key=lambda r: r[1]):
            assert sums[k] == run
            run += w


def test_a_ledger_counts_every_message_twice(spark):
    a = skewed(spark, 60, 40)
    plan = mu.plan_product(a, a.transpose(), Grid(2, 2, 2), keep_idle=True)
    book = ledger.message_ledger(plan, 7)
    of = {r.phase: (r.s, r.r) for r in book.groupBy("phase").agg(F.sum("sent").alias("s"), F.sum("received").alias("r")).collect()}
    nz = a.nnz()
    assert of["deliver_s"] == (2 * nz, 2 * nz) and of["deliver_t"] == (2 * nz, 2 * nz) and of["requests"][0] == of["requests"][1]
    assert {r.worker for r in book.collect()} <= set(range(8))
    rounds = {r.phase: r.rounds for r in ledger.phase_rounds(book, 8).collect()}
    most = book.where("phase = 'deliver_s'").agg(F.greatest(F.max("sent"), F.max("received"))).first()[0]
    assert rounds["deliver_s"] == -(-most // 7)
    assert ledger.block_intake(plan, nz, nz).where("NOT ok").isEmpty()


def test_whole_lines_load_senders_more(spark):
    a = skewed(spark)
    load = lambda chunk: ledger.sender_loads(a, a.transpose(), Grid(2, 2, 2), chunk).agg(F.max("sent"), F.sum("sent")).first()
    pieces, whole = load(5), load(None)
    assert pieces[1] == whole[1] and pieces[0] < whole[0] / 2


def directed(spark, seed, n=40, m=300):
    rng = random.Random(seed)
    pairs = {(rng.randrange(n), rng.randrange(n)) for _ in range(m)} | {(0, k) for k in range(1, n)}
    return Graph.of(spark.createDataFrame(sorted(pairs), "src bigint, dst bigint"), n, directed=True).cut()


def test_packets_are_even_and_lines_are_cut(spark):
    g = directed(spark, 3)
    x = tri.plan_layers(g, 27)
    held = tri.packets(x, 8).groupBy("holder").count().collect()
    assert sum(r["count"] for r in held) == x.m and max(r["count"] for r in held) <= -(-x.m // 8)
    want = {tuple(r) for r in tri.triangles_two_hop(g).collect()}
    for chunk in (3, None):
        found = [tuple(r) for r in tri.list_triangles(g, 27, chunk=chunk).collect()]
        assert len(found) == len(set(found)) and set(found) == want


def test_peeling_bounds_the_arboricity(spark):
    clique = [(i, j) for i in range(8) for j in range(i)]
    g = Graph.of(spark.createDataFrame(clique + [(100 + k, k) for k in range(8)] + [(200, 201)], "src bigint, dst bigint"), 300, directed=False)
    low, high = tri.degeneracy_bounds(g.cut()).first()
    assert low <= 4 <= high <= 8, "a clique of eight needs four forests"
    star = Graph.of(spark.createDataFrame([(0, k) for k in range(1, 30)], "src bigint, dst bigint"), 30, directed=False)
    assert tuple(tri.degeneracy_bounds(star.cut()).first()) == (1, 1)


def test_weighted_paths_with_witnesses(spark):
    rng = random.Random(5)
    g = directed(spark, 5, 14, 40)
    edges = {(r.src, r.dst): rng.randrange(1, 9) for r in g.edges.collect()}
    weights = spark.createDataFrame([(*e, w) for e, w in edges.items()], "src bigint, dst bigint, w bigint")
    dist = {(i, j): edges.get((i, j), 10**9) for i in range(14) for j in range(14) if i != j}
    for k in range(14):
        for i, j in dist:
            if k not in (i, j):
                dist[i, j] = min(dist[i, j], dist[i, k] + dist[k, j])
    got = {(r.src, r.dst): (r.dist, r.via) for r in paths.shortest_paths(g, weights).collect()}
    assert {k: d for k, (d, _) in got.items()} == {k: d for k, d in dist.items() if d < 10**9}
    for (i, j), (d, via) in got.items():
        assert d == edges[via, j] + (0 if via == i else dist[i, via])


def test_powers_use_the_planned_product(spark):
    a = skewed(spark, 40, 20)
    used = []

    def multiply(x, y):
        used.append(1)
        return mu.sparse_multiply(x, y, 6, objective="rounds")

    assert cells(power(a, 3, multiply)) == cells(mu.join_multiply(mu.join_multiply(a, a), a)) and len(used) == 2


def test_clusters_must_name_a_shared_folder(monkeypatch):
    class Context:
        master = "spark://somewhere:7077"
        _jsc = type("J", (), {"sc": staticmethod(lambda: type("S", (), {"getCheckpointDir": staticmethod(lambda: type("N", (), {"isDefined": staticmethod(lambda: False)}))}))})

    class Session:
        sparkContext = Context()
        conf = type("C", (), {"get": staticmethod(lambda *_: None)})

    with pytest.raises(RuntimeError):
        lineage.ensure_checkpoint_dir(Session())

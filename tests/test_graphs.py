"""Cycles, triangles and distances against known graphs and brute force."""

from __future__ import annotations

import itertools
import math

import pytest

from sparsegrid.functions.semiring import MAX_MIN, MIN_PLUS
from sparsegrid.model import Graph, SparseMatrix
from sparsegrid.operators import cycles, paths
from sparsegrid.operators import triangles as tri
from sparsegrid.plans import ledger
from sparsegrid.sources import tables as src
from sparsegrid.sources.files import generate, read_edges, read_matrix, row_vectors, save_bucketed, write_matrix


def undirected(spark, pairs, n=10):
    return Graph.of(spark.createDataFrame(list(pairs) or [], "src bigint, dst bigint"), n, directed=False).cut()


def complete(k):
    return list(itertools.combinations(range(k), 2))


RING4, RING5 = [(0, 1), (1, 2), (2, 3), (3, 0)], [(i, (i + 1) % 5) for i in range(5)]
K33 = [(i, 3 + j) for i in range(3) for j in range(3)]
KNOWN = {"ring4": (RING4, 0, 1, 0), "k4": (complete(4), 4, 3, 0), "k5": (complete(5), 10, 15, 12), "k33": (K33, 0, 9, 0), "star": ([(0, i) for i in range(1, 9)], 0, 0, 0), "path": ([(i, i + 1) for i in range(5)], 0, 0, 0), "ring5": (RING5, 0, 0, 1)}


@pytest.mark.parametrize("name", KNOWN)
def test_known_graphs(spark, name):
    pairs, triangles, fours, fives = KNOWN[name]
    g = undirected(spark, pairs)
    assert cycles.count_four_cycles(g).first()["four_cycles"] == fours
    assert cycles.count_five_cycles(g).first()["five_cycles"] == fives
    for method in ("layered", "oriented", "two_hop", "fixed", "random", "trace"):
        assert tri.count_triangles(g, method, p=2).first()["triangles"] == triangles, method


def test_directed_triangles(spark):
    ring = Graph.of(spark.createDataFrame([(5, 7), (7, 6), (6, 5), (5, 6)], "src bigint, dst bigint"), 3, directed=True).cut()
    assert [tuple(r) for r in tri.list_triangles(ring).collect()] == [(5, 7, 6)]
    assert {tuple(r) for r in tri.rotations(ring).collect()} == {(5, 7, 6), (7, 6, 5), (6, 5, 7)}
    transitive = Graph.of(spark.createDataFrame([(0, 1), (1, 2), (0, 2)], "src bigint, dst bigint"), 3, directed=True)
    assert tri.list_triangles(transitive.cut()).isEmpty()


def test_loops_and_repeats_go(spark):
    g = undirected(spark, [(1, 1), (1, 2), (2, 1), (1, 2)])
    assert sorted(map(tuple, g.edges.collect())) == [(1, 2), (2, 1)]


@pytest.mark.parametrize("view,expected", [("handoff", 871), ("handoff_purchase", 231)])
def test_hand_off_triangles(spark, sf, view, expected):
    g = src.handoff(spark, sf, "purchase" if "purchase" in view else None).cut()
    listed = tri.list_triangles(g).collect()
    assert len(listed) == len(set(listed)) == expected
    found = tri.rotations(g)
    assert found.count() == found.distinct().count() == 3 * expected


def test_co_order(spark, sf):
    g = src.co_order(spark, sf).cut()
    row = cycles.count_four_cycles(g).first()
    assert (row["trace"], row["four_cycles"]) == (69_692_262, 8_308_480)
    assert tri.list_triangles(g).count() == 125_968
    x = tri.plan_layers(g)
    assert x.p == 6 and x.cells.count() == 51
    report = {r.measure: r for r in ledger.listing_report(x).collect()}
    assert all(r.ok for r in report.values()) and report["third part edges"].most == 1_036


def test_sides():
    assert [tri.side_of(n) for n in (1, 8, 9, 27, 150, 2000)] == [1, 2, 3, 3, 6, 13]


def brute_hops(pairs):
    ids = sorted({v for e in pairs for v in e})
    d = {(a, b): 0 if a == b else math.inf for a in ids for b in ids}
    for a, b in pairs:
        d[a, b] = d[b, a] = 1
    for k in ids:
        for a in ids:
            for b in ids:
                d[a, b] = min(d[a, b], d[a, k] + d[k, b])
    return {k: v for k, v in d.items() if v < math.inf}


def test_hops_by_every_way(spark):
    pairs = [(0, 1), (1, 2), (2, 3), (3, 4), (4, 0), (2, 5), (10, 11), (11, 12)]
    g, want = undirected(spark, pairs), brute_hops(pairs)
    told = lambda df: {(r.src, r.dst): r.dist for r in df.collect()}
    assert told(paths.all_pairs_hops(g)) == want
    assert told(paths.all_pairs_hops(g, mode="full")) == want
    assert told(paths.all_pairs_by_squaring(g)) == want
    connected = undirected(spark, pairs[:6])
    assert told(paths.all_pairs_hops(connected, bound="bfs", root=3)) == brute_hops(pairs[:6])
    low, high = paths.diameter_bounds(connected, 3).first()
    assert low <= max(brute_hops(pairs[:6]).values()) <= high
    assert told(paths.all_pairs_hops(g, bound=1)) == {k: v for k, v in want.items() if v <= 1}


def test_forest(spark, sf):
    hops = paths.all_pairs_hops(src.forest(spark, sf).cut())
    r = hops.selectExpr("count(*) AS n", "max(dist) AS m", "sum(dist) AS s").first()
    assert tuple(r) == (7_290, 4, 23_134)


def test_bottleneck_closure(spark):
    df = spark.createDataFrame([(0, 1, 5), (1, 2, 3), (0, 2, 1), (2, 0, 9)], "row bigint, col bigint, val bigint")
    best = {(r.row, r.col): r.val for r in paths.closure(SparseMatrix(df, 3, 3, MAX_MIN)).df.collect()}
    assert best[0, 2] == 3 and best[1, 0] == 3 and best[2, 1] == 5
    walks = {(r.row, r.col): r.val for r in paths.closure(SparseMatrix(df, 3, 3, MIN_PLUS)).df.collect()}
    assert walks[0, 2] == 1 and walks[1, 1] == 17 and walks[1, 0] == 12


@pytest.mark.parametrize("pairs,girth", [(complete(3), 3), (RING4, 4), (RING5, 5), ([(i, (i + 1) % 6) for i in range(6)], 6), ([(0, 1), (1, 2)], None)])
def test_girth(spark, pairs, girth):
    assert paths.girth_upto(undirected(spark, pairs), 8) == girth


def test_files(spark, sf, tmp_path):
    g = src.handoff(spark, sf).cut()
    a = g.matrix()
    write_matrix(a, str(tmp_path / "m"), bands=3)
    assert read_matrix(spark, str(tmp_path / "m"), a.n, a.n).nnz() == 207
    e = g.edges.selectExpr("src", "dst", "1.5D AS w")
    for fmt in ("csv", "json", "orc", "parquet"):
        e.write.format(fmt).save(str(tmp_path / fmt))
        assert sorted(read_edges(spark, str(tmp_path / fmt), fmt).collect()) == sorted(e.collect())
    (tmp_path / "x.mtx").write_text("%%MatrixMarket matrix coordinate real general\n% note\n3 3 2\n1 2 0.5\n3 1 2\n")
    assert sorted(map(tuple, read_edges(spark, str(tmp_path / "x.mtx"), "mtx").collect())) == [(0, 1, 0.5), (2, 0, 2.0)]
    assert row_vectors(a).count() == 15
    save_bucketed(a, "bucketed_handoff", 2)
    assert spark.table("bucketed_handoff").count() == 207
    spark.sql("DROP TABLE bucketed_handoff")


@pytest.mark.parametrize("kind,count", [("star", 5), ("path", 4), ("complete", 20), ("band", 13)])
def test_generators(spark, kind, count):
    assert generate(spark, kind, 5).count() == count
    assert generate(spark, "random", 30, 0.1, 2).collect() == generate(spark, "random", 30, 0.1, 2).collect()

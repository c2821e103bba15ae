"""What the second round of findings asked for, on the smallest tables."""

from __future__ import annotations

from sparsegrid.queries import QUERIES


def test_divisor_grids_read_a_table(spark, sf):
    """F28"""
    assert any("part.parquet" in f for f in QUERIES["udtf_divisor_grid"](spark, sf).inputFiles())


def test_row_sums_of_a_chain_form_no_product_of_matrices(spark, sf, monkeypatch):
    """F18"""
    from sparsegrid.operators import multiply as mu
    from sparsegrid.queries import products

    widths, plain = [], mu.sparse_multiply

    def seen(s, t, **rest):
        widths.append(t.n_cols)
        return plain(s, t, **rest)

    chain = products.al.multiply_chain
    monkeypatch.setattr(products.al, "multiply_chain", lambda factors: chain(factors, seen))
    assert QUERIES["chain_cust_supp_supply"](spark, sf).count()
    assert widths == [1, 1, 1]


def _hubs(spark, leaves=30):
    """Two hubs that share four neighbours, with ``leaves`` each, and a triangle: few classes, many pairs."""
    from sparsegrid.model import Graph

    pairs = [(h, 10 + h * 100 + i) for h in (1, 2) for i in range(leaves)] + [(h, 5 + i) for h in (1, 2) for i in range(4)] + [(900, 901), (901, 902), (902, 900)]
    return Graph.of(spark.createDataFrame(pairs, "src bigint, dst bigint"), 100, directed=False).cut()


def test_hops_are_summed_over_classes(spark):
    """F12, F14, F16"""
    from functools import partial

    from sparsegrid.operators import paths

    g, sizes = _hubs(spark), []

    def seen(hops):
        def run(graph, **rest):
            sizes.append(graph.edges.count())
            return hops(graph, **rest)

        return run

    want = [tuple(r) for r in g.edges.sparkSession.createDataFrame(paths.all_pairs_hops(g).toPandas()).selectExpr("count(*)", "max(dist)", "sum(dist)").collect()]
    for hops, root in ((paths.all_pairs_hops, None), (paths.all_pairs_by_squaring, None), (partial(paths.all_pairs_hops, bound="bfs"), 5)):
        assert [tuple(r) for r in paths.hops_summary(g, seen(hops), root).collect()] == want
    assert sizes == [14] * 3  # leaves of each hub, the hubs, the shared ones and the triangle


def test_five_cycles_of_classes(spark):
    """F5"""
    from sparsegrid.model import Graph
    from sparsegrid.operators import cycles
    from sparsegrid.operators.multiply import sparse_multiply

    entries = []

    def seen(s, t):
        entries.append(t.nnz())
        return sparse_multiply(s, t)

    # a ring of five whose vertex 0 has 20 twins and 1 has 30 leaves: each twin closes a ring
    pairs = [(0, 1), (1, 2), (2, 3), (3, 4), (4, 0)] + [(50 + i, v) for i in range(20) for v in (1, 4)] + [(1, 100 + i) for i in range(30)]
    g = Graph.of(spark.createDataFrame(pairs, "src bigint, dst bigint"), 60, directed=False).cut()
    assert cycles.count_five_cycles(g, seen).first()["five_cycles"] == 21
    assert max(entries) == 12


def test_hashed_twins_are_verified(spark, monkeypatch):
    """where hashes meet that should not, classes fall apart."""
    from pyspark.sql import functions as F

    from sparsegrid.operators import twins

    g = _hubs(spark, 3)
    monkeypatch.setattr(twins.F, "xxhash64", lambda *c: F.lit(0).cast("bigint"))
    t = twins.merge_twins(g)
    lines = {}
    for a, b in g.edges.collect():
        lines.setdefault(a, set()).add(b)
    for v, rep in t.members.collect():
        assert lines[v] == lines[rep]


def test_ends_are_on_no_cycle(spark):
    """F21"""
    from sparsegrid.model import Graph
    from sparsegrid.operators import paths

    tree = [(0, 1), (0, 2)] + [(k, 10 * k + i) for k in (1, 2) for i in range(1, 9)]
    of = lambda pairs: Graph.of(spark.createDataFrame(pairs, "src bigint, dst bigint"), 30, directed=False).cut()
    assert paths.without_ends(of(tree)).edges.isEmpty()
    ringed = paths.without_ends(of(tree + [(11, 12)]))
    assert sorted(map(tuple, ringed.edges.where("src < dst").collect())) == [(1, 11), (1, 12), (11, 12)]
    assert paths.girth_upto(of(tree), 6) is None and paths.girth_upto(of(tree + [(11, 21)]), 6) == 5


def test_largest_products_come_from_few_documents(spark, sf, monkeypatch):
    """most documents are too short for the fifty largest products; their terms are not counted."""
    from sparsegrid.sources import tables

    asked, plain = [], tables.doc_term

    def seen(spark, folder, only=None):
        asked.append(None if only is None else only.count())
        return plain(spark, folder, only)

    monkeypatch.setattr(tables, "doc_term", seen)
    documents = spark.read.parquet(f"{sf}/documents.parquet").count()
    for name in ("doc_overlap_topk", "doc_benchmark_topk"):
        asked.clear()
        assert QUERIES[name](spark, sf).count() == 50
        assert None not in asked and asked[-1] < documents, (name, asked)


def test_lengths_of_lines(spark, sf):
    """F4, F15"""
    from sparsegrid.sources import tables as src

    df = spark.createDataFrame([(1, "a b a A, é"), (2, None), (3, " 1 "), (4, "x"), (4, "x x"), (None, "y")], "doc_id bigint, text string")
    assert {r["id"]: round(r["length"] ** 2, 6) for r in src.term_lengths(df, "doc_id", "text").collect()} == {1: 11.0, 4: 9.0}
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    from pyspark.sql import functions as F

    exact = src.terms_matrix(docs, "doc_id", "text").groupBy("row").agg(F.sqrt(F.sum(F.col("val") * F.col("val"))).alias("x"))
    both = exact.join(src.term_lengths(docs, "doc_id", "text"), F.col("row") == F.col("id"), "full")
    assert both.where("abs(x - length) > 1e-6 OR x IS NULL OR length IS NULL").isEmpty()


def _random_block(seed, rows, pages, cols, n, high=1000):
    import numpy as np
    import pyarrow as pa

    r = np.random.default_rng(seed)
    s = {(int(a), int(b)): int(v) for a, b, v in zip(r.integers(0, rows, n) * 7, r.integers(0, pages, n) * 3, r.integers(1, high, n), strict=True)}
    t = {(int(a), int(b)): int(v) for a, b, v in zip(r.integers(0, pages, n) * 3, r.integers(0, cols, n) * 5, r.integers(1, high, n), strict=True)}
    lines = [(0, a, b, v) for (a, b), v in s.items()] + [(1, b, a, v) for (a, b), v in t.items()]
    table = pa.table({"side": pa.array([x[0] for x in lines], pa.int8()), "outer": [x[1] for x in lines], "page": [x[2] for x in lines], "val": [x[3] for x in lines]})
    want: dict = {}
    for (i, k), x in s.items():
        for (l, j), y in t.items():
            if k == l:
                want.setdefault((i, j), []).append(x * y)
    return table, want


def test_large_blocks_go_in_strips(monkeypatch):
    """a block larger than a dense tile is never made dense, and strips make the same sums and folds."""
    from functools import reduce
    from math import gcd
    from operator import mul

    from sparsegrid.functions import tiles

    table, want = _random_block(3, 40, 30, 50, 300)
    monkeypatch.setattr(tiles, "_STRIP", 64)
    for dense in (1 << 21, 0):
        monkeypatch.setattr(tiles, "_DENSE", dense)
        if not dense:
            monkeypatch.setattr(tiles, "_dense", None)
        batches = list(tiles._block(table, mul, None, 0))
        got = {(r["row"], r["col"]): r["val"] for b in batches for r in b.to_pylist()}
        assert got == {k: sum(v) for k, v in want.items()}
        assert dense or len(batches) > 10
    got = {(r["row"], r["col"]): r["val"] for b in tiles._block(table, mul, gcd, 0) for r in b.to_pylist()}
    assert got == {k: reduce(gcd, v) for k, v in want.items()}


def test_blocks_do_not_overflow():
    """sums beyond 2**53 are exact, beyond 2**63 an error."""
    from operator import mul

    import pytest

    from sparsegrid.functions import tiles

    table, want = _random_block(4, 5, 4, 5, 12, 1 << 30)
    assert {(r["row"], r["col"]): r["val"] for b in tiles._block(table, mul, None, 0) for r in b.to_pylist()} == {k: sum(v) for k, v in want.items()}
    table, _ = _random_block(4, 5, 4, 5, 12, 1 << 40)
    with pytest.raises(Exception):  # noqa: B017
        list(tiles._block(table, mul, None, 0))


def test_announced_graphs_raise_no_products(spark, sf, monkeypatch):
    """F17"""
    import random

    from sparsegrid.model import Graph
    from sparsegrid.operators import paths

    r = random.Random(5)
    pairs = [(r.randrange(150) * 3, r.randrange(150) * 3) for _ in range(300)] + [(1000, 1001)]
    g = Graph.of(spark.createDataFrame(pairs, "src bigint, dst bigint"), 160, directed=True).cut()
    want = sorted(map(tuple, paths.all_pairs_hops(g).collect()))
    assert sorted(map(tuple, paths.all_pairs_announced(g).collect())) == want
    assert sorted(map(tuple, paths.all_pairs_announced(g, most=5).collect())) == want
    monkeypatch.setattr(paths, "all_pairs_hops", None)
    assert QUERIES["apsp_handoff_purchase"](spark, sf).count()
    assert paths.all_pairs_announced(Graph.of(spark.createDataFrame([], "src bigint, dst bigint"), 1, directed=True)).isEmpty()


def test_seven_products_are_not_exchanged(spark, monkeypatch):
    """one exchange, of the factors' entries; dense and sorted strips and Python's numbers give the product."""
    import random

    from sparsegrid.functions import tiles
    from sparsegrid.model import SparseMatrix
    from sparsegrid.operators import multiply as mu

    r = random.Random(3)
    for high, dense in ((5, 1 << 21), (1 << 20, 1 << 21), (1 << 28, 1 << 21)):
        s = {(r.randrange(-9, 30), r.randrange(20)): r.randrange(-high, high) or 1 for _ in range(200)}
        t = {(r.randrange(20), r.randrange(30)): r.randrange(-high, high) or 1 for _ in range(200)}
        want: dict = {}
        for (i, k), x in s.items():
            for (l, j), y in t.items():
                if k == l:
                    want[i, j] = want.get((i, j), 0) + x * y
        a, b = (SparseMatrix(spark.createDataFrame([(*k, v) for k, v in m.items()], "row bigint, col bigint, val bigint"), 40, 40) for m in (s, t))
        out = mu.multiply_bilinear(a, b)
        assert {(x.row, x.col): x.val for x in out.df.collect()} == {k: v for k, v in want.items() if v}
        assert out.df._jdf.queryExecution().optimizedPlan().toString().count("Aggregate") == 0


def _chains(spark, price, extra=()):
    """Links of three chains of 2, 5 and 9 vertices, and further ones."""
    rows, v = [], 0
    for part, n in ((7, 2), (8, 5), (9, 9)):
        rows += [(part, v + i, v + i + 1, price(v + i)) for i in range(n - 1)]
        v += n
    return spark.createDataFrame(rows + list(extra), "part bigint, src bigint, dst bigint, w bigint")


def test_paths_of_parts(spark, sf, monkeypatch):
    """parts are solved in their tasks; large parts, and parts that meet, by the general method, with the same paths."""
    from sparsegrid.model import Graph
    from sparsegrid.operators import parts, paths

    extra = [(9, 9, 8, 3), (9, 8, 10, 2), (9, 14, 7, 11), (11, 40, 41, 1), (12, 41, 42, 1), (9, 12, 12, 1)]
    links = _chains(spark, lambda v: 1 + v * 7 % 5, extra)
    both = links.where("src <> dst").select("src", "dst", "w").union(links.where("src <> dst").selectExpr("dst", "src", "w")).groupBy("src", "dst").agg({"w": "min"}).toDF("src", "dst", "w").localCheckpoint()
    want = sorted(map(tuple, paths.shortest_paths(Graph(both.select("src", "dst"), 50, False), both).collect()))
    for most in (256, 5, 0):
        assert sorted(map(tuple, parts.shortest_paths_of_parts(links, 50, most).collect())) == want
    monkeypatch.setattr(parts, "shortest_paths", None)
    assert QUERIES["weighted_paths_order_chain"](spark, sf).first()["pairs"]


def test_bottlenecks_of_parts(spark, sf, monkeypatch):
    """F13"""
    from sparsegrid.functions.semiring import MAX_MIN
    from sparsegrid.model import SparseMatrix
    from sparsegrid.operators import parts, paths

    links = _chains(spark, lambda v: v * 7 % 5 - 2, [(9, 9, 8, 3), (9, 8, 10, 2), (11, 40, 41, 1), (12, 41, 42, 1)])
    both = links.selectExpr("src AS row", "dst AS col", "w AS val").union(links.selectExpr("dst", "src", "w")).groupBy("row", "col").agg({"val": "max"}).toDF("row", "col", "val")
    want = sorted(map(tuple, paths.closure(SparseMatrix(both, 50, 50, MAX_MIN)).df.select("row", "col", "val").collect()))
    for most in (256, 5, 0):
        assert sorted(map(tuple, parts.bottleneck_of_parts(links, 50, most).df.collect())) == want
    monkeypatch.setattr(parts, "closure", None)
    assert QUERIES["bottleneck_order_chain"](spark, sf).first()["pairs"]


def test_batches_are_cut_between_parts():
    """F10, F13"""
    import numpy as np
    import pyarrow as pa

    from sparsegrid.operators.parts import _whole

    column = np.array([-3, -3, 1, 1, 1, 1, 2, 5, 5, 9])
    for step in range(1, 11):
        batches = [pa.RecordBatch.from_arrays([pa.array(column[a : a + step])], ["part"]) for a in range(0, 10, step)]
        cut = [set(c[0].tolist()) for c in _whole(iter(batches)) if len(c[0])]
        assert sum(map(len, cut)) == 5 and [x for c in _whole(iter(batches)) for x in c[0].tolist()] == column.tolist()


def test_five_cycles_by_rows(spark, monkeypatch):
    """a told graph makes no products of matrices, and counts the same; sums that floats would round are exact."""
    import random

    from sparsegrid.model import Graph
    from sparsegrid.operators import cycles

    r = random.Random(8)
    of = lambda pairs: Graph.of(spark.createDataFrame(pairs, "src bigint, dst bigint"), 60, directed=False).cut()
    g = of([(r.randrange(40) * 10**11, r.randrange(40) * 10**11) for _ in range(150)] + [(7, 10**11), (8, 10**11)])
    want = cycles.count_five_cycles(g, most=3).first()[0]
    assert want > 0
    ring = of([(0, 1), (1, 2), (2, 3), (3, 4), (4, 0)])
    merged = cycles.merge_twins(ring)
    large = merged.sizes.withColumn("size", cycles.F.lit(50000).cast("bigint"))  # five classes of 50,000 in a ring
    got = cycles._rows_of_powers(merged.matrix(), large).toPandas().sum()
    assert (int(got["t5"]), int(got["t3"])) == (10 * 50000**5, 0)
    monkeypatch.setattr(cycles, "sparse_multiply", None)
    monkeypatch.setattr(cycles.count_five_cycles, "__defaults__", (None, 4_000_000))
    assert cycles.count_five_cycles(g).first()[0] == want


def test_four_cycles_of_two_kinds(spark, sf, monkeypatch):
    """the kind with fewer wedges between its pairs is counted, in arrays and by sorting; the square is not formed."""
    import random

    from sparsegrid.model import Graph, SparseMatrix
    from sparsegrid.operators import cycles

    r = random.Random(4)
    pairs = [(r.randrange(60), r.randrange(9) * 10**14) for _ in range(300)]
    s = SparseMatrix.of(spark.createDataFrame([(a, b, 1) for a, b in pairs] + [(None, 0, 1)], "row bigint, col bigint, val bigint"), 60, 9)
    g = Graph.of(spark.createDataFrame([(a, b + 1000) for a, b in pairs], "src bigint, dst bigint"), 69, directed=False).cut()
    want = cycles.count_four_cycles(g).first()["four_cycles"]
    assert [cycles.count_four_cycles_bipartite(x).first()[0] for x in (s, s.transpose())] == [want, want]
    assert cycles.count_four_cycles_bipartite(s.with_df(s.df.where("row < 0"))).first()[0] == 0
    import pyarrow as pa

    lists = [sorted({r.randrange(12) * 10**13 for _ in range(r.randrange(9))}) for _ in range(40)]
    made = [(a, b) for x in lists for i, a in enumerate(x) for b in x[i + 1 :]]
    for dense in (1 << 23, 0):
        monkeypatch.setattr(cycles, "_DENSE", dense)
        monkeypatch.setattr(cycles, "_CHUNK", 7)
        got: dict = {}
        halves = (pa.RecordBatch.from_arrays([pa.array(lists, pa.list_(pa.int64())).slice(k, 20)], ["ends"]) for k in (0, 20))
        for b in cycles._counted_pairs(halves):
            for row in b.to_pylist():
                got[row["a"], row["b"]] = got.get((row["a"], row["b"]), 0) + row["c"]
        assert got == {k: made.count(k) for k in made}
    monkeypatch.setattr(cycles, "sparse_multiply", None)
    monkeypatch.setattr(cycles.count_four_cycles, "__defaults__", (None,))
    assert QUERIES["four_cycles_supply"](spark, sf).first()["four_cycles"]


def test_similar_triangles_list_no_pairs(spark, sf, monkeypatch):
    """counts by tiles are those of the listing; nulls, other lengths and ties at the bar count as before."""
    from sparsegrid.operators import similar
    from sparsegrid.queries import graphs

    df = spark.read.parquet(f"{sf}/embeddings.parquet").where("vec_id < 300")
    rows = [(r.vec_id, r.label, [float(x) for x in r.embedding]) for r in df.collect()]
    rows += [(1000 + i, 77, v) for i, v in enumerate(([0.15, 1.0], [1.0, 0.0], [0.15, (1 - 0.15**2) ** 0.5], [1.0, 1.0, 1.0], None, [1.0, None]))]
    odd = spark.createDataFrame(rows, "vec_id bigint, label int, embedding array<double>")
    monkeypatch.setattr(graphs.src, "load_table", lambda *a: odd.select(*a[3]) if len(a) > 3 else odd)
    want = graphs.tri.list_triangles(graphs.src.similar(spark, sf).cut()).join(odd, graphs.F.col("v1") == odd["vec_id"]).groupBy("label").count()
    want = sorted(map(tuple, want.collect()))
    for side in (1024, 7):
        assert sorted(map(tuple, similar.similar_triangles(odd, "label", "vec_id", "embedding", 0.15, side).collect())) == want
    monkeypatch.undo()
    monkeypatch.setattr(graphs.tri, "list_triangles", None)
    assert QUERIES["triangles_similar_by_label"](spark, sf).count() == 10


def test_packed_integers_come_back():
    """F2"""
    import numpy as np

    from sparsegrid.operators.gram import pack, unpack

    for a in ([], [5], [-(1 << 63), (1 << 63) - 1, 0, -1], list(range(1000, 0, -3)), [7] * 40):
        assert unpack(pack(np.array(a, np.int64))).tolist() == a



def test_wedges_are_not_exchanged(spark, sf, monkeypatch):
    """neither are edges written both ways."""
    from sparsegrid.operators import triangles as tri
    from sparsegrid.sources import tables as src

    g = src.co_order(spark, sf)
    want = tri.triangles_oriented(g.cut()).count()
    for name in ("triangles_oriented", "cut_lineage"):
        monkeypatch.setattr(tri, name, None)
    assert QUERIES["triangle_count_co_order_oriented"](spark, sf).first()["triangles"] == want > 0


def test_oriented_count_without_arrays(spark, monkeypatch):
    """ids far apart and blocks with few products; degrees of too many vertices are not told."""
    from sparsegrid.model import Graph
    from sparsegrid.operators import triangles as tri

    far = [-(1 << 62), 3, 1 << 40, 1 << 62]
    pairs = [(a, b) for a in far for b in far if a < b] + [(3, 10**9 * i) for i in range(1, 60)] + [(3, 3), (1 << 40, 3)]
    g = Graph.of(spark.createDataFrame(pairs, "src bigint, dst bigint"), 64, directed=False)
    assert [tri.count_oriented(x, m).first()["triangles"] for x, m in ((g, 1 << 24), (g.cut(), 1 << 24), (g, 5))] == [4, 4, 4]
    assert tri.count_oriented(Graph.of(spark.createDataFrame([], "src bigint, dst bigint"), 1, directed=False)).first()["triangles"] == 0


def test_decimal_product_is_made_in_blocks(spark, sf, monkeypatch):
    """no partial sums are exchanged; sums beyond BIGINT stay exact."""
    from decimal import Decimal

    from sparsegrid.functions.semiring import DECIMAL_PLUS_TIMES
    from sparsegrid.model import SparseMatrix
    from sparsegrid.operators.gram import gram_multiply
    from sparsegrid.queries import products

    monkeypatch.setattr(products.mu, "local_products", None)
    assert QUERIES["sparse_multiply_qty_decimal"](spark, sf).count()
    big, a = 3 * 10**18, [(1, 10, 3 * 10**18), (1, 20, -2), (2, 10, 3 * 10**18), (2, 20, 5), (3, 30, 1), (3, 10, 1)]
    m = SparseMatrix(spark.createDataFrame(a, "row bigint, col bigint, val bigint"), 3, 3, DECIMAL_PLUS_TIMES)
    got = {(r["row"], r["col"]): r["val"] for r in gram_multiply(m).df.collect()}
    assert got == {(10, 10): Decimal(2 * big * big + 1), (10, 20): Decimal(3 * big), (20, 10): Decimal(3 * big), (20, 20): Decimal(29), (30, 30): Decimal(1), (10, 30): Decimal(1), (30, 10): Decimal(1)}


def test_square_is_summed_where_it_is_made(spark, sf, monkeypatch):
    """no product or partial sum passes through an exchange."""
    from sparsegrid.operators import multiply as mu
    from sparsegrid.sources import tables as src

    p = mu.join_multiply(*[src.co_order(spark, sf).cut().matrix()] * 2).df.selectExpr("count(*)", "sum(val)", "sum(val * val)").first()
    for name in ("join_multiply", "local_products"):
        monkeypatch.setattr(mu, name, None)
    assert QUERIES["four_cycles_co_order"](spark, sf).first()["trace"] == p[2]
    for name in ("square_co_order", "square_co_order_fixed_cube"):
        assert tuple(QUERIES[name](spark, sf).first()) == tuple(p)[:2]


def test_layers_meet_from_packed_lines(spark, sf, monkeypatch):
    """F8: no edge is copied as a row; hot pairs of parts, ids far apart and first edges that are no array count the same."""
    import numpy as np

    from sparsegrid.model import Graph
    from sparsegrid.operators import layers
    from sparsegrid.operators import triangles as tri

    want = QUERIES["triangle_count_co_order_oriented"](spark, sf).first()["triangles"]
    draw = np.random.default_rng(3).integers(0, 90, (900, 2)).tolist()
    pairs = [(a, b) for a, b in draw] + [(h, b) for h in (7, 8) for b in range(300)]
    near, far = (Graph.of(spark.createDataFrame([(a * k - 9 * k, b * k - 9 * k) for a, b in pairs], "src bigint, dst bigint"), 300, directed=False) for k in (1, 10**12))
    some = tri.triangles_oriented(near.cut()).count()
    assert tri.count_layered(near, 8, most=5).first()["triangles"] == some > 0
    for name in ("list_triangles", "plan_layers", "cut_lineage"):
        monkeypatch.setattr(tri, name, None)
    assert QUERIES["triangle_count_co_order_layered"](spark, sf).first()["triangles"] == want > 0
    for g, workers in ((near, 1), (far, 27)):
        assert tri.count_triangles(g, "layered", workers=workers).first()["triangles"] == some
    assert tri.count_layered(Graph.of(spark.createDataFrame([(4, 4)], "src bigint, dst bigint"), 1, directed=False)).first()["triangles"] == 0
    # two lines with the lists (0, 2) and (1), (0, 2, 3) and (1, 2); edges between 0 and 1, 2 and 2, 3 and 1
    lists = [np.array(x) for x in ([2, 3], [0, 2, 0, 2, 3], [1, 2], [1, 1, 2])]
    first = np.array([0, 2, 3]), np.array([1, 2, 1])
    assert [layers._closed(first, *lists, most) for most in (100, 0)] == [4, 4]
    own = np.array([0, 0, 1]), np.array([1, 3, 2])  # among the later places of each list
    assert [layers._closed(own, np.array([2, 3]), np.array([0, 1, 0, 2, 3]), None, None, most) for most in (100, 0)] == [2, 2]


def test_ablation_exchanges_no_pages(spark, sf, monkeypatch):
    """loads come from histograms of packed lines; repeated and missing ids count as before, and so do more documents than tasks are told."""
    from sparsegrid.queries import planning

    rows = [(i % 23, " ".join(f"w{chr(97 + (i * k) % 26)}{chr(97 + k % 11)}" for k in range(i % 9 + 1)) + " Ähre ähre 7") for i in range(60)]
    rows += [(None, "lost words"), (70, None), (71, ""), (-5, "wea only"), (1 << 50, "wea ähre")]
    odd = spark.createDataFrame(rows, "doc_id bigint, text string")
    monkeypatch.setattr(planning.src, "load_table", lambda *a: odd.select(*a[3]) if len(a) > 3 else odd)
    got = sorted(map(tuple, QUERIES["ablation_doc_term"](spark, sf).collect()))
    monkeypatch.setattr(planning.loads_by_dealing, "__defaults__", (5,))
    assert sorted(map(tuple, QUERIES["ablation_doc_term"](spark, sf).collect())) == got
    monkeypatch.undo()
    monkeypatch.setattr(planning.mu, "plan_product", None)
    assert QUERIES["ablation_doc_term"](spark, sf).count() == 4

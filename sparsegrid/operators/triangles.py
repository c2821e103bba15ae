"""Listing and counting triangles: the layered, sparsity-aware method and its baselines.

A triangle is a directed cycle v1 -> v2 -> v3 -> v1; in an undirected graph both
directions of every edge are there, so each set of three appears six times as a
cycle and is listed once.
"""

from __future__ import annotations

from dataclasses import dataclass
from math import ceil

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from sparsegrid.model import Graph, SparseMatrix
from sparsegrid.operators.algebra import trace_of_product
from sparsegrid.operators.gram import count_closed_wedges, lines_of, pack, unpack
from sparsegrid.operators.layers import count_by_layers
from sparsegrid.operators.multiply import multiply_bilinear, sliced, sparse_multiply
from sparsegrid.operators.ranking import deal
from sparsegrid.plans.lineage import cut_lineage


def side_of(n: int) -> int:
    """The least p with p ** 3 >= n."""
    p = max(1, round(n ** (1 / 3)) - 1)
    while p**3 < n:
        p += 1
    return p


def vertex_parts(g: Graph, p: int, mode: str = "degree") -> DataFrame:
    """(v, d, part): vertices dealt to p parts by total degree; ``random`` uses a seeded hash instead."""
    weighed = g.degrees().select("v", (F.col("d_out") + F.col("d_in")).alias("d"))
    if mode == "random":
        return weighed.withColumn("part", F.pmod(F.xxhash64("v", F.lit(7)), F.lit(p)).cast("int"))
    return deal(weighed, "v", "d", p, name="part")


def edge_parts(g: Graph, parts: DataFrame) -> DataFrame:
    """Edges with the parts of both ends: (src, dst, pi, pj)."""
    i, j = parts.select(F.col("v").alias("src"), F.col("part").alias("pi")), parts.select(F.col("v").alias("dst"), F.col("part").alias("pj"))
    return g.edges.join(i, "src").join(j, "dst").select("src", "dst", "pi", "pj")


def part_matrix(tagged: DataFrame) -> DataFrame:
    """(pi, pj, m): edges between parts."""
    return tagged.groupBy("pi", "pj").agg(F.count("*").alias("m"))


def split_parts(tagged: DataFrame, m: int, p: int) -> DataFrame:
    """(pi, pj, v, k, l): the vertices of a part with edges into another, split into sets of about m / p^2 such edges."""
    counts = tagged.groupBy("pi", "pj", F.col("src").alias("v")).agg(F.count("*").alias("k"))
    sets = part_matrix(tagged).select("pi", "pj", F.ceil(F.col("m") * (p * p) / F.lit(m)).cast("int").alias("sets"))
    return deal(counts.join(sets, ["pi", "pj"]), "v", "k", F.col("sets"), within=["pi", "pj"], name="l").drop("sets")


def assign_cells(sets: DataFrame, p: int) -> DataFrame:
    """(pi, pj, l, edges, set_id, wave, cell): the sets numbered in order; p * p cells take one set in each wave."""
    each = sets.groupBy("pi", "pj", "l").agg(F.sum("k").alias("edges"))
    # at most 2 p^2 rows whatever the graph
    number = F.row_number().over(Window.orderBy("pi", "pj", "l")) - 1
    return each.withColumn("set_id", number).withColumn("wave", F.floor(F.col("set_id") / (p * p)).cast("int")).withColumn("cell", F.pmod("set_id", F.lit(p * p)).cast("int"))


def third_parts(tagged: DataFrame, pairs: DataFrame, p: int) -> DataFrame:
    """(pi, pj, v, w, d): for every pair of parts in use, all vertices dealt to p hands by their edges from the second and to the first."""
    into = tagged.groupBy(F.col("pi").alias("pj"), F.col("dst").alias("v")).agg(F.count("*").alias("w"))
    out = tagged.groupBy(F.col("pj").alias("pi"), F.col("src").alias("v")).agg(F.count("*").alias("w"))
    both = pairs.join(into, "pj").select("pi", "pj", "v", "w").union(pairs.join(out, "pi").select("pi", "pj", "v", "w"))
    return deal(both.groupBy("pi", "pj", "v").agg(F.sum("w").alias("w")), "v", "w", p, within=["pi", "pj"], name="d")


@dataclass(frozen=True)
class Layers:
    """The tables that the layered method decides on before edges move."""

    g: Graph
    p: int
    m: int
    parts: DataFrame
    tagged: DataFrame
    sets: DataFrame
    cells: DataFrame
    third: DataFrame
    vertices: int
    most: int


def plan_layers(g: Graph, workers: int | None = None, parts: str = "degree") -> Layers:
    """``workers`` stands for n; each cell has p members, so about 2 p^3 logical workers in two waves."""
    p = side_of(workers or g.n)
    split = cut_lineage(vertex_parts(g, p, parts))
    line = split.agg(F.count("*"), F.max("d"), F.sum("d")).first()  # no line of edges is longer than the largest degree
    vertices, most, m = (int(x or 0) for x in line)
    m //= 2  # every edge is in two degrees
    tagged = cut_lineage(edge_parts(g, split))
    sets = cut_lineage(split_parts(tagged, max(m, 1), p))
    cells = cut_lineage(assign_cells(sets, p))
    third = cut_lineage(third_parts(tagged, part_matrix(tagged).select("pi", "pj"), p))
    return Layers(g, p, m, split, tagged, sets, cells, third, vertices, most)


def packets(x: Layers, holders: int, edges: DataFrame | None = None) -> DataFrame:
    """(src, dst, set_id, holder): every edge with the set that has to learn it, dealt evenly to ``holders``.

    Edges are numbered set by set; a set holds about m / p^2 edges, so numbering
    one is a window of bounded size, and the sets' offsets are a table of 2 p^2
    rows.  No holder has more than one packet above the mean.
    """
    sets = x.sets.select("pi", "pj", F.col("v").alias("src"), "l").join(x.cells.select("pi", "pj", "l", "set_id"), ["pi", "pj", "l"]).select("pi", "pj", "src", "set_id")
    told = (x.tagged if edges is None else edges).join(sets, ["pi", "pj", "src"]).select("src", "dst", "set_id")
    sizes = told.groupBy("set_id").agg(F.count("*").alias("c_"))
    offsets = sizes.select("set_id", (F.sum("c_").over(Window.orderBy("set_id")) - F.col("c_")).alias("first_"))
    place = F.row_number().over(Window.partitionBy("set_id").orderBy("src", "dst")) - 1
    return told.withColumn("at_", place).join(offsets, "set_id").select("src", "dst", "set_id", F.pmod(F.col("first_") + F.col("at_"), F.lit(holders)).cast("int").alias("holder"))


def learned_edges(x: Layers, canonical: bool = True, directed: bool = True, holders: int | None = None, chunk: int | None = None) -> tuple[DataFrame, DataFrame, DataFrame]:
    """The three edge sets of every worker: first edges, edges to the third vertex, edges back.

    With ``canonical`` only edges that a triangle told from its smallest vertex
    can use are sent, which halves the copies or better.  First edges go to
    ``holders`` in even packets (by default one for each shuffle partition), and
    from there to all members of their set's cell.  The others are routed like a
    product's entries: the lines of the third vertices are held in pieces of at
    most ``chunk``, and a cell's third part asks for each piece.
    """
    worker = (F.col("set_id") * x.p + F.col("d")).cast("int")
    k = holders or int(x.g.edges.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = packets(x, k, x.tagged.where("src < dst") if canonical else None).repartitionById(k, F.col("holder"))
    every = F.explode(F.sequence(F.lit(0), F.lit(x.p - 1))).alias("d")
    e1 = dealt.select("set_id", F.col("src").alias("v1"), F.col("dst").alias("v2"), every).select(worker.alias("worker"), "v1", "v2")
    third, in_use = x.third.select("pi", "pj", F.col("v").alias("v3"), "d"), x.cells.select("pi", "pj", "set_id")
    a = SparseMatrix(x.tagged.select(F.col("src").alias("row"), F.col("dst").alias("col"), (F.col("pi") * x.p + F.col("pj")).alias("val")), x.g.n, x.g.n)
    paths = []
    for line, keep, part, near, far in (("col", None if not canonical or directed else "row < col", F.floor(F.col("val") / x.p), "pj", "v2"), ("row", "col < row" if canonical else None, F.pmod("val", F.lit(x.p)), "pi", "v1")):
        lines = sliced(a, line, chunk, x.m, x.vertices, x.most)
        held = lines.entries.where(keep) if keep else lines.entries
        asked = lines.asked(third, "v3")
        other = "row" if line == "col" else "col"
        told = held.select(F.col(line).alias("v3"), F.col(other).alias(far), part.cast("int").alias(near), "piece").join(asked, [near, "v3", "piece"])
        paths.append(told.join(in_use, ["pi", "pj"]).select(worker.alias("worker"), "v3", far))
    return e1, paths[0].select("worker", "v2", "v3"), paths[1].select("worker", "v3", "v1")


def list_triangles(g: Graph, workers: int | None = None, parts: str = "degree", tasks: int | None = None, chunk: int | None = None) -> DataFrame:
    """(v1, v2, v3): every triangle once, smallest vertex first (in an undirected graph in rising order).

    ``workers`` logical workers are dealt to ``tasks`` tasks.  Edges are copied
    in proportion to the cube root of the workers, so by default there are eight
    for each task (n at most), not one for each vertex.
    """
    k = tasks or int(g.edges.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    x = plan_layers(g, workers or min(g.n, 8 * k), parts)
    e1, e2, e3 = (e.repartitionById(k, F.pmod("worker", F.lit(k))) for e in learned_edges(x, True, g.directed, k, chunk))
    met = e1.join(e2.hint("shuffle_hash"), ["worker", "v2"]).where("v1 < v3").join(e3.hint("shuffle_hash"), ["worker", "v3", "v1"])
    return met.select("v1", "v2", "v3")


def rotations(g: Graph, workers: int | None = None) -> DataFrame:
    """All cycles (v1, v2, v3) as the workers find them, each rotation on its own: the coverage the method is proved to have."""
    e1, e2, e3 = learned_edges(plan_layers(g, workers), canonical=False)
    return e1.join(e2, ["worker", "v2"]).join(e3, ["worker", "v3", "v1"]).select("v1", "v2", "v3")


def _canonical(g: Graph) -> Column:
    return (F.col("v1") < F.col("v2")) & (F.col("v1") < F.col("v3")) & (F.lit(True) if g.directed else F.col("v2") < F.col("v3"))


def triangles_fixed_triples(g: Graph, p: int) -> DataFrame:
    """Baseline: parts by hash, a worker for every ordered triple of parts."""
    part = lambda c: F.pmod(F.xxhash64(c), F.lit(p))
    free = F.explode(F.sequence(F.lit(0), F.lit(p - 1)))
    code = lambda a, b, c: ((a * p + b) * p + c).alias("worker")
    e = g.edges.select("src", "dst", part("src").alias("a"), part("dst").alias("b"), free.alias("f"))
    e1 = e.select(code(F.col("a"), F.col("b"), F.col("f")), F.col("src").alias("v1"), F.col("dst").alias("v2"))
    e2 = e.select(code(F.col("f"), F.col("a"), F.col("b")), F.col("src").alias("v2"), F.col("dst").alias("v3"))
    e3 = e.select(code(F.col("b"), F.col("f"), F.col("a")), F.col("src").alias("v3"), F.col("dst").alias("v1"))
    return e1.join(e2, ["worker", "v2"]).join(e3, ["worker", "v3", "v1"]).where(_canonical(g)).select("v1", "v2", "v3")


def triangles_two_hop(g: Graph) -> DataFrame:
    """Baseline: every vertex learns its two-hop neighbourhood; wedges are closed by a semi join."""
    x, y = g.edges.select(F.col("src").alias("v1"), F.col("dst").alias("v2")), g.edges.select(F.col("src").alias("v2"), F.col("dst").alias("v3"))
    wedges = x.join(y, "v2").where(_canonical(g))
    return wedges.join(g.edges.select(F.col("src").alias("v3"), F.col("dst").alias("v1")), ["v3", "v1"], "left_semi").select("v1", "v2", "v3")


def triangles_oriented(g: Graph) -> DataFrame:
    """Baseline by low degrees: edges point from the lower (degree, id) to the higher, wedges leave the lower end.

    Undirected graphs only; the wedges of a vertex are bounded by the arboricity
    rather than by the largest degree.
    """
    d = g.degrees().select("v", (F.col("d_out") + F.col("d_in")).alias("d"))
    e = g.edges.join(d.select(F.col("v").alias("src"), F.col("d").alias("ds")), "src").join(d.select(F.col("v").alias("dst"), F.col("d").alias("dd")), "dst")
    up = e.where("ds < dd OR (ds = dd AND src < dst)").select("src", "dst")
    wedge = up.alias("x").join(up.alias("y"), "src").where("x.dst < y.dst").select("src", F.col("x.dst").alias("a"), F.col("y.dst").alias("b"))
    closed = wedge.join(g.edges.select(F.col("src").alias("a"), F.col("dst").alias("b")), ["a", "b"], "left_semi")
    three = F.array_sort(F.array("src", "a", "b"))
    return closed.select(three[0].alias("v1"), three[1].alias("v2"), three[2].alias("v3"))


def count_oriented(g: Graph, most: int = 1 << 24) -> DataFrame:
    """One row: how many triangles ``triangles_oriented`` lists, with wedges closed in the blocks where they are made.

    Tasks are told the degrees, of at most ``most`` vertices; of more the
    triangles are listed.
    """
    if g.directed:
        raise ValueError("wedges leave the lower end in undirected graphs")
    lines = lines_of(g)
    ids, degree = lines.known()
    if len(ids) > most:
        return triangles_oriented(Graph(cut_lineage(g.edges), g.n, g.directed)).agg(F.count("*").alias("triangles"))
    told = g.edges.sparkSession.sparkContext.broadcast((pack(ids), pack(degree)))
    seen: list = []

    def up(own, line, near):
        if not seen:
            seen.extend(unpack(x) for x in told.value)
        known, d = seen
        low, high = d[np.searchsorted(known, own)][line], d[np.searchsorted(known, near)]
        return np.flatnonzero((low < high) | ((low == high) & (own[line] < near)))

    return count_closed_wedges(lines, up)


def count_layered(g: Graph, workers: int | None = None, most: int = 1 << 24) -> DataFrame:
    """One row: how many triangles ``list_triangles`` lists, with paths packed and wedges closed in the tasks that learn them.

    Tasks are told the parts, of at most ``most`` vertices; of more, and in
    directed graphs, the triangles are listed.
    """
    if not g.directed:
        lines = lines_of(g)
        ids, degree = lines.known()
        if len(ids) <= most:
            k = int(g.edges.sparkSession.conf.get("spark.sql.shuffle.partitions"))
            return count_by_layers(lines, ids, degree, side_of(workers or min(g.n, 8 * k)))
        g = Graph(cut_lineage(g.edges), g.n, g.directed)
    return list_triangles(g, workers).agg(F.count("*").alias("triangles"))


def triangles_by_trace(g: Graph, multiply=sparse_multiply) -> DataFrame:
    """One row: the number of triangles from the trace of the cube; ``multiply`` may be the seven-product scheme."""
    a = g.matrix()
    trace = trace_of_product(multiply(a, a), a)
    return trace.select(F.floor(F.col("trace") / (3 if g.directed else 6)).alias("triangles"))


def degeneracy_bounds(g: Graph, slack: float = 0.1, most: int = 1 << 12) -> DataFrame:
    """One row (low, high) with low <= arboricity <= high for an undirected graph.

    Vertices of at most 2 (1 + slack) times the density are peeled in rounds,
    whose number grows with the logarithm of the graph.  The densest rest has a
    forest cover of m / (n - 1) at least; with edges oriented toward what is
    peeled later no vertex keeps more than it had when peeled.
    """
    edges, low, high = cut_lineage(g.edges), 0, 0
    for _ in range(most):
        degrees = cut_lineage(edges.groupBy("src").agg(F.count("*").alias("d")))
        n, ends = degrees.agg(F.count("*"), F.sum("d")).first()
        if not n:
            break
        m = ends / 2
        low = max(low, ceil(m / (n - 1)) if n > 1 else 0)
        bar = 2 * (1 + slack) * m / n
        gone = degrees.where(F.col("d") <= bar)
        high = max(high, int(gone.agg(F.max("d")).first()[0] or 0))
        rest = degrees.where(F.col("d") > bar).select("src")
        edges = cut_lineage(edges.join(rest, "src", "left_semi").join(rest.select(F.col("src").alias("dst")), "dst", "left_semi").select("src", "dst"))
    return g.edges.sparkSession.range(1).select(F.lit(low).cast("bigint").alias("low"), F.lit(high).cast("bigint").alias("high"))


def count_triangles(g: Graph, method: str = "layered", p: int = 4, workers: int | None = None) -> DataFrame:
    """One row (triangles) by any of the methods."""
    if method == "oriented" and not g.directed:
        return count_oriented(g)
    if method == "layered":
        return count_layered(g, workers)
    if method in ("trace", "fast_trace"):
        return triangles_by_trace(g, multiply_bilinear if method == "fast_trace" else sparse_multiply)
    listed = {
        "random": lambda: list_triangles(g, workers, parts="random"),
        "fixed": lambda: triangles_fixed_triples(g, p),
        "two_hop": lambda: triangles_two_hop(g),
        "oriented": lambda: triangles_oriented(g),
    }[method]()
    return listed.agg(F.count("*").alias("triangles"))

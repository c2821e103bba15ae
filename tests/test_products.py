"""Products: equal to their definition on every path, semiring and shape."""

from __future__ import annotations

import random
from collections import defaultdict

import pytest
from pyspark.sql import functions as F

from sparsegrid.functions.semiring import MAX_MIN, MIN_PLUS, OR_AND, PLUS_TIMES
from sparsegrid.functions.tiles import block_multiply
from sparsegrid.model import SparseMatrix
from sparsegrid.operators import algebra as al
from sparsegrid.operators import multiply as mu
from sparsegrid.plans import ledger
from sparsegrid.plans.planner import Grid

OPS = {"plus_times": (lambda a, b: a + b, lambda x, y: x * y), "min_plus": (min, lambda x, y: x + y), "or_and": (lambda a, b: a or b, lambda x, y: x and y), "max_min": (max, min)}


def matrix(spark, cells, n=10, m=10, ring=PLUS_TIMES):
    rows = [(r, c, v) for (r, c), v in cells.items()]
    kind = "boolean" if ring is OR_AND else "bigint"
    return SparseMatrix.of(spark.createDataFrame(rows, f"row bigint, col bigint, val {kind}"), n, m, ring)


def cells(a):
    return {(r.row, r.col): r.val for r in a.df.collect()}


def defined(s, t, ring):
    plus, times = OPS[ring.name]
    out = {}
    by_row = defaultdict(list)
    for (r, c), v in t.items():
        by_row[r].append((c, v))
    for (r, k), x in s.items():
        for c, y in by_row[k]:
            v = times(x, y)
            out[r, c] = plus(out[r, c], v) if (r, c) in out else v
    return {k: v for k, v in out.items() if ring.zero is None or v != ring.zero}


def sample(seed, n=12, density=0.25, ring=PLUS_TIMES):
    rng = random.Random(seed)
    return {(r, c): True if ring is OR_AND else rng.choice([-2, -1, 1, 2, 3]) for r in range(n) for c in range(n) if rng.random() < density}


@pytest.mark.parametrize("ring", [PLUS_TIMES, MIN_PLUS, OR_AND, MAX_MIN], ids=lambda r: r.name)
def test_semirings(spark, ring):
    s, t = sample(1, ring=ring), sample(2, ring=ring)
    a, b = matrix(spark, s, ring=ring), matrix(spark, t, ring=ring)
    want = defined(s, t, ring)
    assert cells(mu.join_multiply(a, b)) == want
    assert cells(mu.balanced_multiply(a, b, Grid(2, 3, 2))) == want


@pytest.mark.parametrize("grid", [Grid(1, 1, 1), Grid(5, 1, 1), Grid(1, 3, 2), Grid(3, 2, 1), Grid(2, 2, 5)], ids=str)
def test_any_grid_gives_the_product(spark, grid):
    s, t = sample(3), sample(4)
    assert cells(mu.balanced_multiply(matrix(spark, s), matrix(spark, t), grid)) == defined(s, t, PLUS_TIMES)


def test_baselines_and_variants(spark):
    s, t = sample(5, density=0.6), sample(6)
    a, b, want = matrix(spark, s), matrix(spark, t), defined(s, t, PLUS_TIMES)
    ways = [
        mu.multiply_fixed_cube(a, b, 8), mu.multiply_random(a, b, Grid(2, 2, 2)), mu.multiply_bilinear(a, b), mu.broadcast_multiply(a, b), block_multiply(a, b, 2),
        mu.sparse_multiply(a, b, 8, objective="rounds"), mu.sparse_multiply(a, b, 8), mu.sparse_multiply(a, b, 8, least=0), mu.sparse_multiply(a, b, 8, split=(2, 2)), mu.balanced_multiply(a, b, Grid(2, 2, 2), "serpentine", "serpentine", "products", chunk=2),
    ]
    for way in ways:
        assert cells(way) == want


def test_cancelled_values_are_not_stored(spark):
    a = matrix(spark, {(0, 0): 1, (0, 1): 1})
    b = matrix(spark, {(0, 0): 5, (1, 0): -5, (1, 1): 2})
    assert cells(mu.balanced_multiply(a, b, Grid(1, 2, 2))) == {(0, 1): 2}
    assert cells(mu.multiply_bilinear(a, b)) == {(0, 1): 2}


def test_empty_and_identity(spark):
    none, s = matrix(spark, {}), sample(7)
    a, one = matrix(spark, s), matrix(spark, {(i, i): 1 for i in range(12)})
    assert cells(mu.sparse_multiply(a, none, 4)) == {}
    assert cells(mu.balanced_multiply(none, a, Grid(2, 2, 1))) == {}
    assert cells(mu.balanced_multiply(a, one, Grid(2, 2, 2))) == s


def test_algebra(spark):
    s, t, u = sample(8), sample(9), sample(10)
    a, b, c = (matrix(spark, x) for x in (s, t, u))
    left = mu.join_multiply(mu.join_multiply(a, b), c)
    assert cells(left) == cells(mu.join_multiply(a, mu.join_multiply(b, c))) == cells(al.multiply_chain([a, b, c]))
    assert cells(mu.join_multiply(a, b).transpose()) == cells(mu.join_multiply(b.transpose(), a.transpose()))
    assert cells(mu.join_multiply(a, al.add(b, c))) == cells(al.add(mu.join_multiply(a, b), mu.join_multiply(a, c)))
    assert cells(al.power(a, 3)) == cells(mu.join_multiply(mu.join_multiply(a, a), a))
    assert al.trace_of_product(a, b).first()["trace"] == sum(v for (r, k), v in cells(mu.join_multiply(a, b)).items() if r == k)
    assert al.compare(a, a).isEmpty()


def test_many_and_masked(spark):
    s, t = sample(11), sample(12)
    a, b = matrix(spark, s), matrix(spark, t)
    got = {(r.instance, r.row, r.col): r.val for r in mu.multiply_many([(a, b), (b, a)]).collect()}
    assert got == {(0, *k): v for k, v in defined(s, t, PLUS_TIMES).items()} | {(1, *k): v for k, v in defined(t, s, PLUS_TIMES).items()}
    assert cells(mu.masked_multiply(a, b, a)) == {k: v for k, v in defined(s, t, PLUS_TIMES).items() if k in s}


def test_permutation_comes_back(spark):
    s = sample(13)
    a = matrix(spark, s)
    rows, cols = mu.band_positions(mu.bands(a, "row", 3)), mu.band_positions(mu.bands(a, "col", 4))
    moved = mu.permute(a, rows, cols)
    assert sorted(cells(moved).values()) == sorted(s.values()) and cells(mu.unpermute(moved, rows, cols)) == s


def test_a_suppressed_or_unknown_value_is_left_out(spark):
    df = spark.createDataFrame([(0, 0, 0), (0, 1, None), (None, 1, 4), (1, 1, 4)], "row bigint, col bigint, val bigint")
    assert cells(SparseMatrix.of(df, 2, 2)) == {(1, 1): 4}


def test_entries_are_placed_once_for_each_other_band(spark):
    s = sample(14, density=0.9)
    a = matrix(spark, s)
    plan = mu.plan_product(a, a, Grid(2, 3, 2), keep_idle=True)
    left, right = mu.route_entries(plan)
    assert left.count() == 3 * len(s) and right.count() == 2 * len(s)


def test_a_worker_is_a_partition_and_sums_without_exchange(spark):
    a = matrix(spark, sample(15))
    plan = mu.plan_product(a, a, Grid(2, 2, 3))
    local = mu.local_products(plan, *mu.route_entries(plan))
    seen = local.select("worker", F.spark_partition_id().alias("p")).distinct().collect()
    assert all(r.worker == r.p for r in seen)
    text = local._jdf.queryExecution().executedPlan().toString()
    join = text.index("ShuffledHashJoin")
    assert "hashpartitioning" not in text[:join], "no exchange between the placement and the local sums"


def test_bounds_hold(spark, sf):
    from sparsegrid.sources.tables import co_order

    a = co_order(spark, sf).cut().matrix()
    nz = a.nnz()
    assert (a.n, nz) == (200, 17_798)
    plan = mu.plan_product(a, a, Grid(5, 10, 4), keep_idle=True)
    assert ledger.balance_check(plan, nz, nz).where("NOT ok").isEmpty()
    assert ledger.page_loads(plan).where("NOT ok").isEmpty()
    assert ledger.intake_report(plan, nz, nz).first()["ok"]
    phases = {p: m for p, m, _ in ledger.fixed_phases(a.n, nz, nz, 50)}
    assert phases["transpose_t"] == nz and phases["assemble_bound"] == 200**3 // 50
    assert ledger.rounds([399, 7], 200) == 3

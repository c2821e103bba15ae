"""Claims behind the plans: dealing, slicing, splits and formulas."""

from __future__ import annotations

import math
import random

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from sparsegrid.operators.ranking import deal, ranked
from sparsegrid.plans import cost
from sparsegrid.plans.planner import Grid, choose_split, divisors, grids, workers_for


def hands(weights, k, mode="stride"):
    """Dealing by its definition, on a list."""
    order = sorted(range(len(weights)), key=lambda i: (weights[i], i))
    pad = -len(weights) % k
    out = [[] for _ in range(k)]
    for rank, i in enumerate(order):
        r = rank + pad
        out[r % k if mode == "stride" or (r // k) % 2 == 0 else k - 1 - r % k].append(weights[i])
    return out


@settings(max_examples=300, deadline=None)
@given(st.lists(st.integers(0, 10**6), max_size=60), st.integers(1, 12), st.sampled_from(["stride", "serpentine"]))
def test_dealing_is_balanced(weights, k, mode):
    dealt = hands(weights, k, mode)
    assert max(map(len, dealt)) - min(map(len, dealt)) <= 1
    most = max(weights, default=0)
    assert all(sum(h) <= sum(weights) / k + most for h in dealt)


@settings(max_examples=300, deadline=None)
@given(st.lists(st.integers(0, 500), min_size=1, max_size=80))
def test_slices_are_few_and_short(lines):
    n, chunk = len(lines), max(1, math.ceil(sum(lines) / len(lines)))
    pieces = sum(-(-x // chunk) for x in lines)
    assert chunk <= sum(lines) / n + 1
    assert pieces <= 2 * n


@pytest.mark.parametrize("weights,k", [([], 3), ([5], 3), ([1] * 10, 4), ([0] * 7, 7), ([1, 2, 3, 1000], 3), (list(range(50)), 7)])
@pytest.mark.parametrize("mode", ["stride", "serpentine"])
def test_deal_equals_definition(spark, weights, k, mode):
    df = spark.createDataFrame([(i, w) for i, w in enumerate(weights)], "id bigint, w bigint")
    rows = deal(df, "id", "w", k, mode=mode).collect()
    got = [sorted(r.w for r in rows if r.band == h) for h in range(k)]
    assert got == [sorted(h) for h in hands(weights, k, mode)]


def test_rank_needs_no_order_of_partitions(spark):
    rng = random.Random(3)
    rows = [(g, rng.randrange(20_000), rng.randrange(5)) for g in range(3) for _ in range(300)]
    rows = [(g, i, w) for (g, i), w in {(g, i): w for g, i, w in rows}.items()]
    df = spark.createDataFrame(rows, "g int, id bigint, w bigint").repartition(7)
    got = {(r.g, r.id): r["rank"] for r in ranked(df, "id", "w", ["g"]).collect()}
    for g in range(3):
        order = sorted((w, i) for h, i, w in rows if h == g)
        assert [got[g, i] for _, i in order] == list(range(len(order)))


def test_split_is_the_exact_minimum():
    for n, s, t in [(200, 17_798, 17_798), (64, 64, 4096), (150, 7_966, 7_966), (1000, 10, 10**6)]:
        g = choose_split(n, s, t)
        assert g.workers == n
        assert cost.split_cost(n, s, t, g.a, g.b) == min(cost.split_cost(n, s, t, a, b) for a in divisors(n) for b in divisors(n // a))


def test_split_of_dense_factors_is_the_cube():
    assert choose_split(64, 64**2, 64**2) == Grid(4, 4, 4)


def test_split_of_very_sparse_factors_sums_nothing():
    n = 1000
    g = choose_split(n, n, n)
    assert g.c == 1


@pytest.mark.parametrize("n,nz,grid,value", [(200, 17_798, (5, 10, 4), 10.67), (2_000, 231_458, (25, 40, 2), 5.76), (20_000, 2_392_000, (125, 160, 1), 2.70), (150, 7_966, (5, 10, 3), 8.31)])
def test_split_predictions(n, nz, grid, value):
    g = choose_split(n, nz, nz)
    assert (g.a, g.b, g.c) in (grid, (grid[1], grid[0], grid[2]))
    assert round(cost.split_cost(n, nz, nz, g.a, g.b), 2) == value


def test_one_sided_sparsity_is_not_square():
    g = choose_split(4096, 4096, 4096**2)
    assert g.a < g.b


def test_closed_form_is_near_the_optimum():
    for s, t in [(10**5, 10**5), (10**4, 10**6)]:
        a, b = cost.closed_form_split(4096, s, t)
        real = cost.split_cost(4096, s, t, a, b)
        assert choose_split(4096, s, t, method="closed_form").workers == 4096
        g = choose_split(4096, s, t)
        assert cost.split_cost(4096, s, t, g.a, g.b) <= 3 * (real + 1)


def test_k_workers_with_all_nodes_is_the_base_model():
    n, s = 64, 500
    assert cost.split_cost_k(n, n, s, s, 4, 4) == pytest.approx(1 + cost.split_cost(n, s, s, 4, 4))


def test_empty_factors_have_a_grid():
    assert choose_split(8, 0, 0).workers == 8
    assert cost.closed_form_split(8, 0, 5) == (1.0, 1.0)


def test_bytes_objective_prefers_plain_joins_for_few_products():
    assert choose_split(1000, 1000, 1000, 64, "bytes", 1000, 1000, 1000) == Grid(1, 1, 64)
    dense = choose_split(100, 10_000, 10_000, 64, "bytes", 100, 100, 10**6)
    assert dense.a * dense.b > 1


def test_formulas():
    assert cost.crossover_four_cycles(100) == 1000
    assert cost.crossover_counting(10) == pytest.approx(10 ** (8 / 3 - 2 / cost.OMEGA))
    assert cost.crossover_paths(10, 1, rounded=True) == pytest.approx(10**1.474)
    assert cost.rounds_two_hop(10, 7) == 5
    assert cost.triangles_arboricity_floor(10, 100) == 10
    assert cost.rounds_triangles(8, 32) == pytest.approx(2)
    assert len(grids(64)) == 28
    assert workers_for(10**9, 10**9) > workers_for(10**6, 10**6) >= 1

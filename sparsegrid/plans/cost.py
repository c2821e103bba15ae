"""Cost formulas: rounds of the all-to-all message model, without hidden constants."""

from __future__ import annotations

import math

# The exponent of matrix multiplication that the ring baselines rest on, and its rounded rate.
OMEGA = 2.3728639
RING_RATE_ROUNDED = 0.158


def split_cost(n: float, nz_s: float, nz_t: float, a: float, b: float) -> float:
    """Sending S, sending T and gathering partial rows with an a x b grid of blocks."""
    return nz_s * b / n**2 + nz_t * a / n**2 + n / (a * b)


def split_cost_k(n: float, k: float, nz_s: float, nz_t: float, a: float, b: float) -> float:
    """The same with k workers, each standing for n / k nodes."""
    return n**2 / k**2 + nz_s * b / k**2 + nz_t * a / k**2 + n**2 / (k * a * b)


def closed_form_split(n: float, nz_s: float, nz_t: float) -> tuple[float, float]:
    """The real-valued grid at which all three terms are equal; (1, 1) for an empty factor."""
    if not nz_s or not nz_t:
        return 1.0, 1.0
    return n * nz_s ** (1 / 3) / nz_t ** (2 / 3), n * nz_t ** (1 / 3) / nz_s ** (2 / 3)


def rounds_product(n: float, nz_s: float, nz_t: float) -> float:
    return (nz_s * nz_t) ** (1 / 3) / n + 1


def rounds_equal_sparsity(n: float, m: float) -> float:
    return m ** (2 / 3) / n + 1


def rounds_one_sparse(n: float, m: float) -> float:
    return (m / n) ** (1 / 3) + 1


def rounds_routing(n: float, nz_s: float, nz_t: float, a: float, b: float) -> float:
    return nz_s * b / n**2 + nz_t * a / n**2 + 1


def rounds_assembly(n: float, a: float, b: float) -> float:
    return n / (a * b) + 1


def rounds_all_pairs(n: float, m: float, diameter: float) -> float:
    return diameter * rounds_one_sparse(n, m)


def rounds_triangles(n: float, m: float) -> float:
    return m / n ** (5 / 3) + 1


def rounds_k(n: float, k: float, nz_s: float, nz_t: float) -> float:
    return n ** (2 / 3) * (nz_s * nz_t) ** (1 / 3) / k ** (5 / 3) + 1


def rounds_dense(n: float) -> float:
    return n ** (1 / 3)


def rounds_ring(n: float) -> float:
    return n ** (1 - 2 / OMEGA)


def rounds_two_hop(n: float, max_degree: float) -> float:
    return math.ceil(max_degree**2 / n)


def rounds_arboricity(n: float, arboricity: float) -> float:
    return arboricity**2 / n + math.log(n) / math.log(2 + n / arboricity**2)


def triangles_arboricity_floor(n: float, m: float) -> float:
    return m**2 / n**3


def rounds_listing_floor(n: float) -> float:
    """Below this no method lists the triangles of a graph with n^2 edges, but for a logarithmic factor."""
    return n ** (1 / 3)


def crossover_four_cycles(n: float) -> float:
    """Up to this number of edges, counting 4-cycles takes constantly many rounds."""
    return n**1.5


def crossover_paths(n: float, diameter: float, rounded: bool = False) -> float:
    """Below this number of edges, sparse powers beat the ring method for all-pairs hops."""
    rate = RING_RATE_ROUNDED if rounded else 1 - 2 / OMEGA
    return n ** (1 + 3 * rate) / diameter**3


def crossover_counting(n: float, rounded: bool = False) -> float:
    """Below this number of edges, listing triangles beats the ring method for counting them."""
    rate = RING_RATE_ROUNDED if rounded else 1 - 2 / OMEGA
    return n ** (5 / 3 + rate)


def band_bound(nz: float, groups: int, n: float) -> float:
    """The most a dealt band may hold: the mean and one largest line."""
    return nz / groups + n


def intake_bound(n: float, nz_s: float, nz_t: float, a: float, b: float, k: float | None = None) -> float:
    """The most entries that one of ``k`` workers (n by default) receives."""
    return nz_s * b / (k or n) + nz_t * a / (k or n) + 6 * n


def listing_alpha(n: float, m: float) -> float:
    return m / n ** (1 / 3) + n


def listing_beta(n: float, m: float) -> float:
    return m / n ** (2 / 3) + n

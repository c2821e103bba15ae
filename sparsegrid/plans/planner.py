"""Choosing the worker grid from a few scalars."""

from __future__ import annotations

from dataclasses import dataclass

from sparsegrid.plans.cost import closed_form_split, split_cost, split_cost_k


@dataclass(frozen=True)
class Grid:
    """a row bands, b column bands and c workers for each block."""

    a: int
    b: int
    c: int

    @property
    def workers(self) -> int:
        return self.a * self.b * self.c


def divisors(k: int) -> list[int]:
    low = [d for d in range(1, int(k**0.5) + 1) if k % d == 0]
    return sorted({*low, *(k // d for d in low)})


def grids(k: int) -> list[Grid]:
    """All ways to write k as a * b * c."""
    return [Grid(a, b, k // a // b) for a in divisors(k) for b in divisors(k // a)]


def choose_split(n: int, nz_s: int, nz_t: int, workers: int | None = None, objective: str = "rounds", n_rows: int | None = None, n_cols: int | None = None, products: int | None = None, method: str = "exact") -> Grid:
    """The cheapest grid.

    ``rounds`` minimises the message rounds (with ``workers`` below n those of
    the k-worker form); ``bytes`` the rows that cross the network: copies of
    both factors and the partial results, which number at most the elementary
    products.  ``closed_form`` takes the feasible grid nearest to the real-valued
    optimum instead.  Ties go to the smaller a, then the smaller b.
    """
    k = workers or n
    options = grids(k)
    if method == "closed_form":
        a, b = closed_form_split(n, nz_s, nz_t)
        return min(options, key=lambda g: (abs(_log(g.a) - _log(a)) + abs(_log(g.b) - _log(b)), g.a, g.b))
    if objective == "bytes":
        rows, cols = n_rows or n, n_cols or n
        made = products if products is not None else rows * cols * k

        def moved(g: Grid) -> float:
            return nz_s * g.b + nz_t * g.a + (min(g.c * rows * cols, made) if g.c > 1 else 0)

        return min(options, key=lambda g: (moved(g), g.a, g.b))
    if k == n:
        return min(options, key=lambda g: (split_cost(n, nz_s, nz_t, g.a, g.b), g.a, g.b))
    return min(options, key=lambda g: (split_cost_k(n, k, nz_s, nz_t, g.a, g.b), g.a, g.b))


def workers_for(nz_s: int, nz_t: int, entry_bytes: int = 24, per_worker: int = 256 << 20, most: int = 1 << 16) -> int:
    """The fewest workers, a power of two, whose intake under the cheapest grid stays below ``per_worker`` bytes."""
    k = 1
    while k < most:
        g = choose_split(max(nz_s, nz_t, 1), nz_s, nz_t, k, "bytes", products=0)
        if (nz_s * g.b + nz_t * g.a) * entry_bytes <= per_worker * k:
            break
        k *= 2
    return k


def _log(x: float) -> float:
    from math import log

    return log(max(x, 1e-9))

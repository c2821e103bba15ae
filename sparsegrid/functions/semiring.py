"""Semirings: an aggregate for plus, a column expression for times."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Semiring:
    """``zero`` is neutral for plus and never stored; ``one`` is neutral for times.

    ``plus`` must be associative and commutative; nothing else is asked of it,
    so there need be no subtraction.  Both are built-in column functions, which
    keeps products inside generated code.  ``fold`` is plus as a Python function
    of two values, for products that are made in Arrow batches.
    """

    name: str
    plus: Callable[[Column], Column]
    times: Callable[[Column, Column], Column]
    zero: object
    one: object
    kind: str
    fold: Callable[[object, object], object] | None = None

    def present(self, value: Column) -> Column:
        """Whether a value has to be stored: it is known and not the suppressed one."""
        return value.isNotNull() if self.zero is None else value.isNotNull() & (value != F.lit(self.zero))


def _least(x: Column, y: Column) -> Column:
    return F.least(x, y)


def _greatest(x: Column, y: Column) -> Column:
    return F.greatest(x, y)


PLUS_TIMES = Semiring("plus_times", F.sum, lambda x, y: x * y, 0, 1, "bigint")
DECIMAL_PLUS_TIMES = Semiring("decimal_plus_times", F.sum, lambda x, y: x * y, 0, 1, "decimal(38,0)")
MIN_PLUS = Semiring("min_plus", F.min, lambda x, y: x + y, None, 0, "bigint")
MAX_PLUS = Semiring("max_plus", F.max, lambda x, y: x + y, None, 0, "bigint")
OR_AND = Semiring("or_and", F.bool_or, lambda x, y: x & y, False, True, "boolean")
MAX_MIN = Semiring("max_min", F.max, _least, None, None, "bigint")
MIN_MAX = Semiring("min_max", F.min, _greatest, None, None, "bigint")
MAX_TIMES = Semiring("max_times", F.max, lambda x, y: x * y, 0, 1, "double")



def own_plus(reduce: Callable[[object, object], object], kind: str) -> Callable[[Column], Column]:
    """A semiring's plus from a Python function of two values, as a grouped aggregate over Arrow batches.

    For operations that no built-in aggregate has.  The values of one group are
    in memory together, and nothing is summed before the exchange.
    """
    from functools import reduce as fold

    import pandas as pd

    def plus(values):
        return fold(reduce, values)

    plus.__annotations__ = {"values": pd.Series, "return": int}  # what makes it a grouped aggregate
    return F.pandas_udf(plus, kind)


SEMIRINGS = {s.name: s for s in (PLUS_TIMES, DECIMAL_PLUS_TIMES, MIN_PLUS, MAX_PLUS, OR_AND, MAX_MIN, MIN_MAX, MAX_TIMES)}

"""Table functions."""

from __future__ import annotations

from pyspark.sql.functions import udtf


class _DivisorGrid:
    """All ways to write k as a * b * c."""

    def eval(self, k: int):
        for a in range(1, k + 1):
            if k % a == 0:
                for b in range(1, k // a + 1):
                    if k // a % b == 0:
                        yield a, b, k // a // b


def divisor_grid(k):
    """A table (a, b, c) for one value of k."""
    return udtf(_DivisorGrid, returnType="a int, b int, c int")(k)


class _DealRanks:
    """The rows of one partition in their order, dealt to ``hands`` in turn."""

    def __init__(self) -> None:
        self.seen = 0

    def eval(self, row, hands: int):
        yield row["id"], self.seen, self.seen % hands
        self.seen += 1


def deal_ranks(spark) -> None:
    """Registers ``deal_ranks(TABLE(t) PARTITION BY g ORDER BY w, id, hands)``: (id, place, hand) of each group's rows.

    A group is one task; ``operators.ranking.deal`` is the distributed form.
    """
    spark.udtf.register("deal_ranks", udtf(_DealRanks, returnType="id bigint, place bigint, hand int"))

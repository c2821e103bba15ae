"""Ranks and round-robin dealing without a single-task window."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

_RUN = 12  # ids that share all but the last 12 bits are ranked in one window
#: Further bits by which runs are gathered, so that no window holds more than 2**20 of them wherever ids lie.
_WIDE = (20, 16)


def _offsets(counts: DataFrame, group: Sequence[str], run: str, shifts: Sequence[int]) -> DataFrame:
    """Adds ``before_``: the sum of ``c_`` over the earlier runs of the group, by way of coarser and coarser runs."""
    if not shifts:
        return counts.withColumn("before_", F.sum("c_").over(Window.partitionBy(*group).orderBy(run)) - F.col("c_"))
    up = f"{run}{len(shifts)}_"
    within = counts.withColumn(up, F.shiftright(run, shifts[0]))
    coarse = _offsets(within.groupBy(*group, up).agg(F.sum("c_").alias("c_")), group, up, shifts[1:])
    inner = F.sum("c_").over(Window.partitionBy(*group, up).orderBy(run)) - F.col("c_")
    both = within.withColumn("inner_", inner).join(coarse.select(*group, up, F.col("before_").alias("outer_")), [*group, up])
    return both.withColumn("before_", F.col("inner_") + F.col("outer_")).drop("inner_", "outer_", up)


def ranked(items: DataFrame, key: str, weight: str, within: Sequence[str] = (), wide: bool = False) -> DataFrame:
    """Adds ``rank`` (from 0, by weight and then key) and ``count``, in each group of ``within``.

    The rank is the number of items of smaller weight, plus those of equal
    weight in earlier runs of keys, plus the place in the run: small histograms
    and a window over a few thousand neighbouring keys, wherever all items have
    the same weight too.  ``wide`` says that keys are spread over all of BIGINT
    (hashes): runs are then gathered in steps, each in windows of bounded size.
    """
    group = list(within)
    runs = items.withColumn("run_", F.shiftright(key, _RUN))
    fine = _offsets(runs.groupBy(*group, weight, "run_").agg(F.count("*").alias("c_")), [*group, weight], "run_", _WIDE if wide else ())
    coarse = fine.groupBy(*group, weight).agg(F.sum("c_").alias("rk_weight_total_"))
    by_weight = Window.partitionBy(*group).orderBy(weight) if group else Window.orderBy(weight)
    whole = Window.partitionBy(*group)
    coarse = coarse.withColumn("below_", F.sum("rk_weight_total_").over(by_weight) - F.col("rk_weight_total_")).withColumn("count", F.sum("rk_weight_total_").over(whole))
    base = fine.join(coarse, [*group, weight]).select(*group, weight, "run_", (F.col("before_") + F.col("below_")).alias("base_"), "count")
    place = F.row_number().over(Window.partitionBy(*group, weight, "run_").orderBy(key)) - 1
    return runs.withColumn("place_", place).join(base, [*group, weight, "run_"]).withColumn("rank", F.col("base_") + F.col("place_")).drop("run_", "base_", "place_")


def running_sum(items: DataFrame, key: str, value: str, name: str, wide: bool = False) -> DataFrame:
    """Adds ``name``: the sum of ``value`` over the items with smaller keys, in the same steps."""
    runs = items.withColumn("run_", F.shiftright(key, _RUN)).withColumn("all_", F.lit(0))
    base = _offsets(runs.groupBy("all_", "run_").agg(F.sum(value).alias("c_")), ["all_"], "run_", _WIDE if wide else ()).select("run_", F.col("before_").alias("base_"))
    inner = F.sum(value).over(Window.partitionBy("run_").orderBy(key)) - F.col(value)
    return runs.withColumn("inner_", inner).join(base, "run_").withColumn(name, F.col("base_") + F.col("inner_")).drop("run_", "base_", "inner_", "all_")


def deal(items: DataFrame, key: str, weight: str, k: int | Column, within: Sequence[str] = (), mode: str = "stride", name: str = "band", wide: bool = False) -> DataFrame:
    """Deals items to ``k`` hands in the order of their weights.

    Hands differ by at most one in size, and each weighs at most the mean plus
    one largest item: missing items are thought of as weightless ones that come
    first.  ``serpentine`` turns the direction at the end of each round;
    ``ranges`` gives each hand a run of consecutive ranks (a baseline).
    Returns ``items`` with the column ``name``.
    """
    hands = F.lit(k) if isinstance(k, int) else k
    out = ranked(items, key, weight, within, wide)
    r = F.col("rank") + F.pmod(-F.col("count"), hands)
    if mode == "stride":
        hand = F.pmod(r, hands)
    elif mode == "serpentine":
        hand = F.when(F.pmod(F.floor(r / hands), F.lit(2)) == 0, F.pmod(r, hands)).otherwise(hands - 1 - F.pmod(r, hands))
    else:
        hand = F.floor(F.col("rank") * hands / F.col("count"))
    return out.withColumn(name, hand.cast("int")).drop("rank", "count")

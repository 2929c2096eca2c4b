"""Exclusive prefix sums without a window over all rows."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame, Window, functions as F

#: Groups whose totals the driver may hold.
MOST_GROUPS = 4_000_000


def starts(totals: Iterable[tuple[int, int]]) -> dict[int, int]:
    """(group, total) in any order -> start of each group in group order."""
    at, out = 0, {}
    for group, n in sorted(totals):
        out[group] = at
        at += n
    return out


def exclusive_prefix(df: DataFrame, group: str, order: str, value: str, name: str = "start", naive: bool = False) -> DataFrame:
    """df + name: the sum of `value` over all rows before this one in (group, order).

    Two levels: one total per group goes to the driver (a checked number of groups), the running sum stays inside the group.
    Groups must be contiguous in `order` between them, and `order` unique in a group. naive: one window over everything, for tests.
    """
    value_col = F.col(value).cast("bigint")
    if naive:
        return df.withColumn(name, F.sum(value_col).over(Window.orderBy(group, order)) - value_col)
    totals = df.groupBy(group).agg(F.sum(value_col).alias("n")).limit(MOST_GROUPS + 1).collect()
    if len(totals) > MOST_GROUPS:
        raise ValueError(f"over {MOST_GROUPS} groups; take coarser ones")
    base = starts((r[0], r["n"]) for r in totals)
    side = df.sparkSession.createDataFrame(list(base.items()), f"_g {df.schema[group].dataType.simpleString()}, _base bigint")
    inside = F.sum(value_col).over(Window.partitionBy(group).orderBy(order)) - value_col
    return df.join(F.broadcast(side), F.col(group) == F.col("_g")).withColumn(name, F.col("_base") + inside).drop("_g", "_base")

"""Row numbers: from a unique column, from file positions, or dense in the order of all columns."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window, functions as F

from ..operators.prefix import starts


#: Rows that one task ranks, about.
GROUP_ROWS = 4_000_000


def file_rid(df: DataFrame) -> DataFrame:
    """df + rid from file name and row index (Parquet): unique, stable while the files stay, no shuffle."""
    return df.withColumn("rid", F.shiftleft(F.pmod(F.xxhash64("_metadata.file_path"), F.lit(1 << 22)), 40) + F.col("_metadata.row_index"))


def dense_rid(df: DataFrame, lead: str, groups: int = 64, name: str = "rid") -> DataFrame:
    """df + 0-based position in the order of (lead, all other columns); lead is an integer column.

    Two levels: equal ranges of `lead` are counted (a few numbers reach the driver), rows are ranked inside their range.
    """
    low, high, rows = df.agg(F.min(lead), F.max(lead), F.count("*")).first()
    low, high = (low or 0), (high or 0)
    groups = max(groups, -(-rows // GROUP_ROWS))
    width = max(1, -(-(high - low + 1) // groups))
    ranged = df.withColumn("_g", F.coalesce(F.floor((F.col(lead) - low) / width), F.lit(-1)).cast("bigint"))
    base = starts((r["_g"], r["count"]) for r in ranged.groupBy("_g").count().collect())
    side = df.sparkSession.createDataFrame(list(base.items()) or [(0, 0)], "_g bigint, _base bigint")
    order = [lead, *[c for c in df.columns if c != lead]]
    rank = F.row_number().over(Window.partitionBy("_g").orderBy(*order)) - 1
    return ranged.join(F.broadcast(side), "_g").withColumn(name, F.col("_base") + rank).drop("_g", "_base")

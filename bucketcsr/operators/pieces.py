"""Joins against a side that is too large to be sent to every executor at once."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, functions as F


def met_in_pieces(a: DataFrame, b: DataFrame, pieces: int, piece_a: Column, piece_b: Column, meet: Callable[[DataFrame, DataFrame], DataFrame]) -> DataFrame:
    """meet(rows of a, rows of b) of every piece; rows that can meet have to bear one number of 0 .. pieces - 1.

    Both sides are written once by piece to the shared folder, then one job per piece reads its own rows alone. So only one piece of b is held
    at a time, by the driver and by every executor.
    """
    from ..sources.storage import forget, shared_folder

    spark = a.sparkSession
    folder = shared_folder(spark, "pieces")
    sides = []
    for name, df, piece in (("a", a, piece_a), ("b", b, piece_b)):
        marked = df.withColumn("_piece", piece.cast("int"))
        marked.write.partitionBy("_piece").option("compression", "zstd").parquet(f"{folder}/{name}")
        sides.append(spark.read.schema(marked.schema).parquet(f"{folder}/{name}"))
    kind = None
    for p in range(pieces):
        one, two = (s.where(F.col("_piece") == p).drop("_piece") for s in sides)
        met = meet(one, two)
        kind = met.schema
        met.write.option("compression", "zstd").parquet(f"{folder}/met/{p}")
    for name in ("a", "b"):
        forget(spark, f"{folder}/{name}")
    return spark.read.schema(kind).parquet(*[f"{folder}/met/{p}" for p in range(pieces)])

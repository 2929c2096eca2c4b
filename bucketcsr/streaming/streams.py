"""Structured Streaming over the events table.

Each function starts an availableNow query that writes to a folder shared by the cluster and returns its result. In append mode
a window comes out once the watermark has passed its end; later rows of it are dropped and counted by the query's progress.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, functions as F

from ..functions.hashing import bucket_of
from ..sources.storage import forget, shared_folder


def _folder(spark: SparkSession) -> str:
    return shared_folder(spark, "stream")


def source(spark: SparkSession, path: str, at: str | None = "ts", files_per_batch: int = 1000) -> DataFrame:
    """A stream of Parquet files; the event time becomes a TIMESTAMP, which watermarks need. The path may be a folder or one file."""
    pattern = f"{path[:-1]}[{path[-1]}]"  # a plain path would have to be a folder
    stream = spark.readStream.schema(spark.read.parquet(path).schema).option("maxFilesPerTrigger", files_per_batch).parquet(pattern)
    return stream.withColumn(at, F.col(at).cast("timestamp")) if at else stream


def drain(stream: DataFrame) -> DataFrame:
    """Runs the stream over all there is and reads what it appended."""
    spark = stream.sparkSession
    folder = _folder(spark)
    query = stream.writeStream.format("parquet").outputMode("append").option("path", f"{folder}/rows").option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    forget(spark, f"{folder}/state")
    return spark.read.schema(stream.schema).parquet(f"{folder}/rows")


def _ntz(df: DataFrame, *names: str) -> DataFrame:
    return df.withColumns({n: F.col(n).cast("timestamp_ntz") for n in names})


def windowed_counts(spark: SparkSession, path: str, key: str, v: int, length: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """(begin, end, bucket, n) of closed windows."""
    rows = source(spark, path).withWatermark("ts", late).withColumn("bucket", bucket_of([F.col(key).cast("bigint")], v))
    window = F.window("ts", length, slide) if slide else F.window("ts", length)
    counts = rows.groupBy(window, "bucket").agg(F.count("*").alias("n"))
    return _ntz(drain(counts.select(F.col("window.start").alias("begin"), F.col("window.end").alias("end"), "bucket", "n")), "begin", "end")


def sessions(spark: SparkSession, path: str, key: str, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """(key, begin, end, n) of closed sessions."""
    rows = source(spark, path).withWatermark("ts", late)
    made = rows.groupBy(F.session_window("ts", gap), key).agg(F.count("*").alias("n"))
    return _ntz(drain(made.select(key, F.col("session_window.start").alias("begin"), F.col("session_window.end").alias("end"), "n")), "begin", "end")


def first_seen(spark: SparkSession, path: str, keys: list[str], late: str = "1 hour") -> DataFrame:
    """Distinct key tuples of each day as they first appear, then over all days; state is dropped once the watermark has passed a day."""
    rows = source(spark, path).withWatermark("ts", late).select(*keys, F.window("ts", "1 day").alias("day"))
    return drain(rows.dropDuplicates([*keys, "day"]).select(*keys)).distinct()


def first_within(spark: SparkSession, path: str, keys: list[str], within: str = "1 hour") -> DataFrame:
    """Rows of key tuples that were not seen in the `within` before; a tuple's state is dropped after that time, so it stays bounded."""
    rows = source(spark, path).select(*keys, "ts").withWatermark("ts", within)
    return _ntz(drain(rows.dropDuplicatesWithinWatermark(keys)), "ts")


def split_late(spark: SparkSession, path: str, length: str = "1 day", late: str = "1 hour", files_per_batch: int = 1000) -> tuple[DataFrame, DataFrame]:
    """(rows in time, late rows): a row is late if its window had closed when its batch began.

    A window closes when the largest event time of earlier batches, less `late`, has reached its end. Late rows are kept in a table of their
    own, where the engine's windows would only count them. Each batch writes a folder named by its number, so a repeated batch writes the same rows again.
    Rows without event time are in time. At least one batch must arrive.
    """
    folder = _folder(spark)
    rows = source(spark, path, "ts", files_per_batch)

    def each(batch: DataFrame, number: int) -> None:
        mark = batch.sparkSession.read.schema("high timestamp").parquet(f"{folder}/marks/{number - 1}").first()[0] if number else None
        ends = F.window("ts", length)["end"]
        closed = F.coalesce(ends <= F.lit(mark) - F.expr(f"INTERVAL {late}"), F.lit(False)) if mark else F.lit(False)
        marked = batch.withColumn("_late", closed).persist()
        marked.where("not _late").drop("_late").write.mode("overwrite").parquet(f"{folder}/rows/{number}")
        marked.where("_late").drop("_late").write.mode("overwrite").parquet(f"{folder}/late/{number}")
        high = marked.agg(F.greatest(F.max("ts"), F.lit(mark).cast("timestamp")).alias("high"))
        high.write.mode("overwrite").parquet(f"{folder}/marks/{number}")
        marked.unpersist()

    rows.writeStream.foreachBatch(each).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start().awaitTermination()
    forget(spark, f"{folder}/state")
    read = lambda name: _ntz(spark.read.schema(rows.schema).option("recursiveFileLookup", "true").parquet(f"{folder}/{name}"), "ts")
    return read("rows"), read("late")


def static_probe(spark: SparkSession, path: str, key: str, index_edges: DataFrame, v: int) -> DataFrame:
    """(rid, r_rid): stream rows against a static index, by bucket and key."""
    rows = source(spark, path, None).withColumn("bucket", bucket_of([F.col(key).cast("bigint")], v))
    built = index_edges.select("bucket", F.col("key").alias("_k"), F.col("rid").alias("r_rid"))
    return drain(rows.join(built, (rows["bucket"] == built["bucket"]) & (F.col(key) == F.col("_k"))).select(F.col("event_id").alias("rid"), "r_rid"))


def batches_into(spark: SparkSession, path: str, each: Callable[[DataFrame, int], None]) -> None:
    """Hands each micro-batch to `each`, the way delta indexes are appended."""
    folder = _folder(spark)
    source(spark, path, None).writeStream.foreachBatch(each).option("checkpointLocation", folder).trigger(availableNow=True).start().awaitTermination()


def running_bins(spark: SparkSession, path: str, key: str, v: int, width: int) -> DataFrame:
    """(bin, n): rows so far per bin, kept as state of one long per bin; the largest n of a bin is its total."""

    def step(k: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        n = (state.get[0] if state.exists else 0) + sum(len(f) for f in frames)
        state.update((n,))
        yield pd.DataFrame({"bin": [k[0]], "n": [n]})

    rows = source(spark, path, None).select(F.floor(bucket_of([F.col(key).cast("bigint")], v) / F.lit(width)).cast("bigint").alias("bin"))
    made = rows.groupBy("bin").applyInPandasWithState(step, "bin bigint, n bigint", "n bigint", "append", "NoTimeout")
    return drain(made).groupBy("bin").agg(F.max("n").alias("n"))

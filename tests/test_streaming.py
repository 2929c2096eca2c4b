"""Streams that have seen all there is agree with the batch result."""

from datetime import timedelta

from pyspark.sql import functions as F

from bucketcsr import catalogue
from bucketcsr.functions.hashing import bucket_of
from bucketcsr.operators import build, dynamic
from bucketcsr.plans.params import BuildSpec
from bucketcsr.streaming import streams

PATH = "/root/testdata/sf0.001/events.parquet"


def test_closed_windows_equal_the_batch(spark):
    events = spark.read.parquet(PATH)
    limit = events.agg(F.max("ts") - F.expr("INTERVAL 1 HOUR")).first()[0]
    batch = events.groupBy(F.window(F.col("ts").cast("timestamp"), "1 day").alias("w"), bucket_of([F.col("user_id")], 8).alias("bucket")).agg(F.count("*").alias("n"))
    batch = batch.select(F.col("w.start").cast("timestamp_ntz").alias("begin"), F.col("w.end").cast("timestamp_ntz").alias("end"), "bucket", "n").where(F.col("end") <= F.lit(limit))
    got = streams.windowed_counts(spark, PATH, "user_id", 8)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, batch.collect()))


def test_first_seen_and_running_bins(spark):
    events = spark.read.parquet(PATH)
    assert streams.first_seen(spark, PATH, ["user_id"]).count() == events.select("user_id").distinct().count()
    assert streams.running_bins(spark, PATH, "user_id", 8, 4).agg(F.sum("n")).first()[0] == events.count()


def test_batches_become_delta_indexes(spark):
    spec = BuildSpec(bins=4, parts=2)
    events = spark.read.parquet(PATH)
    empty = events.where("false")
    state = {"live": dynamic.LiveIndex(build.build_binned(empty, "user_id", "event_id", BuildSpec(buckets=64, bins=4, parts=2)))}

    def each(batch, _):
        # a micro-batch frame lives only inside the call
        kept = spark.createDataFrame(batch.select("user_id", "event_id").collect(), "user_id bigint, event_id bigint")
        state["live"] = state["live"].append(kept, "user_id", "event_id")

    streams.batches_into(spark, PATH, each)
    assert state["live"].edges().count() == events.count() and spec.bins == 4


def test_late_rows_have_a_table_of_their_own(spark, tmp_path):
    for day, hours in ((3, (1, 5)), (2, (9,)), (3, (2,)), (1, (0, 23))):
        rows = [(f"2024-01-0{day} {h:02d}:00:00",) for h in hours]
        spark.createDataFrame(rows, "t string").select(F.col("t").cast("timestamp_ntz").alias("ts"), F.lit(day).alias("day")).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    on_time, late = streams.split_late(spark, str(tmp_path / "in"), late="6 hours", files_per_batch=1)
    # the mark after the first batch is 5 o'clock of the third day less six hours: day 2 is still open, day 1 closed
    assert sorted(r["day"] for r in on_time.collect()) == [2, 3, 3, 3]
    assert [r["day"] for r in late.collect()] == [1, 1]


def test_rows_delivered_twice_come_out_once(spark, tmp_path):
    for _ in range(2):
        spark.read.parquet(PATH).write.mode("append").parquet(str(tmp_path / "in"))
    got = streams.first_within(spark, str(tmp_path / "in"), ["event_id"])
    assert got.count() == got.select("event_id").distinct().count() == spark.read.parquet(PATH).count()


def test_late_rows_where_a_file_of_the_first_half_is_empty(spark, tmp_path):
    """The largest file holds old rows only, so the first task writes a file without rows; one event has no time."""
    write = lambda rows: spark.createDataFrame(rows, "event_id bigint, t string").select("event_id", F.col("t").cast("timestamp_ntz").alias("ts")).coalesce(1).write.mode("append").parquet(str(tmp_path / "events.parquet"))
    write([(i, f"2024-01-01 {i % 24:02d}:{i % 60:02d}:00") for i in range(5000)])
    for part in range(4):
        write([(10_000 * (part + 1) + i, f"2024-01-{2 + i % 9:02d} {i % 24:02d}:00:00") for i in range(1500)])
    write([(99_999, None)])
    got = {r["event_id"]: r["late"] for r in catalogue.queries()["stream_late_rows"](spark, str(tmp_path)).collect()}
    rows = {r["event_id"]: r["ts"] for r in spark.read.parquet(str(tmp_path / "events.parquet")).collect()}
    times = sorted(t for t in rows.values() if t)
    half, mark = times[(len(times) - 1) // 2], times[-1] - timedelta(hours=1)
    closes = lambda t: t.replace(hour=0, minute=0) + timedelta(days=1)
    assert got == {k: None if t is None else t < half and closes(t) <= mark for k, t in rows.items()}

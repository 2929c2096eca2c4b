"""Features of values longer than 64 characters."""

from pyspark.sql import functions as F

from bucketcsr.llm import secrets


def test_variety_counts_the_whole_value(spark):
    values = ["ab" * 32, "ab" * 32 + "cdefghij0123456789", "a" * 200 + "b", "xyz1"]
    made = secrets._features(F.col("value"), F.lit(True), F.lit(""), F.lit(""))[secrets.FEATURES.index("variety")]
    got = [r[0] for r in spark.createDataFrame([(v,) for v in values], "value string").coalesce(1).select(made).collect()]
    assert got == [len(set(v)) / min(len(v), 64) for v in values]

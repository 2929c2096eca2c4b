"""Sketches against exact numbers, and what a run measures."""

import pytest
from pyspark.sql import functions as F

from bucketcsr import measures
from bucketcsr.baselines import minhash


def test_hot_keys_are_all_found_and_exact(spark):
    hot = spark.range(30_000).select(F.when(F.col("id") % 3 == 0, -1).when(F.col("id") % 10 == 1, -2).otherwise(F.col("id")).alias("k"))
    got = {r["key"]: r["n"] for r in measures.hot_keys(hot, "k", 0.06).collect()}
    assert got == {-1: 10_000, -2: hot.where("k = -2").count()}
    nulls = spark.sql("SELECT CAST(NULL AS BIGINT) AS k")
    assert measures.hot_keys(nulls, "k", 0.5).count() == 0 == measures.hot_keys(nulls.where("false"), "k", 0.5).count()
    with pytest.raises(ValueError):
        measures.hot_keys(hot, "k", 0)


def test_sketched_distinct(spark):
    got = measures.sketched_distinct(spark.range(20_000).select(F.floor(F.col("id") / 4).alias("k")), "k").first()
    assert got["n"] == 20_000 and abs(got["distinct_estimate"] - 5000) < 300 and abs(got["appearances"] - 4) < 0.3
    assert measures.sketched_distinct(spark.range(0), "id").first()["n"] == 0


def test_run_facts(spark):
    wide = spark.range(50_000).groupBy((F.col("id") % 1000).alias("k")).count()
    facts = measures.run_facts(wide)
    assert facts["exchanges"] == 1 and facts["shuffle_bytes"] > 0 and facts["spill_bytes"] == 0
    assert measures.run_facts(spark.range(10))["exchanges"] == 0


def test_minwise_values_of_short_and_long_texts(spark):
    long = " ".join(f"w{i}" for i in range(20_000))  # the words are split once, not once a shingle
    docs = spark.createDataFrame([(1, "one"), (2, ""), (3, None), (4, long)], "doc_id bigint, text string")
    got = minhash.signatures(docs, "doc_id", "text", k=3, bits=4).collect()
    assert sorted((r["doc_id"], r["component"]) for r in got) == [(d, c) for d in (1, 2, 4) for c in range(3)]
    assert all(0 <= r["value"] < 16 for r in got)


def test_expected_squares_of_many_rows(spark):
    """The number of pairs of 50,000 rows is beyond 32 bits; a row without a key is none."""
    keys = spark.range(50_000).select(F.col("id").alias("key")).unionAll(spark.sql("SELECT CAST(NULL AS BIGINT)"))
    got = {r["load"]: r["expected_sum_sq"] for r in measures.expected(keys, (0.5, 1.0)).collect()}
    assert got == {0.5: round(50_000 + 50_000 * 49_999 / 100_000, 3), 1.0: 99_999.0}

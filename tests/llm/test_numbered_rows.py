"""Rows are picked by their numbers without moving."""

from pyspark.sql import functions as F

from bucketcsr.llm import shared, simhash


def test_numbered_rows_stay_where_they_are(spark):
    rows = shared.store(spark.range(0, 70_000, 1, 3).select(F.col("id").alias("x")).withColumn("n", F.monotonically_increasing_id()))
    chosen = rows.where("x % 7 = 3 or x in (0, 69999)").select(F.col("n").alias("c"))
    want = {x for x in range(70_000) if x % 7 == 3 or x in (0, 69_999)}
    for most in (shared.BITMAP_BYTES, 0):
        got = [r["x"] for r in shared.numbered(rows, "n", chosen, "c", most).select("x").collect()]
        assert len(got) == len(want) and set(got) == want


def test_texts_kept_of_groups_are_not_exchanged(spark):
    docs = spark.createDataFrame([(i, f"one two three four five six seven w{i // 2}") for i in range(40)], "doc_id bigint, text string")
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        kept = simhash.one_per_group(docs, similarity=simhash.Similarity())
        assert "hashpartitioning" not in kept._jdf.queryExecution().executedPlan().toString()
        ids = [r["doc_id"] for r in kept.collect()]
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)
    assert ids and len(ids) == len(set(ids)) and all(i % 2 == 0 for i in ids)

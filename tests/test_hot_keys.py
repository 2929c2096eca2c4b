"""Builds and joins where one key holds nearly all rows."""

from collections import Counter

import pytest
from pyspark.sql import functions as F

from bucketcsr.operators import build, joins, probe
from bucketcsr.plans.params import BuildSpec

LIMIT = 200
SPEC = BuildSpec(bins=8, parts=4, hot_bucket_rows=LIMIT)


@pytest.fixture(scope="module")
def hot(spark):
    """4,000 rows: 95 % have key 7, some keys occur once, some rows none."""
    key = F.when(F.col("id") % 20 != 0, 7).when(F.col("id") % 40 == 0, F.col("id")).otherwise(None)
    return spark.range(4000).select(key.cast("bigint").alias("k"), F.col("id").alias("rid"))


def test_a_hot_bucket_fills_its_slice_in_pieces(hot):
    ix = build.build_binned(hot, "k", "rid", SPEC)
    assert len(ix.hot) == 1 and ix.hot[0][1] >= 3800  # other keys may share the bucket
    edges = ix.edges.select("bucket", "pos", "key", "rid").collect()
    n = hot.where("k is not null").count()
    assert sorted(r["pos"] for r in edges) == list(range(n)) and len({r["rid"] for r in edges}) == n
    slices = {r["bucket"]: (r["start"], r["len"]) for r in ix.offsets.collect()}
    assert sum(m for _, m in slices.values()) == n
    assert all(slices[r["bucket"]][0] <= r["pos"] < sum(slices[r["bucket"]]) for r in edges)
    plain = build.build_binned(hot, "k", "rid", BuildSpec(bins=8, parts=4))
    assert not plain.hot and {r["bucket"]: (r["start"], r["len"]) for r in plain.offsets.collect()} == slices


def test_no_task_sorts_a_whole_hot_bucket(hot):
    rows = build.bucketed(build.rows_of(hot, "k", "rid"), build.resolve(3900, SPEC), SPEC)
    cut = build.hot_chunks(rows, LIMIT)
    assert cut.groupBy("bucket", "chunk").count().where(F.col("count") > LIMIT).count() == 0
    # the pieces that are ranked one by one are of about the limit
    pieces = rows.where("key = 7").groupBy(F.pmod(F.xxhash64(*rows.columns), F.lit(3800 // LIMIT))).count().agg(F.max("count")).first()[0]
    assert pieces < 2 * LIMIT


@pytest.mark.parametrize("how", joins.HOW)
def test_joins_on_a_hot_key_equal_plain_ones(spark, hot, how):
    other = spark.createDataFrame([(7, 1), (7, 2), (7, 3), (80, 4), (81, 5), (None, 6)] + [(9000, 100 + i) for i in range(300)], "k bigint, r bigint")
    got = joins.bucket_join(hot, other, "k", "k", "rid", "r", how, SPEC)
    a, b = hot.select(F.col("k").alias("key"), F.col("rid").alias("l_rid")), other.select(F.col("k").alias("key"), F.col("r").alias("r_rid"))
    want = a.join(b, "key", how)
    assert Counter(map(tuple, got.select(*want.columns).collect())) == Counter(map(tuple, want.collect()))


def test_hot_lists_meet_chunk_by_chunk(hot):
    left = hot.where("k = 7").select(F.lit(1).alias("bucket"), F.col("k").alias("key"), F.col("rid").alias("l_rid"))
    right = left.where("l_rid % 8 = 1").withColumnRenamed("l_rid", "r_rid")
    pairs = probe.tiles(left, right, LIMIT)
    assert pairs.count() == left.count() * right.count() == pairs.distinct().count()


def test_counts_leave_each_task_as_one_number(spark, hot):
    got = probe.cobucket_count(hot.repartition(4), hot.repartition(4), "k", "k")
    assert got.first()["n_pairs"] == 3800**2 + 100
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "partial_count" in plan and "Window" not in plan


def test_a_stored_side_keeps_its_parts(spark, hot, tmp_path):
    from bucketcsr.sources import storage

    ix = build.build_binned(hot, "k", "rid", SPEC)
    storage.save(ix, str(tmp_path / "ix"))
    back = storage.load(spark, str(tmp_path / "ix"))
    assert back.hot == ix.hot
    other = spark.createDataFrame([(7, 1), (80, 4), (120, 5), (5, 6)], "k bigint, r bigint")
    met = probe.cobucket_probe(probe.align(back, other, "k", "r"), back)
    want = other.join(hot, "k").select("k", "r", "rid")
    assert Counter(map(tuple, met.collect())) == Counter(map(tuple, want.collect()))
    assert probe.cobucket_probe(probe.align(back, other, "k", "r"), back, "count").first()[0] == want.count()


def test_tables_bucketed_by_list_meet_without_an_exchange(spark, hot):
    from bucketcsr.measures import plan_facts
    from bucketcsr.sources import storage

    names = ("hot_lists_a", "hot_lists_b")
    try:
        one, two = (storage.save_lists_table(build.build_binned(hot, "k", "rid", SPEC), n, 4) for n in names)
        met = one.hint("merge").join(two.withColumnRenamed("n", "m"), ["bucket", "key"])
        assert plan_facts(met)["hash_exchanges"] == 0 and met.count() == 101
    finally:
        for n in names:
            spark.sql(f"drop table if exists {n}")

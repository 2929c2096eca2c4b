"""Stored indexes, explain texts, readers and SQL functions."""

import uuid

import pytest
from pyspark.sql import functions as F

from bucketcsr import catalogue
from bucketcsr.functions import udfs
from bucketcsr.functions.hashing import HashSpec, mix32
from bucketcsr.functions.rowid import dense_rid, file_rid
from bucketcsr.operators import build, probe
from bucketcsr.plans.explain import explain_build, explain_probe
from bucketcsr.plans.params import BuildSpec
from bucketcsr.sources import storage

SF = "/root/testdata/sf0.001"


def test_saved_index_opens_equal(spark, tmp_path):
    spec = BuildSpec(bins=4, parts=2, hash=HashSpec("xx64"))
    ix = build.build_binned(spark.read.parquet(f"{SF}/orders.parquet"), "o_custkey", "o_orderkey", spec)
    path = f"file://{tmp_path}/ix"
    storage.save(ix, path)
    again = storage.load(spark, path)
    assert (again.layout, again.spec) == (ix.layout, ix.spec)
    cols = ["bucket", "pos", "key", "rid"]
    assert again.edges.select(*cols).exceptAll(ix.edges.select(*cols)).count() == 0
    assert {r["rid"] for r in again.get(7).collect()} == {r["rid"] for r in ix.get(7).collect()}


def test_bucketed_tables_join_without_an_exchange(spark):
    names = [f"t_{uuid.uuid4().hex}" for _ in range(2)]
    orders = spark.read.parquet(f"{SF}/orders.parquet")
    a, b = probe.build_pair(orders, orders, "o_custkey", "o_custkey", "o_orderkey", "o_orderkey", BuildSpec(bins=8, parts=2))
    conf = {"spark.sql.requireAllClusterKeysForCoPartition": "false", "spark.sql.autoBroadcastJoinThreshold": "-1", "spark.sql.adaptive.enabled": "false"}
    before = {k: spark.conf.get(k) for k in conf}
    try:
        left, right = (storage.save_table(ix, n, 4) for ix, n in zip((a, b), names, strict=True))
        for k, v in conf.items():
            spark.conf.set(k, v)
        joined = left.join(right.withColumnRenamed("rid", "other"), ["bin", "bucket", "key"])
        plan = joined._jdf.queryExecution().executedPlan().toString()
        assert "Exchange" not in plan
        assert joined.count() == orders.groupBy("o_custkey").count().agg(F.sum(F.col("count") * F.col("count"))).first()[0]
    finally:
        for k, v in before.items():
            spark.conf.set(k, v)
        for n in names:
            spark.sql(f"DROP TABLE IF EXISTS {n}")


def test_explain_texts():
    assert "V = 50 buckets" in explain_build(100, BuildSpec(load=2.0, bins=5))
    assert explain_probe(1 << 20, False, False, 1).startswith("lookup") and "rows: 0" in explain_probe(1 << 20, False, False, 1)
    assert explain_probe(1 << 40, True, True, 1).startswith("cobucket")
    assert explain_probe(1 << 40, False, False, 30, "count").endswith("rows: 2.")


def test_row_numbers(spark):
    lines = spark.read.parquet(f"{SF}/lineitem.parquet")
    got = dense_rid(lines, "l_orderkey", groups=7).select("l_orderkey", "rid").orderBy("rid").collect()
    assert [r["rid"] for r in got] == list(range(len(got)))
    assert all(a["l_orderkey"] <= b["l_orderkey"] for a, b in zip(got, got[1:], strict=False))
    assert file_rid(lines).select("rid").distinct().count() == len(got)


def test_functions(spark):
    df = spark.createDataFrame([(0,), (1,), (2**31 - 1,), (12345,), (None,)], "k bigint")
    assert df.where(~mix32(F.col("k")).eqNullSafe(udfs.mix32_arrow("k"))).count() == 0
    with pytest.raises(ValueError):
        HashSpec("nothing")
    with pytest.raises(ValueError):
        storage.read_any(spark, SF, "xls")


def test_examples_stand_on_given_tables(spark):
    """The worked example and the join with null keys read their rows from the tables."""
    d = "/root/testdata/sf0.001"
    made = catalogue.queries()["csr_example"](spark, d)
    assert any("orders" in f for f in made.inputFiles())
    offsets = [tuple(r) for r in made.orderBy("bucket").collect()]
    orders = spark.read.parquet(f"{d}/orders.parquet")
    assert [b for b, _, _ in offsets] == list(range(10)) and sum(n for _, _, n in offsets) == orders.count()
    assert all(start == sum(n for _, _, n in offsets[:b]) for b, start, _ in offsets) and any(n == 0 for _, _, n in offsets)
    joined = catalogue.queries()["join_null_keys"](spark, d)
    assert {n for f in joined.inputFiles() for n in ("orders", "events") if n in f} == {"orders", "events"}
    a = {r["o_orderkey"]: r["o_custkey"] for r in orders.collect() if r["o_custkey"] % 10 != 3}
    b = {r["event_id"]: r["user_id"] for r in spark.read.parquet(f"{d}/events.parquet").collect() if r["user_id"] % 10 != 7}
    rows = [tuple(r) for r in joined.collect()]
    pairs = [(a[i], i, j) for i in a for j in b if a[i] == b[j]]
    assert sorted(r for r in rows if None not in r) == sorted(pairs)
    lonely = [r for r in rows if None in r]
    assert len(lonely) == orders.count() - len({i for _, i, _ in pairs}) + 1000 - len({j for _, _, j in pairs}) and any(r[0] is None for r in lonely)

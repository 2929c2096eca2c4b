"""Baselines against simulations."""

import random

import pytest
from pyspark.sql import functions as F

from bucketcsr.baselines import cuckoo, joins, linear, lists
from bucketcsr.functions.hashing import HashSpec, bucket_of
from bucketcsr.plans.params import capacity, storage_elements, work_terms


def homes(spark, keys, slots):
    df = spark.createDataFrame([(k, i) for i, k in enumerate(keys)], "key bigint, rid bigint")
    return df, [r[0] for r in df.orderBy("rid").select(bucket_of([F.col("key")], slots)).collect()]


@pytest.mark.parametrize("keys,slots", [([1] * 20, 41), (list(range(60)), 67), ([x % 9 for x in range(50)], 53), ([4], 2)])
def test_linear_probing_closed_form(spark, keys, slots):
    df, at = homes(spark, keys, slots)
    table, moved = linear.simulate(at, slots)
    random.Random(1).shuffle(at)
    assert linear.simulate(at, slots)[1] == moved  # order does not matter
    assert linear.displacement(df, slots, bins=4).first()["displacement"] == moved
    cost = 0
    for h in at:
        k = h
        while table[k] is not None:
            k = (k + 1) % slots
        cost += (k - h) % slots + 1
    assert linear.find_all_cost(df, slots, bins=4).first()["slots_read"] == cost


def test_equal_keys_cost_quadratically(spark):
    df, _ = homes(spark, [7] * 30, 64)
    assert linear.displacement(df, 64).first()["displacement"] == 30 * 29 // 2
    with pytest.raises(ValueError):
        linear.displacement(df, 30)


def test_lists(spark):
    df, _ = homes(spark, [1, 1, 1, 2], 1)
    r = lists.chain_cost(df, 1).first()
    assert (r["insert_steps"], r["find_all_steps"], r["words"]) == (6, 16, 9)
    s = lists.slab_cost(df, 1, slab=3).first()
    assert (s["slabs"], s["links"], s["slabs_read"]) == (2, 1, 8)
    assert lists.resizable_cost(5000) == {"capacity": 8192, "copied": 1024 + 2048 + 4096, "rehashes": 3}
    assert lists.coalesced_cost(df, 8, bins=1).first()["collisions"] >= 2
    two = lists.two_choice_cost(spark.range(400).select(F.col("id").alias("key"), F.col("id").alias("rid")), 400, bins=1).first()
    assert two["longest_two"] <= two["longest_one"]


def test_cuckoo_places_unique_keys_and_stashes_many_equal_ones(spark):
    unique = spark.range(200).select(F.col("id").alias("key"), F.col("id").alias("rid"))
    t = cuckoo.cuckoo_build(unique, 400)
    assert t.stash.count() == 0 and t.placed.select("slot").distinct().count() == 200
    assert sorted(tuple(r) for r in t.lookup(unique.where("key < 5")).collect()) == [(i, i, i) for i in range(5)]
    same = spark.range(6).select(F.lit(3).cast("bigint").alias("key"), F.col("id").alias("rid"))
    s = cuckoo.cuckoo_build(same, 20, max_rounds=6)
    assert s.stash.count() >= 2
    assert s.lookup(same).count() == 36


def test_unique_only_table_refuses_duplicates(spark):
    df = spark.createDataFrame([(1,), (1,), (2,)], "k bigint")
    with pytest.raises(joins.DuplicateKeyError):
        joins.unique_table(df, "k")
    assert joins.search_steps(7) == 3 and joins.search_steps(0) == 0


def test_cost_terms():
    one, two = work_terms(100, 50, 4, 2, False), work_terms(100, 50, 4, 2, True)
    assert two["work"] > one["work"] and one["per_core"] == one["work"] / 2
    assert storage_elements(100, 50, 4, True)["reorganised"] == 200
    assert capacity(32 << 30, 1.0, False, entry_bytes=8) > capacity(32 << 30, 1.0, True, entry_bytes=8)
    assert HashSpec().family == "murmur32"


def test_chains_as_nodes_and_their_probe_cost(spark):
    from bucketcsr.operators import build
    from bucketcsr.plans.params import BuildSpec

    keys = [random.Random(3).randrange(40) for _ in range(200)]
    df = spark.createDataFrame([(k, i) for i, k in enumerate(keys)] + [(None, 900)], "key bigint, rid bigint")
    probes = [*range(60), None, 5, 5]
    asked = spark.createDataFrame([(k,) for k in probes], "key bigint")
    for hot in (None, 10):  # with and without hot buckets
        ix = build.build_binned(df, "key", "rid", BuildSpec(buckets=23, bins=4, parts=2, hot_bucket_rows=hot))
        chains = {}
        for r in lists.chain_table(ix).orderBy("node").collect():
            chains.setdefault(r["bucket"], []).append(r)
        assert sum(map(len, chains.values())) == len(keys)
        for nodes in chains.values():
            assert [n["next_node"] for n in nodes] == [n["node"] for n in nodes[1:]] + [None]
        at = {r["key"]: r["b"] for r in asked.where("key is not null").distinct().select("key", bucket_of([F.col("key")], 23).alias("b")).collect()}
        want = dict.fromkeys(("hits", "misses", "hit_nodes", "miss_nodes"), 0)
        for k in probes:
            if k is None:
                continue
            chain = [n["key"] for n in chains.get(at[k], [])]
            kind = "hit" if k in chain else "miss"
            want["hits" if kind == "hit" else "misses"] += 1
            want[f"{kind}_nodes"] += chain.index(k) + 1 if kind == "hit" else len(chain)
        assert lists.chain_probe_cost(ix, asked, "key").first().asDict() == want


def test_two_choice_rounds_balance(spark):
    keys = spark.range(4000).select(F.col("id").alias("key"), F.col("id").alias("rid"))
    placed = lists.two_choice_rounds(keys, 1000, rounds=8)
    assert placed.agg(F.sum("n")).first()[0] == 4000
    two = placed.groupBy("tab", "bucket").agg(F.sum("n").alias("s")).agg(F.max("s")).first()[0]
    one = keys.groupBy(bucket_of([F.col("key")], 1000)).count().agg(F.max("count")).first()[0]
    assert two < one
    assert lists.two_choice_rounds(keys.where("false"), 10, rounds=2).count() == 0


@pytest.mark.parametrize("load", [0.5, 0.9])
def test_walks_of_a_miss(spark, load):
    keys = [x * x % 97 for x in range(60)]
    slots = linear.slots_for(len(keys), load)
    df, at = homes(spark, keys, slots)
    table, _ = linear.simulate(at, slots)
    walk = lambda h: next(k for k in range(slots) if table[(h + k) % slots] is None) + 1
    assert linear.miss_cost(df, slots, bins=5).first()["slots_read"] == sum(walk(h) for h in range(slots))


def test_walks_take_time_in_proportion_to_the_slots(spark):
    """Every window frame ends at its row; one that ends with its bin costs slots times slots."""
    df = spark.range(1000).select(F.col("id").alias("key"))
    plans = [f(df, 2000)._jdf.queryExecution().optimizedPlan().toString() for f in (linear.miss_cost, linear.find_all_cost)]
    assert all("unboundedfollowing$()" not in p for p in plans) and all("currentrow$()" in p for p in plans)


def test_broadcast_join_of_a_side_over_the_limit(spark):
    """A side of more rows than may be sent at once goes out in pieces and loses no pair."""
    a = spark.range(400).select((F.col("id") % 150).alias("key"), F.col("id").alias("l_rid")).unionAll(spark.sql("SELECT CAST(NULL AS BIGINT), -1L"))
    b = spark.range(200).select((F.col("id") % 170).alias("key"), F.col("id").alias("r_rid")).unionAll(spark.sql("SELECT CAST(NULL AS BIGINT), -1L"))
    want = sorted(map(tuple, a.join(b, "key").collect()))
    got = joins.broadcast_join(a, b, "key", most_rows=40)
    assert got.columns == ["key", "l_rid", "r_rid"] and sorted(map(tuple, got.collect())) == want
    assert joins.broadcast_join(a, b.where("key > 500"), "key", most_rows=1).count() == 0
    assert joins.broadcast_join(a.where("false"), b, "key", most_rows=40).count() == 0

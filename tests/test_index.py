"""Invariants of builds and probes on small inputs."""

import random
from collections import Counter, defaultdict

import pytest
from hypothesis import HealthCheck, given, settings, strategies as st
from pyspark.sql import functions as F

from bucketcsr.functions.hashing import HashSpec, bucket_of
from bucketcsr.measures import plan_facts
from bucketcsr.operators import build, dynamic, joins, probe
from bucketcsr.operators.prefix import exclusive_prefix
from bucketcsr.plans.params import BuildSpec, bucket_count, choose_load, resolve

KEYS = [5, 5, -3, 2**63 - 1, -(2**63), 0, 7, 7, 7, 12, 900, None]


def frame(spark, keys, kind="bigint"):
    return spark.createDataFrame([(k, i) for i, k in enumerate(keys)], f"key {kind}, rid bigint")


def rows(df, *cols):
    return sorted(tuple(r) for r in df.select(*cols).collect())


def check_index(ix, keys):
    edges = ix.edges.collect()
    offsets = {r["bucket"]: (r["start"], r["len"]) for r in ix.offsets.collect()}
    present = [(k, i) for i, k in enumerate(keys) if k is not None]
    assert sorted((r["key"], r["rid"]) for r in edges) == sorted(present)
    assert sorted(r["pos"] for r in edges) == list(range(len(present)))
    assert sum(n for _, n in offsets.values()) == len(present)
    at = 0
    for b in sorted(offsets):
        assert offsets[b][0] == at
        at += offsets[b][1]
    for r in edges:
        start, n = offsets[r["bucket"]]
        assert start <= r["pos"] < start + n
        assert r["bin"] == r["bucket"] // ix.layout.width
    for r in ix.bins.collect():
        own = [o for b, o in offsets.items() if b // ix.layout.width == r["bin"]]
        assert r["n"] == sum(n for _, n in own) and r["bin_start"] == min(s for s, _ in own)


@pytest.mark.parametrize("load,bins,parts", [(1.0, 3, 2), (0.5, 1, 1), (4.0, 100, 4), (20.0, 2, 2)])
@pytest.mark.parametrize("how", [build.build_binned, build.build_single_sweep, build.build_tiered])
def test_builds_agree_with_definition(spark, how, load, bins, parts):
    check_index(how(frame(spark, KEYS), "key", "rid", BuildSpec(load=load, bins=bins, parts=parts)), KEYS)


@settings(max_examples=6, deadline=None, suppress_health_check=[HealthCheck.function_scoped_fixture])
@given(st.lists(st.integers(-50, 50), max_size=40), st.sampled_from([0.5, 1.0, 3.0]), st.integers(1, 9))
def test_single_and_binned_are_identical(spark, keys, load, bins):
    spec = BuildSpec(load=load, bins=bins, parts=2)
    one, two = (rows(how(frame(spark, keys), "key", "rid", spec).edges, "bucket", "pos", "key", "rid") for how in (build.build_single_sweep, build.build_binned))
    assert one == two


def test_bins_that_dont_divide_the_range():
    layout = resolve(10, BuildSpec(buckets=10, bins=3))
    assert (layout.width, layout.bins) == (4, 3)
    assert resolve(5, BuildSpec(bins=1 << 30)).bins == 5
    assert bucket_count(0, 1.0) == 1 and bucket_count(5, 2.0) == 3
    assert choose_load(10, 0) == 2.0 and choose_load(0, 10) == 1.0
    with pytest.raises(ValueError):
        bucket_count(5, 0)


def test_hash_is_the_same_for_int_and_bigint_and_zero_signs(spark):
    df = spark.createDataFrame([(1, 0.0), (1, -0.0)], "i int, d double")
    rows_i = build.rows_of(df, "i", None)
    assert rows_i.schema["key"].dataType.simpleString() == "bigint"
    got = {r[0] for r in build.rows_of(df, "d", None).select(bucket_of([F.col("key")], 97)).collect()}
    assert len(got) == 1
    with pytest.raises(ValueError):
        bucket_of([F.col("k")], 1 << 40, HashSpec())


def brute_pairs(a, b):
    by = defaultdict(list)
    for j, k in enumerate(b):
        by[k].append(j)
    return sorted((k, i, j) for i, k in enumerate(a) if k is not None for j in by[k])


@pytest.mark.parametrize("seed", range(2))
def test_probes_and_joins_agree_with_brute_force(spark, seed):
    rng = random.Random(seed)
    a = [rng.choice([None, *range(12)]) for _ in range(40)]
    b = [rng.choice([None, *range(6, 20)]) for _ in range(30)]
    left, right = frame(spark, a), frame(spark, b)
    spec = BuildSpec(bins=5, parts=3)
    want = brute_pairs(a, b)
    ix = build.build_binned(right, "key", "rid", spec)
    for kernel in ("merge", "scan"):
        assert rows(probe.lookup_probe(ix, left, "key", "rid", kernel=kernel), "key", "l_rid", "r_rid") == want
    assert rows(probe.lookup_probe(ix, left, "key", "rid", broadcast_bytes=0), "key", "l_rid", "r_rid") == want
    ia, ib = probe.build_pair(left, right, "key", "key", "rid", "rid", spec)
    for kernel in ("merge", "scan"):
        assert rows(probe.cobucket_probe(ia, ib, kernel=kernel), "key", "l_rid", "r_rid") == want
    assert probe.cobucket_probe(ia, ib, "count").first()[0] == len(want) == probe.lookup_probe(ix, left, "key", "rid", "count").first()[0]
    assert {r[0] for r in probe.cobucket_probe(ia, ib, kernel="set").collect()} == {k for k, _, _ in want}
    first = {(k, i): min(j for x, y, j in want if (x, y) == (k, i)) for k, i, _ in want}
    assert {(r["key"], r["l_rid"]): r["r_rid"] for r in probe.cobucket_probe(ia, ib, "first").collect()} == first
    semi, anti = (joins.bucket_join(left, right, "key", "key", "rid", "rid", h, spec).select("l_rid").collect() for h in ("left_semi", "left_anti"))
    assert sorted(r[0] for r in semi + anti) == list(range(40))
    full = joins.bucket_join(left, right, "key", "key", "rid", "rid", "full", spec).collect()
    assert sum(r["l_rid"] is not None and r["r_rid"] is not None for r in full) == len(want)
    assert {r["l_rid"] for r in full} - {None} == set(range(40)) and {r["r_rid"] for r in full} - {None} == set(range(30))


def test_comparisons_at_one_bucket(spark):
    a, b = probe.build_pair(frame(spark, [1, 2, 3]), frame(spark, [2, 2]), "key", "key", "rid", "rid", BuildSpec(buckets=1))
    r = probe.comparisons(a, b).first()
    assert (r["comparisons"], r["cobucket_fetches"], r["cobucket_elements"]) == (6, 1, 5)


def test_co_bucket_probe_moves_each_side_once(spark):
    a, b = probe.build_pair(frame(spark, range(50)), frame(spark, range(50)), "key", "key", "rid", "rid", BuildSpec(bins=8, parts=4))
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    try:
        facts = plan_facts(probe.cobucket_probe(a, b))
    finally:
        spark.conf.set("spark.sql.adaptive.enabled", "true")
    assert facts["hash_exchanges"] == 0 and facts["single"] == 0 and facts["python"] == 0


def test_empty_tables(spark):
    none = frame(spark, [])
    ix = build.build_binned(none, "key", "rid", BuildSpec(bins=2))
    assert ix.edges.count() == 0 and ix.offsets.count() == 0
    assert probe.lookup_probe(ix, frame(spark, [1]), "key", "rid").count() == 0
    a, b = probe.build_pair(none, frame(spark, [1]), "key", "key", "rid", "rid")
    assert probe.cobucket_probe(a, b, "count").first()[0] == 0


def test_prefix_matches_the_plain_window(spark):
    df = spark.createDataFrame([(i // 4, i, (i * 7) % 5) for i in range(23)], "g bigint, o bigint, n bigint")
    assert rows(exclusive_prefix(df, "g", "o", "n"), "o", "start") == rows(exclusive_prefix(df, "g", "o", "n", naive=True), "o", "start")


def test_point_lookups_and_dense_offsets(spark):
    ix = build.build_binned(frame(spark, KEYS), "key", "rid", BuildSpec(bins=4, parts=2))
    assert rows(ix.get(7), "rid") == [(6,), (7,), (8,)]
    assert rows(ix.get_many([5, 404]), "rid") == [(0,), (1,)]
    array = {r["i"]: r["start"] for r in ix.offset_array().collect()}
    assert len(array) == ix.layout.v + 1 and array[ix.layout.v] == 11
    assert all(array[i] <= array[i + 1] for i in range(ix.layout.v))


def test_delete_append_compact(spark):
    spec = BuildSpec(bins=4, parts=2)
    live = dynamic.LiveIndex(build.build_binned(frame(spark, [1, 2, 2, 3]), "key", "rid", spec))
    more = spark.createDataFrame([(2, 10), (9, 11)], "key bigint, rid bigint")
    live = live.append(more, "key", "rid").delete(spark.createDataFrame([(1,), (1,), (77,)], "rid bigint"))
    packed = live.compact()
    assert rows(packed.edges, "key", "rid") == [(1, 0), (2, 2), (2, 10), (3, 3), (9, 11)]
    assert sorted(r["pos"] for r in packed.edges.collect()) == list(range(5))
    lens = live.offsets().agg(F.sum("len"), F.sum("live_len")).first()
    assert tuple(lens) == (4, 3)


def test_hot_chunks_are_bounded_and_whole(spark):
    df = frame(spark, [1] * 100 + [2] * 3)
    rows_ = build.bucketed(build.rows_of(df, "key", "rid"), resolve(103, BuildSpec()), BuildSpec())
    got = build.hot_chunks(rows_, 10).collect()
    sizes = Counter((r["bucket"], r["chunk"]) for r in got)
    assert max(sizes.values()) <= 10 and len(got) == 103
    for b in {r["bucket"] for r in got}:
        own = sorted(r["rank"] for r in got if r["bucket"] == b)
        assert own == list(range(len(own)))


def test_an_index_over_the_broadcast_limit_is_looked_up_in_pieces(spark):
    """Beside a probe side of several times its size the choice stays with the lookup, whatever the size."""
    built, probing = frame(spark, list(range(200))), frame(spark, [x % 230 for x in range(900)] + [None])
    ix = build.build_binned(built, "key", "rid", BuildSpec(bins=4, parts=2))
    want = rows(built.withColumnRenamed("rid", "r_rid").join(probing.withColumnRenamed("rid", "l_rid"), "key"), "key", "l_rid", "r_rid")
    kind, got = probe.auto_probe(ix, probing, "key", "rid", appearances=4.07, broadcast_bytes=2000)
    assert kind == "lookup" and rows(got, "key", "l_rid", "r_rid") == want
    kind, got = probe.auto_probe(ix, probing, "key", "rid", appearances=4.07, broadcast_bytes=0)
    assert kind == "cobucket" and rows(got, "key", "l_rid", "r_rid") == want
    assert probe.auto_probe(ix, built, "key", "rid", appearances=4.07, broadcast_bytes=2000)[0] == "cobucket"


@pytest.mark.parametrize("hot", [None, 5])
def test_more_bins_than_the_driver_lists(spark, monkeypatch, hot):
    """One bin per bucket: the counts stay in a table, and the index is the same."""
    df = frame(spark, [x * x % 101 for x in range(300)] + [7] * 20 + [None])
    spec = BuildSpec(bins=1 << 30, parts=3, hot_bucket_rows=hot)
    cols = {"bins": ("bin", "part", "n", "bin_start"), "offsets": ("part", "bin", "bucket", "start", "len"), "edges": ("part", "bin", "bucket", "pos", "key", "rid")}
    one = build.build_binned(df, "key", "rid", spec)
    want = {k: rows(getattr(one, k), *c) for k, c in cols.items()}
    tiered = rows(build.build_tiered(df, "key", "rid", spec, tier_bins=128).edges, *cols["edges"])
    monkeypatch.setattr(build, "MOST_LISTED", 10)

    def refused(_):
        raise AssertionError("bins are listed")

    counted = build.count_bins
    monkeypatch.setattr(build, "count_bins", refused)
    two = build.build_binned(df, "key", "rid", spec)
    assert {k: rows(getattr(two, k), *c) for k, c in cols.items()} == want
    monkeypatch.setattr(build, "count_bins", counted)  # tiers are few and listed
    assert rows(build.build_tiered(df, "key", "rid", spec, tier_bins=128).edges, *cols["edges"]) == tiered

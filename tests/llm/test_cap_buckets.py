"""Buckets of the cap filters: cut over batches, single and double precision, and the marks that stand for many links."""

from collections import Counter

import numpy as np
import pytest

from bucketcsr.llm import capfilter

from .test_other_operators import brute_links


@pytest.mark.parametrize("kind", ["float", "double"])
@pytest.mark.parametrize("tile", [4, 2048])
def test_links_when_buckets_run_over_many_batches(spark, kind, tile):
    rng = np.random.default_rng(9)
    base = rng.normal(size=(4, 16))
    rows = [(i, [float(np.float32(x)) for x in base[i % 4] + rng.normal(0, 0.05, 16)], "a" if i % 3 else "b") for i in range(120)]
    rows += [(200 + i, [float(np.float32(x)) for x in rng.normal(size=5)], "a") for i in range(10)] + [(300, rows[0][1], rows[0][2])]
    df = spark.createDataFrame(rows, f"vec_id bigint, embedding array<{kind}>, label string")
    old = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "7")
    try:
        got = capfilter.near_duplicates(df, caps=capfilter.Caps(tile=tile)).collect()
    finally:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", old)
    assert Counter((r["vec_id"], r["n_links"], r["component_id"]) for r in got) == brute_links(rows)


def components(size, pairs):
    root = list(range(size))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in pairs:
        root[find(int(a))] = find(int(b))
    return [min(y for y in range(size) if find(y) == find(x)) for x in range(size)]


@pytest.mark.parametrize("share", [0.0, 0.004, 0.02, 0.3, 1.0])
def test_marks_connect_what_the_links_connect(share):
    near = np.random.default_rng(2).random((70, 90)) < share
    rows, columns = np.nonzero(near)
    assert components(160, zip(*capfilter._tree(near), strict=True)) == components(160, zip(rows, columns + 70, strict=True))


def test_a_long_chain_of_links_is_one_component():
    near = np.eye(80, dtype=bool) | np.eye(80, k=1, dtype=bool)
    assert set(components(160, zip(*capfilter._tree(near), strict=True))) == {0}

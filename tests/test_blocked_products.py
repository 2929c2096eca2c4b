"""Sparse products and triangle counts cut into blocks: what moves are lists, not products or wedges."""

import itertools
import random
import re

import pytest

from bucketcsr.operators import applications as apps
from bucketcsr.plans.params import BuildSpec

SPEC = BuildSpec(bins=3, parts=2)


def _times(a, b):
    want = {}
    for (i, k), x in a:
        for (k2, j), y in b:
            if k == k2 and k is not None:
                want[i, j] = want.get((i, j), 0) + x * y
    return want


@pytest.mark.parametrize("kind", ["bigint", "string"])
def test_a_matrix_times_its_transpose_in_many_blocks(spark, kind):
    rng = random.Random(4)
    name = (lambda x: x) if kind == "bigint" else str
    a = [((name(rng.choice([-(2**63), *range(9), 2**63 - 1])), rng.choice([None, *range(6)])), rng.randrange(-3, 5)) for _ in range(60)] + [((None, 1), 2), ((None, 2), 3)]
    df = spark.createDataFrame([(i, k, v) for (i, k), v in a], f"row {kind}, col bigint, val bigint")
    got = apps.spgemm(df, None, SPEC, block_products=10).collect()
    want = _times(a, [((k, i), v) for (i, k), v in a])
    assert len(got) == len(want) and {(r["row"], r["col"]): r["val"] for r in got} == want


def test_two_matrices_in_many_blocks(spark):
    rng = random.Random(5)
    a, b = ([((rng.randrange(12), rng.randrange(7)), rng.randrange(5)) for _ in range(50)] for _ in range(2))
    b = [((i % 7, j), v) for (i, j), v in b]
    one, two = (spark.createDataFrame([(i, k, v) for (i, k), v in m], "row bigint, col bigint, val bigint") for m in (a, b))
    got = apps.spgemm(one, two, SPEC, block_products=10)
    assert {(r["row"], r["col"]): r["val"] for r in got.collect()} == _times(a, b)
    # products are added up where they are made: no exchange by row and column
    exchanges = re.findall(r"Exchange (\w+)\(([^)]*)", got._jdf.queryExecution().executedPlan().toString())
    assert exchanges and not [at for kind, at in exchanges if kind == "hashpartitioning" and "row#" in at and "col#" in at]


def test_triangles_in_many_blocks(spark):
    rng = random.Random(6)
    edges = {(rng.randrange(30), rng.randrange(30)) for _ in range(150)} | {(0, i) for i in range(30)}
    plain = {tuple(sorted(e)) for e in edges if e[0] != e[1]}
    want = sum((a, b) in plain and (b, c) in plain and (a, c) in plain for a, b, c in itertools.combinations(range(30), 3))
    df = spark.createDataFrame([*edges, (None, 1), (2, None)], "src bigint, dst bigint")
    got = apps.count_triangles(df, SPEC, block_edges=20)
    assert got.first()[0] == want
    # lists meet in their blocks: no exchange by the ends of a wedge
    assert "hashpartitioning(p#" not in got._jdf.queryExecution().executedPlan().toString()
    assert apps.count_triangles(df.where("false"), SPEC).first()[0] == 0

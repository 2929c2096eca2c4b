"""Range and as-of joins, sparse products, triangles, k-mers and sketches on small inputs."""

import itertools
import random

from pyspark.sql import functions as F

from bucketcsr.baselines import minhash
from bucketcsr.operators import applications as apps, joins
from bucketcsr.plans.params import BuildSpec

SPEC = BuildSpec(bins=3, parts=2)


def test_range_join(spark):
    rng = random.Random(3)
    points = [rng.randrange(100) for _ in range(40)]
    spans = [(a, a + rng.randrange(0, 30)) for a in (rng.randrange(100) for _ in range(15))]
    p = spark.createDataFrame([(x, i) for i, x in enumerate(points)], "x bigint, i bigint")
    s = spark.createDataFrame([(a, b, j) for j, (a, b) in enumerate(spans)], "lo bigint, hi bigint, j bigint")
    got = sorted(tuple(r) for r in joins.range_join(p, s, "x", "lo", "hi", 8).select("i", "j").collect())
    assert got == sorted((i, j) for i, x in enumerate(points) for j, (a, b) in enumerate(spans) if a <= x < b)


def test_asof_takes_the_last_at_or_before(spark):
    left = spark.createDataFrame([(1, 5, "a"), (1, 1, "b"), (2, 9, "c")], "k bigint, t bigint, tag string")
    right = spark.createDataFrame([(1, 2, 20.0), (1, 5, 50.0), (1, 6, 60.0)], "k bigint, t bigint, v double")
    got = {r["tag"]: r["last_value"] for r in joins.asof_join(left, right, "k", "t", "v").collect()}
    assert got == {"a": 50.0, "b": None, "c": None}


def test_sparse_products(spark):
    a = {(0, 0): 2, (0, 2): 1, (1, 1): 3}
    b = {(0, 1): 4, (2, 0): 5, (1, 1): 6}
    frame = lambda m: spark.createDataFrame([(i, j, v) for (i, j), v in m.items()], "row bigint, col bigint, val bigint")
    got = {(r["row"], r["col"]): r["val"] for r in apps.spgemm(frame(a), frame(b), SPEC).collect()}
    want = {}
    for (i, k), x in a.items():
        for (k2, j), y in b.items():
            if k == k2:
                want[i, j] = want.get((i, j), 0) + x * y
    assert got == want
    x = spark.createDataFrame([(0, 10), (2, 1)], "idx bigint, x bigint")
    assert {r["row"]: r["y"] for r in apps.spmv(frame(a), x, SPEC).collect()} == {0: 21}


def test_triangles(spark):
    rng = random.Random(5)
    edges = {(rng.randrange(14), rng.randrange(14)) for _ in range(50)}
    plain = {tuple(sorted(e)) for e in edges if e[0] != e[1]}
    want = sum((a, b) in plain and (b, c) in plain and (a, c) in plain for a, b, c in itertools.combinations(range(14), 3))
    df = spark.createDataFrame(list(edges), "src bigint, dst bigint")
    assert apps.count_triangles(df, SPEC).first()[0] == want


def test_kmers_and_cells(spark):
    docs = spark.createDataFrame([(1, "abcdé"), (2, "ab"), (3, None)], "doc_id bigint, text string")
    assert sorted((r["doc_id"], r["pos"], r["kmer"]) for r in apps.kmers(docs, "doc_id", "text", 4).collect()) == [(1, 0, "abcd"), (1, 1, "bcdé")]
    v = spark.createDataFrame([([0.1, -0.1, 1.0],), ([0.2, -0.3, 1.2],)], "embedding array<float>")
    assert {tuple(r["cell"]) for r in apps.cells(v, 0.5).collect()} == {(0, -1, 2)}


def test_minhash_estimates_similarity(spark):
    a = " ".join(str(i) for i in range(200))
    b = " ".join(str(i) for i in range(20, 220))
    docs = spark.createDataFrame([(1, a), (2, b)], "doc_id bigint, text string")
    k = 64
    sig = minhash.signatures(docs, "doc_id", "text", k=k)
    pair = sig.where("doc_id = 1").alias("x").join(sig.where("doc_id = 2").alias("y"), "component")
    equal = pair.where(F.col("x.value") == F.col("y.value")).count()
    got = spark.range(1).select(minhash.estimate(F.lit(equal), k)).first()[0]
    assert abs(got - 179 / 219) < 0.2

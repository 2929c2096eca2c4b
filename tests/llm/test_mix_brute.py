"""The mix row by row: quotas over blocks in keyed order, in plain Python over Spark's hashes."""

import re
from collections import Counter, defaultdict

import pytest
from pyspark.sql import functions as F

from bucketcsr.llm import mixing

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def plain(docs, plan):
    """Counter of (doc_id, size, passes) by the rule of the docstring."""
    key = F.xxhash64(F.lit(plan.seed), F.col("doc_id").cast("string"), F.xxhash64("text"))
    hashed = docs.select("doc_id", "text", "source", key.alias("key"))
    hashed = hashed.select("*", F.xxhash64(F.lit(1), "key").alias("deal"), F.xxhash64(F.lit(3), "key").alias("rank"))
    by = defaultdict(list)
    for r in hashed.collect():
        by[r["source"]].append((r["doc_id"], len(WORD.findall(r["text"] or "")), r["deal"], r["rank"]))
    order = sorted(by, key=lambda s: (s is None, s or ""))
    goal = mixing.targets({s: sum(r[1] for r in rows) for s, rows in by.items()}, plan)
    spark, out = docs.sparkSession, Counter()
    for s_id, s in enumerate(order):
        rows, total = by[s], sum(r[1] for r in by[s])
        n_blocks = max(1, min(plan.blocks, len(rows)))
        blocks = defaultdict(list)
        for r in rows:
            blocks[r[2] % n_blocks].append(r)
        ids = spark.createDataFrame([(s_id, b) for b in blocks], "s int, b int")
        ranks = {r["b"]: r["h"] for r in ids.select("b", F.xxhash64(F.lit(2), F.lit(plan.seed), "s", "b").alias("h")).collect()}
        whole = int(goal[s] // total) if total else 0
        left = goal[s] - whole * total
        taken, missing = set(), left
        for b in sorted(blocks, key=lambda b: (ranks[b], b)):
            size = sum(r[1] for r in blocks[b])
            quota = min(max(left, 0.0), size)
            left -= size
            if quota <= 0:
                continue
            upto = 0
            for i, r in sorted(enumerate(blocks[b]), key=lambda p: p[1][3]):
                upto += r[1]
                if quota >= size or upto <= quota:
                    taken.add((b, i))
                    missing -= r[1]
        spare = [(abs(missing - r[1]), r[3], (b, i)) for b in blocks for i, r in enumerate(blocks[b]) if (b, i) not in taken and abs(missing - r[1]) < missing]
        if spare:
            taken.add(min(spare)[2])
        for b in blocks:
            for i, r in enumerate(blocks[b]):
                out[(r[0], r[1], whole + ((b, i) in taken))] += 1
    return out


@pytest.mark.parametrize("plan", [mixing.MixPlan(), mixing.MixPlan(weights=(9.0, 0.1), blocks=7, shards=5, seed=3), mixing.MixPlan(most_passes=1.4, blocks=1)])
def test_rows_equal_the_plain_rule(spark, plan):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text", "source")
    docs = docs.unionByName(spark.createDataFrame([(90001, None, None), (90002, "a b c", None), (90003, "", "src1"), (90004, "w " * 700, "z")], docs.schema))
    got = mixing.mix(docs, plan=plan, keep=["doc_id"])
    assert Counter((r["doc_id"], r["size"], r["passes"]) for r in got.collect()) == plain(docs, plan)

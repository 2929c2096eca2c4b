"""What a triangle count moves: whole lists of narrow numbers, few times, a bounded number of them at once."""

import itertools
import random

import pytest

from bucketcsr import measures
from bucketcsr.operators import applications as apps
from bucketcsr.plans.params import BuildSpec

SPEC = BuildSpec(bins=3, parts=2)


def _graph(seed, nodes, n):
    """Random pairs, some of them twice, and a node with an edge to every other."""
    rng = random.Random(seed)
    edges = [(rng.randrange(nodes), rng.randrange(nodes)) for _ in range(n)]
    return edges + edges[: n // 3] + [(i, nodes // 2) for i in range(nodes)]


def _count(edges, nodes):
    near = [set() for _ in range(nodes)]
    for a, b in edges:
        if a != b:
            near[min(a, b)].add(max(a, b))
    return sum(len(near[a] & near[b]) for a in range(nodes) for b in near[a])


@pytest.mark.parametrize("named", ["src, dst", "src * 4611686018427387 - 4611686018427387904, dst * 4611686018427387 - 4611686018427387904", "string(src), string(dst)"])
def test_groups_of_blocks_in_rounds(spark, named):
    edges = _graph(7, 40, 300)
    df = spark.createDataFrame([*edges, (None, 1), (2, None)], "src bigint, dst bigint").selectExpr(*[f"{e} AS {n}" for e, n in zip(named.split(", "), ("src", "dst"), strict=True)])
    plain = {(min(e), max(e)) for e in edges if e[0] != e[1]}
    want = sum({(a, b), (b, c), (a, c)} <= plain for a, b, c in itertools.combinations(range(40), 3))
    assert apps.count_triangles(df, SPEC, block_edges=10, round_entries=1).first()[0] == want


def test_bytes_that_a_triangle_count_moves(spark):
    edges = _graph(8, 2000, 60_000)
    got = apps.count_triangles(spark.createDataFrame(edges, "src bigint, dst bigint"), SPEC)
    facts = measures.run_facts(got)
    assert got.first()[0] == _count(edges, 2000)
    # each list goes to its bin, to the block that asks for it and to that of its owner
    assert facts["shuffle_bytes"] < 15 * len(edges) and facts["spill_bytes"] == 0

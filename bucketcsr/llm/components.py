"""Connected components of an edge table by alternating star contractions.

A first pass contracts the edges inside each partition with union-find, so later rounds see forests. Then
two star steps alternate: the large step hangs every larger neighbour of a node under the node's smallest
neighbour, the small step does so for its smaller neighbours; both keep the components and end, after about
log n rounds, in stars around the smallest node. Every round is an aggregate and a join whose two sides are
plain exchanges, so AQE can split the rows of a hot centre. Nothing but two counters reaches the driver.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .shared import forget, store_at

MAX_ROUNDS = 60


class Forest:
    """Union-find over integers that keeps the smallest member as root."""

    def __init__(self) -> None:
        self.parent: dict[int, int] = {}

    def root(self, x: int) -> int:
        top = x
        while (up := self.parent.get(top, top)) != top:
            top = up
        while x != top:
            self.parent[x], x = top, self.parent.get(x, top)
        return top

    def union(self, a: int, b: int) -> bool:
        """Whether the two were apart."""
        a, b = self.root(a), self.root(b)
        if a == b:
            return False
        self.parent[max(a, b)] = min(a, b)
        return True

    def pairs(self) -> Iterator[tuple[int, int]]:
        return ((x, self.root(x)) for x in list(self.parent))


def _contract(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    forest = Forest()
    for batch in batches:
        for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            forest.union(a, b)
    found = [p for p in forest.pairs() if p[0] != p[1]]
    for i in range(0, len(found), 50_000):
        part = found[i : i + 50_000]
        yield pa.RecordBatch.from_arrays([pa.array([x[k] for x in part], pa.int64()) for k in (0, 1)], names=["u", "v"])


def _star(edges: DataFrame, large: bool) -> tuple[DataFrame, str]:
    """One star step on edges (u > v)."""
    paths = edges.select("u", "v")
    if large:
        paths = paths.unionAll(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least, at = store_at(paths.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("k"), F.least("u", "m").alias("m")))
    joined = paths.join(least, paths["u"] == least["k"])
    if large:
        moved = joined.where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    else:
        moved = joined.where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionAll(least.select(F.col("k").alias("u"), F.col("m").alias("v")))
    out = store_at(moved.where("u <> v").distinct())
    forget(edges.sparkSession, at)
    return out


def _state(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(20,0)"))).first())


def connected(edges: DataFrame, contracted: bool = False) -> DataFrame:
    """edges(u, v: long) -> (node, root) for every node with an edge; root is the smallest node it reaches.

    Rows with a null end and loops are ignored; repeated and reversed edges count once; no edges: no rows.
    contracted: each partition of edges is a forest already, so the first pass is left out.
    """
    spark = edges.sparkSession
    oriented = edges.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    now, path = store_at(oriented if contracted else oriented.mapInArrow(_contract, "u long, v long"))
    before = _state(now)
    for _ in range(MAX_ROUNDS):
        if not before[0]:
            break
        wide, wide_path = _star(now, large=True)
        forget(spark, path)
        now, path = _star(wide, large=False)
        forget(spark, wide_path)
        after = _state(now)
        if after == before:
            break
        before = after
    else:
        raise RuntimeError(f"components have not settled in {MAX_ROUNDS} rounds")
    return now.select(F.col("u").alias("node"), F.col("v").alias("root")).unionAll(now.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())

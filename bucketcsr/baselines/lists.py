"""Chaining, slab lists, two-choice, coalesced and resizable tables: exact counts."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from ..functions.hashing import HashSpec, bucket_of
from ..operators.build import CsrIndex, key_parts, rows_of
from ..operators.probe import PLACE
from ..sources.storage import forget, shared_folder


def _lengths(keys: DataFrame, v: int, spec: HashSpec) -> DataFrame:
    return keys.where("key is not null").select(bucket_of([F.col("key")], v, spec).alias("bucket")).groupBy("bucket").agg(F.count("*").alias("a"))


def _long(c):
    return F.coalesce(F.sum(c), F.lit(0)).cast("bigint")


def chain_cost(keys: DataFrame, v: int, spec: HashSpec = HashSpec()) -> DataFrame:
    """One row: steps of tail inserts, steps when each key reads its whole list, words of memory."""
    a = F.col("a")
    return _lengths(keys, v, spec).agg(_long(a * (a - 1) / 2).alias("insert_steps"), _long(a * a).alias("find_all_steps"), (2 * _long(a) + F.lit(v)).cast("bigint").alias("words"))


def chain_table(index: CsrIndex) -> DataFrame:
    """(bucket, node, next_node, key, rid): each list as linked nodes in the index's order; the last node has no next."""
    ends = index.offsets.select(*PLACE, (F.col("start") + F.col("len") - 1).alias("last"))
    near = PLACE if not index.hot else ["bucket"]
    nodes = index.edges.join(ends.select(*near, "last"), near)
    return nodes.select("bucket", F.col("pos").alias("node"), F.when(F.col("pos") < F.col("last"), F.col("pos") + 1).alias("next_node"), "key", "rid")


def chain_probe_cost(index: CsrIndex, probe: DataFrame, key: str) -> DataFrame:
    """One row: probes that hit and miss, and nodes read until the first hit or the end of the list. Null keys are no probes.

    Probes are counted by key before they move, so a frequent key is one row.
    """
    rows = rows_of(probe, key, None)
    asked = rows.groupBy(bucket_of(key_parts(rows), index.layout.v, index.spec.hash).alias("bucket"), "key").agg(F.count("*").alias("n"))
    firsts = index.edges.groupBy("bucket", "key").agg(F.min("pos").alias("at"))
    lists = index.offsets.select("bucket", "start", "len")
    met = asked.join(firsts, ["bucket", "key"], "left").join(lists, "bucket", "left")
    hit = F.col("at").isNotNull()
    n = F.col("n")
    return met.agg(
        _long(F.when(hit, n)).alias("hits"),
        _long(F.when(~hit, n)).alias("misses"),
        _long(F.when(hit, n * (F.col("at") - F.col("start") + 1))).alias("hit_nodes"),
        _long(F.when(~hit, n * F.coalesce("len", F.lit(0)))).alias("miss_nodes"),
    )


def slab_cost(keys: DataFrame, v: int, slab: int = 30, spec: HashSpec = HashSpec()) -> DataFrame:
    """One row: slabs, links between slabs, slabs touched when each key reads its whole list."""
    slabs = F.ceil(F.col("a") / F.lit(slab))
    return _lengths(keys, v, spec).agg(_long(slabs).alias("slabs"), _long(slabs - 1).alias("links"), _long(F.col("a") * slabs).alias("slabs_read"))


def resizable_cost(n: int, first: int = 1024, growth: int = 2) -> dict[str, int]:
    """Rows copied while a table grows from `first` slots until n rows fit."""
    size, copied, times = first, 0, 0
    while size < n:
        copied += size
        size *= growth
        times += 1
    return {"capacity": size, "copied": copied, "rehashes": times}


def _per_bin(keys: DataFrame, slots: int, bins: int, spec: HashSpec, second: HashSpec | None = None) -> DataFrame:
    """(bin, rid, h1, h2): each bin's keys form a table of their own, in rid order."""
    per = max(1, slots // bins)
    one = bucket_of([F.col("key")], per * bins, spec)
    two = bucket_of([F.col("key")], per, second or HashSpec(seed=7))
    rows = keys.where("key is not null").select(F.floor(one / per).cast("bigint").alias("bin"), "rid", F.pmod(one, F.lit(per)).alias("h1"), two.alias("h2"))
    return rows.repartition("bin").sortWithinPartitions("bin", "rid")


def _by_bin(kernel, columns: list[str]):
    """Runs kernel(h1 list, h2 list) on each bin of sorted batches; one result row per bin."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        current, one, two, out = None, [], [], []

        def close() -> None:
            if current is not None:
                out.append((current, len(one), *kernel(one, two)))

        for batch in batches:
            for b, x, y in zip(batch.column(0).to_pylist(), batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True):
                if b != current:
                    close()
                    current, one, two = b, [], []
                one.append(x)
                two.append(y)
        close()
        yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], pa.int64()) for i in range(len(columns))], names=columns)

    return run


def _schema(columns: list[str]) -> str:
    return ", ".join(f"{c} bigint" for c in columns)


def coalesced_cost(keys: DataFrame, slots: int, bins: int = 8, spec: HashSpec = HashSpec()) -> DataFrame:
    """Per bin: keys, collisions, steps along chains on insert. A colliding key takes the highest free slot and is linked to its chain's end."""
    per = max(1, slots // bins)

    def kernel(homes: list[int], _) -> tuple[int, int]:
        size = max(per, len(homes))
        used, after = [False] * size, [-1] * size
        top, collisions, steps = size - 1, 0, 0
        for h in homes:
            if not used[h]:
                used[h] = True
                continue
            collisions += 1
            at = h
            while after[at] >= 0:
                at = after[at]
                steps += 1
            while used[top]:
                top -= 1
            used[top] = True
            after[at] = top
            steps += 1
        return collisions, steps

    columns = ["bin", "n", "collisions", "steps"]
    return _per_bin(keys, slots, bins, spec).mapInArrow(_by_bin(kernel, columns), _schema(columns))


def two_choice_cost(keys: DataFrame, slots: int, bins: int = 8, spec: HashSpec = HashSpec()) -> DataFrame:
    """Per bin: keys, longest list with two choices (the shorter of two tables' lists, ties to the first), longest with one."""
    per = max(1, slots // bins)

    def kernel(first: list[int], second: list[int]) -> tuple[int, int]:
        left, right, single = [0] * per, [0] * per, [0] * per
        for a, b in zip(first, second, strict=True):
            single[a] += 1
            if left[a] <= right[b]:
                left[a] += 1
            else:
                right[b] += 1
        return max(max(left), max(right)), max(single)

    columns = ["bin", "n", "longest_two", "longest_one"]
    return _per_bin(keys, slots, bins, spec).mapInArrow(_by_bin(kernel, columns), _schema(columns))


def two_choice_rounds(keys: DataFrame, slots: int, rounds: int = 4, spec: HashSpec = HashSpec(), second: HashSpec = HashSpec(seed=7)) -> DataFrame:
    """(round, tab, bucket, key, n) of one whole table pair of slots / 2 lists each: rows come in rounds by rid, and a key's rows of a
    round go to the list that was shorter when the round began, ties to table 0.

    A round moves one row per key. Null keys are left out; fewer rows than rounds leave rounds empty.
    """
    half = max(1, slots // 2)
    rows = keys.where("key is not null").select("key", F.pmod("rid", F.lit(rounds)).cast("int").alias("round"))
    counted = rows.groupBy("round", "key").agg(F.count("*").alias("n"))
    counted = counted.select("round", "key", "n", bucket_of([F.col("key")], half, spec).alias("h0"), bucket_of([F.col("key")], half, second).alias("h1"))
    spark = keys.sparkSession
    folder = shared_folder(spark, "two_choice")
    counted.write.partitionBy("round").parquet(f"{folder}/keys")
    counted = spark.read.schema(counted.schema).parquet(f"{folder}/keys")
    lists = spark.createDataFrame([], "tab int, bucket bigint, size bigint")
    for i in range(rounds):
        side = lambda t: lists.where(F.col("tab") == t).select(F.col("bucket").alias(f"h{t}"), F.col("size").alias(f"s{t}"))  # noqa: B023, E731
        met = counted.where(F.col("round") == i).join(side(0), "h0", "left").join(side(1), "h1", "left")
        first = F.coalesce("s0", F.lit(0)) <= F.coalesce("s1", F.lit(0))
        placed = met.select("round", F.when(first, 0).otherwise(1).alias("tab"), F.when(first, F.col("h0")).otherwise(F.col("h1")).alias("bucket"), "key", "n")
        placed.write.parquet(f"{folder}/placed/{i}")
        fresh = spark.read.parquet(f"{folder}/placed/{i}").select("tab", "bucket", F.col("n").alias("size"))
        lists.unionByName(fresh).groupBy("tab", "bucket").agg(F.sum("size").alias("size")).write.parquet(f"{folder}/lists/{i}")
        lists = spark.read.parquet(f"{folder}/lists/{i}")
    forget(spark, f"{folder}/keys")
    forget(spark, f"{folder}/lists")
    return spark.read.parquet(*[f"{folder}/placed/{i}" for i in range(rounds)])

"""Cost measures over indexes: bucket statistics, sizes, balance, expected values, rates and plan facts."""

from __future__ import annotations

import re
import time
from collections.abc import Callable, Sequence
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, functions as F

from .functions.hashing import HashSpec, bucket_of
from .operators import build
from .plans.params import BuildSpec, bucket_count, capacity, resolve, storage_elements, work_terms


def _long(c):
    return F.coalesce(F.sum(c), F.lit(0)).cast("bigint")


def uniform_keys(df: DataFrame, id_col: str, appearances: float, seed: int = 7) -> DataFrame:
    """key: uniform over a range that makes each key appear so often on average."""
    span = max(1, int(df.count() / appearances))
    return df.select(bucket_of([F.col(id_col).cast("bigint")], span, HashSpec(seed=seed)).alias("key"))


def exact_keys(df: DataFrame, id_col: str, appearances: int) -> DataFrame:
    """key: every key exactly so often, for ids from 0."""
    return df.select(F.floor(F.col(id_col) / appearances).cast("bigint").alias("key"))


def bucket_stats(offsets: DataFrame, v: int) -> DataFrame:
    """One row: v, nonempty, max_len, sum_sq, collisions."""
    a = F.col("len")
    return offsets.agg(F.lit(v).cast("bigint").alias("v"), F.count("*").alias("nonempty"), F.max("len").alias("max_len"), _long(a * a).alias("sum_sq"), _long(a * (a - 1) / 2).alias("collisions"))


def stats_by_load(sources: Sequence[tuple[str, DataFrame]], loads: Sequence[float]) -> DataFrame:
    """bucket_stats of each (name, keys) at each load."""
    out = []
    for name, keys in sources:
        n = keys.where("key is not null").count()
        for load in loads:
            v = bucket_count(n, load)
            lengths = keys.where("key is not null").groupBy(bucket_of([F.col("key").cast("bigint")], v).alias("bucket")).agg(F.count("*").alias("len"))
            stats = bucket_stats(lengths, v)
            out.append(stats.select(F.lit(name).alias("name"), F.lit(float(load)).alias("load"), *stats.columns))
    return reduce(DataFrame.unionAll, out)


def histogram(offsets: DataFrame) -> DataFrame:
    """(len, buckets, collisions)."""
    return offsets.groupBy("len").agg(F.count("*").alias("buckets"), _long(F.col("len") * (F.col("len") - 1) / 2).alias("collisions"))


def bin_balance(df: DataFrame, key: str, grid: Sequence[int]) -> DataFrame:
    """Per bin count: bins used, rows of the largest, mean rows."""
    rows = build.rows_of(df, key, None)
    n, out = rows.count(), []
    for bins in grid:
        layout = resolve(n, BuildSpec(bins=bins))
        counts = build.bucketed(rows, layout, BuildSpec()).groupBy("bin").agg(F.count("*").alias("n"))
        out.append(counts.agg(F.lit(bins).cast("bigint").alias("bins"), F.count("*").alias("used"), F.max("n").alias("largest"), F.round(F.avg("n"), 6).alias("mean")))
    return reduce(DataFrame.unionAll, out)


def storage(spark: SparkSession, n: int, loads: Sequence[float], bins: int, memory: int = 32 << 30) -> DataFrame:
    rows = []
    for load in loads:
        v = bucket_count(n, load)
        e = storage_elements(n, v, bins, binned=True)
        rows.append((float(load), n, v, e["table"], e["buckets"], e["bins"], e["reorganised"], capacity(memory, load, binned=True)))
    return spark.createDataFrame(rows, "load double, n bigint, v bigint, table_elements bigint, bucket_elements bigint, bin_elements bigint, reorganised bigint, capacity bigint")


def work(spark: SparkSession, n: int, loads: Sequence[float], bins: int, cores: int = 8) -> DataFrame:
    rows = []
    for load in loads:
        v = bucket_count(n, load)
        one, two = (work_terms(n, v, bins, cores, b) for b in (False, True))
        rows.append((float(load), *(int(t[k]) for k in ("hashes", "sweeps", "prefix", "work") for t in (one, two))))
    return spark.createDataFrame(rows, "load double, hashes_single bigint, hashes_binned bigint, sweeps_single bigint, sweeps_binned bigint, prefix_single bigint, prefix_binned bigint, work_single bigint, work_binned bigint")


def expected(keys: DataFrame, loads: Sequence[float]) -> DataFrame:
    """Empty share and sum of squared lengths beside what unique keys under a random hash would give."""
    n = keys.where("key is not null").count()
    stats = stats_by_load([("keys", keys)], loads)
    pairs = F.lit(float(n * (n - 1)))  # in Python's integers: past 46,341 rows the product leaves Spark's INT
    return stats.select("load", F.round(1 - F.col("nonempty") / F.col("v"), 6).alias("empty"), F.round(F.exp(-F.col("load")), 6).alias("expected"), "sum_sq", F.round(F.lit(float(n)) + pairs / F.col("v"), 3).alias("expected_sum_sq"))


def self_join_sizes(sources: Sequence[tuple[str, DataFrame]]) -> DataFrame:
    """Result pairs of a self-join on each key, and their number over the input rows of both sides."""
    out = []
    for name, keys in sources:
        n = F.col("n")
        counts = keys.where("key is not null").groupBy("key").agg(F.count("*").alias("n"))
        out.append(counts.agg(F.lit(name).alias("name"), F.sum("n").alias("n_rows"), _long(n * n).alias("pairs"), F.round(F.sum(n * n) / (2 * F.sum("n")), 6).alias("blow_up")))
    return reduce(DataFrame.unionAll, out)


def timed(make: Callable[[], DataFrame], runs: int = 3) -> float:
    """Median seconds to run a query to the end without keeping its rows, after one warm-up."""
    took = []
    for i in range(runs + 1):
        began = time.perf_counter()
        make().write.format("noop").mode("overwrite").save()
        if i:
            took.append(time.perf_counter() - began)
    return sorted(took)[len(took) // 2]


def rate(rows: int, seconds: float) -> float:
    """Keys per second."""
    return rows / seconds if seconds else float("inf")


def speedup(seconds: float, base_seconds: float) -> float:
    return base_seconds / seconds


def degradation(rate_r: float, rate_1: float) -> float:
    """Share of the rate that is lost against keys appearing once."""
    return 1 - rate_r / rate_1


def plan_facts(df: DataFrame) -> dict[str, int]:
    """Operators of the physical plan that decide about scale."""
    text = df._jdf.queryExecution().executedPlan().toString()
    count = lambda p: len(re.findall(p, text))
    return {"exchanges": count(r"Exchange (?:hashpartitioning|rangepartitioning|RoundRobin|ShufflePartitionIdPassThrough|shufflepartitionid)"), "hash_exchanges": count(r"Exchange hashpartitioning"), "single": count(r"Exchange SinglePartition"), "broadcasts": count(r"BroadcastExchange"), "python": count(r"Python|Pandas|Arrow")}


def run_facts(df: DataFrame) -> dict[str, int]:
    """Runs a query to its end, keeps no row, and adds up what its plan measured: bytes exchanged, bytes spilled, exchanges."""
    done = df._jdf.queryExecution()
    done.toRdd().count()
    total = {"shuffle_bytes": 0, "spill_bytes": 0, "exchanges": 0}
    todo, seen = [done.executedPlan()], set()
    while todo:
        node = todo.pop()
        kind = node.getClass().getSimpleName()
        if kind == "AdaptiveSparkPlanExec":
            todo.append(node.executedPlan())
            continue
        if kind.endswith("QueryStageExec"):
            todo.append(node.plan())
            continue
        if kind == "ReusedExchangeExec" or node.id() in seen:
            continue
        seen.add(node.id())
        metrics = node.metrics()
        read = lambda name: metrics.get(name).get().value() if metrics.contains(name) else 0  # noqa: B023, E731
        total["shuffle_bytes"] += read("shuffleBytesWritten")
        total["spill_bytes"] += read("spillSize")
        total["exchanges"] += kind == "ShuffleExchangeExec"
        children = node.children()
        todo += [children.apply(i) for i in range(children.size())]
    return total


def sketched_distinct(df: DataFrame, key: str, error: float = 0.02) -> DataFrame:
    """One row: n (keys that are not null), distinct_estimate, appearances; by a HyperLogLog sketch, one small state per task."""
    keys = df.where(F.col(key).isNotNull())
    return keys.agg(F.count("*").alias("n"), F.approx_count_distinct(key, error).alias("distinct_estimate")).withColumn("appearances", F.col("n") / F.greatest("distinct_estimate", F.lit(1)))


def hot_keys(df: DataFrame, key: str, share: float = 0.1) -> DataFrame:
    """(key, n) of every key that holds at least `share` of the rows that have one; exact counts.

    A frequent-items sketch of bounded size names all that can be so frequent (its error is far below the share), and only those are counted.
    """
    if not 0.001 <= share <= 1:
        raise ValueError("share must lie between 0.001 and 1")
    keys = df.where(F.col(key).isNotNull()).select(F.col(key).alias("key"))
    most = int(2 / share) + 1
    named = keys.agg(F.expr(f"approx_top_k(key, {most}, {max(64, 32 * most)})").alias("top")).select(F.explode("top").alias("t")).select(F.col("t.item").alias("key"))
    total = keys.agg(F.count("*").alias("total"))
    counted = keys.join(F.broadcast(named), "key", "left_semi").groupBy("key").agg(F.count("*").alias("n"))
    return counted.join(F.broadcast(total)).where(F.col("n") >= F.lit(share) * F.col("total")).select("key", "n")

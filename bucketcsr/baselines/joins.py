"""Baseline joins: unique-only, sorted, native and vectorised."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from ..operators.pieces import met_in_pieces


class DuplicateKeyError(ValueError):
    """A table for unique keys got a key twice."""


def unique_table(df: DataFrame, key: str) -> DataFrame:
    """df, once it is known that no key repeats; the error lists up to ten that do."""
    twice = df.where(F.col(key).isNotNull()).groupBy(key).count().where("count > 1").limit(10).collect()
    if twice:
        raise DuplicateKeyError(f"repeated keys: {[r[key] for r in twice]}")
    return df


def unique_lookup(table: DataFrame, probe: DataFrame, key: str, probe_key: str, rid: str, probe_rid: str) -> DataFrame:
    """(key, l_rid, r_rid): at most one match per probe row."""
    built = unique_table(table, key).select(F.col(key).alias("key"), F.col(rid).alias("r_rid"))
    return probe.select(F.col(probe_key).alias("key"), F.col(probe_rid).alias("l_rid")).join(built, "key")


def multi_split(df: DataFrame, key: str, parts: int) -> DataFrame:
    """(class, n, start): the histogram and prefix by which rows are scattered to classes."""
    from ..operators.prefix import exclusive_prefix

    counts = df.where(F.col(key).isNotNull()).groupBy(F.pmod(F.hash(F.col(key).cast("bigint")), F.lit(parts)).cast("bigint").alias("class")).agg(F.count("*").alias("n"))
    return exclusive_prefix(counts.withColumn("_one", F.lit(0)), "_one", "class", "n").drop("_one")


def sort_merge_join(a: DataFrame, b: DataFrame, on: str) -> DataFrame:
    return a.hint("merge").join(b, on)


def multicore_join(a: DataFrame, b: DataFrame, on: str) -> DataFrame:
    """Partitioned hash join: both sides move, each partition builds one table."""
    return a.hint("shuffle_hash").join(b, on)


def distributed_join(a: DataFrame, b: DataFrame, on: str, partitions: int) -> DataFrame:
    return a.repartition(partitions, on).join(b.repartition(partitions, on).hint("shuffle_hash"), on)


def broadcast_join(a: DataFrame, b: DataFrame, on: str, most_rows: int = 1_000_000) -> DataFrame:
    """b is sent to every executor, after a count shows that it is small; else in pieces of about most_rows rows, one after another.

    A key stays in one piece, so a key of far more rows than most_rows makes a piece that is as large.
    """
    meet = lambda x, y: x.join(F.broadcast(y), on)
    pieces = -(-b.count() // most_rows)
    if pieces <= 1:
        return meet(a, b)
    piece = F.pmod(F.xxhash64(F.col(on)), F.lit(pieces))
    return met_in_pieces(a, b, pieces, piece, piece, meet)


#: Rows of both sides that one vectorised task holds, about.
PIECE_ROWS = 2_000_000


def _cogroup(schema: str, a: DataFrame, b: DataFrame, key: str, pieces: int | None, kernel) -> DataFrame:
    """Runs the kernel on pieces of the key space, as many as the rows need; a key of over PIECE_ROWS rows has to be taken out before."""
    pieces = pieces or max(1, -(-(a.count() + b.count()) // PIECE_ROWS))
    piece = F.pmod(F.hash(F.col(key)), F.lit(pieces))
    left, right = (df.withColumn("_p", piece).groupBy("_p") for df in (a, b))
    return left.cogroup(right).applyInArrow(kernel, schema)


def nested_loop_join(a: DataFrame, b: DataFrame, on: str, most_rows: int = 10_000) -> DataFrame:
    """Every row of a against every row of b, a control for small tables: b is replicated, after a count shows that it is small."""
    if b.count() > most_rows:
        raise ValueError(f"the side to replicate has over {most_rows} rows")
    right = b.withColumnRenamed(on, "_on").hint("shuffle_replicate_nl")
    return a.join(right, F.col(on) == F.col("_on")).drop("_on")


def partition_tables(a: DataFrame, b: DataFrame, pieces: int | None = None) -> DataFrame:
    """(key, l_rid, r_rid): pieces of the key space small enough for a task's own fast memory, each with an open-addressing table of b's rows in
    NumPy; a's keys walk it from their home slot to the first empty one."""

    def kernel(left: pa.Table, right: pa.Table) -> pa.Table:
        keys, rids = right["key"].to_numpy(), right["r_rid"].to_numpy()
        slots = max(2, 2 * len(keys))
        home = lambda x: (x.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(17)).astype(np.int64) % slots
        at = np.full(slots, -1, np.int64)
        todo, spot = np.arange(len(keys)), home(keys)
        while len(todo):
            free = at[spot[todo]] < 0
            at[spot[todo[free]][::-1]] = todo[free][::-1]  # of several newcomers the first stays
            todo = todo[at[spot[todo]] != todo]
            spot[todo] = (spot[todo] + 1) % slots
        want, mine = left["key"].to_numpy(), left["l_rid"].to_numpy()
        todo, spot, out = np.arange(len(want)), home(want), []
        while len(todo):
            here = at[spot[todo]]
            todo, here = todo[here >= 0], here[here >= 0]
            hit = keys[here] == want[todo]
            out.append((todo[hit], here[hit]))
            spot[todo] = (spot[todo] + 1) % slots
        l, r = (np.concatenate([o[k] for o in out] or [np.zeros(0, np.int64)]) for k in (0, 1))
        return pa.table({"key": want[l], "l_rid": mine[l], "r_rid": rids[r]})

    return _cogroup("key bigint, l_rid bigint, r_rid bigint", a, b, "key", pieces, kernel)


def arrow_hash_join(a: DataFrame, b: DataFrame, pieces: int | None = None) -> DataFrame:
    """(key, l_rid, r_rid) of a(key, l_rid) and b(key, r_rid): vectorised joins of key pieces."""

    def kernel(left: pa.Table, right: pa.Table) -> pa.Table:
        return left.drop_columns(["_p"]).join(right.drop_columns(["_p"]), "key", join_type="inner").select(["key", "l_rid", "r_rid"])

    return _cogroup("key bigint, l_rid bigint, r_rid bigint", a, b, "key", pieces, kernel)


def sorted_lookup(a: DataFrame, b: DataFrame, pieces: int | None = None) -> DataFrame:
    """(key, l_rid, r_rid): b's keys are sorted, each key of a finds its run by two binary searches."""

    def kernel(left: pa.Table, right: pa.Table) -> pa.Table:
        keys, rids = right["key"].to_numpy(), right["r_rid"].to_numpy()
        order = np.lexsort((rids, keys))
        keys, rids = keys[order], rids[order]
        want = left["key"].to_numpy()
        lo, hi = np.searchsorted(keys, want, "left"), np.searchsorted(keys, want, "right")
        n = hi - lo
        at = np.repeat(lo - np.concatenate(([0], np.cumsum(n)[:-1])), n) + np.arange(n.sum()) if len(n) else np.zeros(0, np.int64)
        return pa.table({"key": np.repeat(want, n), "l_rid": np.repeat(left["l_rid"].to_numpy(), n), "r_rid": rids[at]})

    return _cogroup("key bigint, l_rid bigint, r_rid bigint", a, b, "key", pieces, kernel)


def search_steps(n: int) -> int:
    """Comparisons of one binary search over n sorted keys."""
    return int(np.ceil(np.log2(n + 1))) if n else 0

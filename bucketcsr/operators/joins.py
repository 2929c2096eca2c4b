"""Joins, key-set operations and grouping over bucket indexes."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, functions as F

from ..plans.params import BuildSpec
from .build import CsrIndex, build_binned
from .probe import PLACE, build_pair, meet, tiles

HOW = ("inner", "left", "right", "full", "left_semi", "left_anti")


def bucket_join(a: DataFrame, b: DataFrame, key_a: str | Sequence[str], key_b: str | Sequence[str], rid_a: str, rid_b: str, how: str = "inner", spec: BuildSpec = BuildSpec()) -> DataFrame:
    """(key, l_rid, r_rid); semi and anti joins: (key, l_rid). Null keys match nothing; rows that an outer join keeps stay."""
    if how not in HOW:
        raise ValueError(f"join {how!r} is none of {HOW}")
    ia, ib = build_pair(a, b, key_a, key_b, rid_a, rid_b, spec)
    out = meet(ia, ib, how)
    if how in ("left_semi", "left_anti"):
        return out.unionAll(_null_keys(a, key_a, rid_a, out)) if how == "left_anti" else out
    if how in ("left", "full"):
        out = out.unionByName(_null_keys(a, key_a, rid_a, out.select("key", "l_rid")).withColumn("r_rid", F.lit(None).cast("bigint")))
    if how in ("right", "full"):
        other = _null_keys(b, key_b, rid_b, out.select("key", "r_rid"))
        out = out.unionByName(other.withColumn("l_rid", F.lit(None).cast("bigint")))
    return out


def null_safe_join(a: DataFrame, b: DataFrame, key_a: str, key_b: str, rid_a: str, rid_b: str, spec: BuildSpec = BuildSpec()) -> DataFrame:
    """(key, l_rid, r_rid) where null meets null as well. Rows without a key form one list on each side: their numbers are told first, and each side's list is
    cut into chunks that meet in tasks of their own."""
    met = bucket_join(a, b, key_a, key_b, rid_a, rid_b, "inner", spec)
    nulls = lambda df, key, rid, name: df.where(F.col(key).isNull()).select(F.lit(0).cast("bigint").alias("bucket"), F.lit(0).alias("key"), F.col(rid).cast("bigint").alias(name))
    pairs = tiles(nulls(a, key_a, rid_a, "l_rid"), nulls(b, key_b, rid_b, "r_rid"), spec.hot_limit())
    return met.unionByName(pairs.select(F.lit(None).cast(met.schema["key"].dataType).alias("key"), "l_rid", "r_rid"))


def _null_keys(df: DataFrame, key: str | Sequence[str], rid: str, like: DataFrame) -> DataFrame:
    keys = [key] if isinstance(key, str) else list(key)
    rows = df.where(" OR ".join(f"`{k}` IS NULL" for k in keys))
    kind = like.schema["key"].dataType
    return rows.select(F.lit(None).cast(kind).alias("key"), F.col(f"`{rid}`").cast("bigint").alias(like.columns[1]))


def key_set(a: DataFrame, b: DataFrame, key_a: str, key_b: str, kind: str, spec: BuildSpec = BuildSpec()) -> DataFrame:
    """Distinct keys of both sides (intersect), of either (union), or of a alone (except)."""
    ia, ib = build_pair(a, b, key_a, key_b, spec=spec)
    left, right = (ix.edges.select(*PLACE, "key").distinct() for ix in (ia, ib))
    on = [*PLACE, "key"]
    if kind == "intersect":
        return left.join(right, on, "left_semi").select("key")
    if kind == "except":
        return left.join(right, on, "left_anti").select("key")
    if kind == "union":
        return left.unionAll(right).groupBy(*on).agg(F.lit(1)).select("key")
    raise ValueError(f"unknown set operation {kind!r}")


def bucket_group_by(df: DataFrame, key: str | Sequence[str], aggregates: Sequence[Column], payload: Sequence[str] = (), spec: BuildSpec = BuildSpec(), index: CsrIndex | None = None) -> DataFrame:
    """Aggregates by key inside the buckets: rows of a key are together already."""
    index = index or build_binned(df, key, None, spec, payload)
    return index.edges.groupBy(*PLACE, "key").agg(*aggregates).drop(*PLACE)


def range_join(points: DataFrame, intervals: DataFrame, point: str, low: str, high: str, width: int) -> DataFrame:
    """Rows with low <= point < high: both sides meet in bands of `width`, an interval in every band that it touches."""
    band = lambda c: F.floor(F.col(c) / F.lit(width)).cast("bigint")
    left = points.withColumn("_band", band(point))
    right = intervals.where(F.col(low) < F.col(high)).withColumn("_band", F.explode(F.sequence(band(low), F.floor((F.col(high) - 1) / F.lit(width)).cast("bigint"))))
    return left.join(right, "_band").where((F.col(point) >= F.col(low)) & (F.col(point) < F.col(high))).drop("_band")


def asof_join(left: DataFrame, right: DataFrame, by: str, at: str, value: str, name: str = "last_value") -> DataFrame:
    """left + the right side's last value by `by` at or before `at`; one sort per key, no pairs."""
    from pyspark.sql import Window

    marked = left.withColumn("_side", F.lit(1)).withColumn("_v", F.lit(None).cast(right.schema[value].dataType))
    extra = [c for c in left.columns if c not in (by, at)]
    events = right.select(F.col(by), F.col(at), *[F.lit(None).cast(left.schema[c].dataType).alias(c) for c in extra], F.lit(0).alias("_side"), F.col(value).alias("_v"))
    w = Window.partitionBy(by).orderBy(at, "_side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    both = marked.select(by, at, *extra, "_side", "_v").unionAll(events.select(by, at, *extra, "_side", "_v"))
    return both.withColumn(name, F.last("_v", ignorenulls=True).over(w)).where("_side = 1").drop("_side", "_v")

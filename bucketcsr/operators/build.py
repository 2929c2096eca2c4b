"""Building a bucket index: rows of each hash bucket side by side, with exact, pre-counted room.

Single sweep: count rows per bucket, prefix the counts, place each row. Binned: rows first move to bins, ranges of
neighbouring buckets; whole bins go to one partition each by a pass-through exchange, and one sort inside it gives
ranks, positions and offsets. That exchange is the only one over the rows.

A bucket of over `hot_bucket_rows` rows would be sorted by one task. Such buckets are found from the bin counts (only rows of bins over the
limit are counted by bucket), their rows are ranked in pieces of about that many rows, and every other row of the bin is moved on
by their number. The order inside a hot bucket is then by piece, not by key.
"""

from __future__ import annotations

from bisect import bisect_right
from collections.abc import Sequence
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, Window, functions as F

from ..functions.hashing import bucket_of, normal_key
from ..plans.params import MOST_PARTS, BuildSpec, Layout, resolve
from .prefix import MOST_GROUPS, exclusive_prefix, starts

#: Bins that the driver lists; the counts of more stay in a table that is joined.
MOST_LISTED = 100_000

#: Hot buckets that the driver may hold and send to every executor.
MOST_HOT = 100_000


@dataclass(frozen=True)
class CsrIndex:
    """edges(part, bin, bucket, pos, key, rid, payload...), offsets(part, bin, bucket, start, len), bins(bin, part, n, bin_start).

    hot: rows of each bucket that is kept in pieces; its edges carry the part after the last one.
    """

    edges: DataFrame
    offsets: DataFrame
    bins: DataFrame
    layout: Layout
    spec: BuildSpec
    hot: tuple[tuple[int, int], ...] = ()
    lists: DataFrame | None = None  # (bucket, key, n), where it is stored

    def persist(self) -> CsrIndex:
        return replace(self, edges=self.edges.persist(), offsets=self.offsets.persist())

    def dense_offsets(self) -> DataFrame:
        """Offsets with a row for empty buckets too."""
        v = self.layout.v
        every = self.edges.sparkSession.range(v).select(F.col("id").alias("bucket"), F.floor(F.col("id") / F.lit(self.layout.width)).cast("bigint").alias("bin"))
        filled = every.join(self.offsets.select("bucket", "len"), "bucket", "left").withColumn("len", F.coalesce("len", F.lit(0)))
        return exclusive_prefix(filled, "bin", "bucket", "len").select("bucket", "start", "len")

    def offset_array(self) -> DataFrame:
        """(i, start) for i in 0 .. V: bucket i's rows are start(i) .. start(i + 1) - 1."""
        end = self.edges.sparkSession.createDataFrame([(self.layout.v, self.layout.n)], "i bigint, start bigint")
        return self.dense_offsets().select(F.col("bucket").alias("i"), "start").unionAll(end)

    def get_many(self, keys: Sequence) -> DataFrame:
        """Edges of some keys; bins of other keys are pruned where the edges are stored by bin."""
        spark = self.edges.sparkSession
        kind = self.edges.schema["key"].dataType.simpleString()
        wanted = spark.createDataFrame([(k,) for k in keys], f"key {kind}").select("key", bucket_of([F.col("key")], self.layout.v, self.spec.hash).alias("bucket"))
        bins = sorted({r["bucket"] // self.layout.width for r in wanted.select("bucket").collect()})
        return self.edges.where(F.col("bin").isin(bins)).join(F.broadcast(wanted), ["bucket", "key"], "left_semi")

    def get(self, key) -> DataFrame:
        return self.get_many([key])

    def views(self, name: str) -> None:
        for part in ("edges", "offsets", "bins"):
            getattr(self, part).createOrReplaceTempView(f"{name}_{part}")


def rows_of(df: DataFrame, key: str | Sequence[str], rid: str | None, payload: Sequence[str] = ()) -> DataFrame:
    """(key, rid, payload...) without null keys; several key columns become one struct."""
    keys = [key] if isinstance(key, str) else list(key)
    cols = [normal_key(df, k) for k in keys]
    one = cols[0] if len(cols) == 1 else F.struct(*[c.alias(k) for c, k in zip(cols, keys, strict=True)])
    kept = df.where(" AND ".join(f"`{k}` IS NOT NULL" for k in keys))
    more = [F.col(f"`{rid}`").cast("bigint").alias("rid")] if rid else []
    return kept.select(one.alias("key"), *more, *payload)


def key_parts(df: DataFrame) -> list[Column]:
    """Columns to hash for the key: the fields of a struct key in order, else the key."""
    kind = df.schema["key"].dataType
    return [F.col(f"key.{f}") for f in kind.names] if hasattr(kind, "names") else [F.col("key")]


def bucketed(rows: DataFrame, layout: Layout, spec: BuildSpec) -> DataFrame:
    bucket = bucket_of(key_parts(rows), layout.v, spec.hash)
    return rows.withColumn("bucket", bucket).withColumn("bin", F.floor(F.col("bucket") / F.lit(layout.width)).cast("bigint"))


def bucket_counts(rows: DataFrame) -> DataFrame:
    return rows.groupBy("bucket").agg(F.count("*").alias("n"))


def count_bins(rows: DataFrame) -> dict[int, int]:
    """Rows per bin; one number per non-empty bin reaches the driver, and no more than MOST_GROUPS of them."""
    found = rows.groupBy("bin").agg(F.count("*").alias("n")).limit(MOST_GROUPS + 1).collect()
    if len(found) > MOST_GROUPS:
        raise ValueError(f"over {MOST_GROUPS} bins; take fewer")
    return {r["bin"]: r["n"] for r in found}


def hot_buckets(rows: DataFrame, counts: dict[int, int], limit: int, everywhere: bool = False) -> dict[int, int]:
    """Rows of each bucket with over `limit` of them; only bins over the limit are looked into (everywhere: all, if any count is over it)."""
    wide = [b for b, n in counts.items() if n > limit]
    if not wide:
        return {}
    inside = rows.where(F.col("bin").isin(wide)) if len(wide) <= 1000 and not everywhere else rows
    found = inside.groupBy("bucket").agg(F.count("*").alias("n")).where(F.col("n") > limit).limit(MOST_HOT + 1).collect()
    if len(found) > MOST_HOT:
        raise ValueError(f"over {MOST_HOT} hot buckets; raise hot_bucket_rows")
    return {r["bucket"]: r["n"] for r in found}


def bins_table(spark, counts: dict[int, int], layout: Layout, weights: dict[int, int] | None = None, parts: dict[int, int] | None = None) -> DataFrame:
    """(bin, part, n, bin_start); parts are runs of bins of about equal weight (default: the counts), or those of another index's bins."""
    begin = starts(counts.items())
    if parts:
        known = sorted(parts)
        part = lambda b: parts[known[max(0, bisect_right(known, b) - 1)]]
        return spark.createDataFrame([(b, part(b), n, begin[b]) for b, n in sorted(counts.items())], "bin bigint, part int, n bigint, bin_start bigint")
    weights = weights or counts
    total, seen, part_of = max(1, sum(weights.values())), 0, {}
    for b in sorted(weights):
        part_of[b] = min(layout.parts - 1, seen * layout.parts // total)
        seen += weights[b]
    rows = [(b, part_of[b], n, begin[b]) for b, n in sorted(counts.items())]
    return spark.createDataFrame(rows, "bin bigint, part int, n bigint, bin_start bigint")


def wide_bins(rows: DataFrame, layout: Layout, total: int) -> DataFrame:
    """bins_table() of more bins than the driver should list: only totals of a thousand runs of neighbouring bins reach it."""
    run = F.floor(F.col("bin") / F.lit(-(-layout.bins // 1000))).cast("bigint")
    counts = rows.groupBy("bin").agg(F.count("*").alias("n")).withColumn("_run", run)
    part = F.least(F.lit(layout.parts - 1), F.expr(f"bin_start * {layout.parts}L div {max(1, total)}L")).cast("int")
    return exclusive_prefix(counts, "_run", "bin", "n", "bin_start").select("bin", part.alias("part"), "n", "bin_start")


def reorganise(rows: DataFrame, bins: DataFrame, parts: int, listed: bool = True) -> DataFrame:
    """Rows moved to their bin's partition: the one exchange of the binned build. Bins that are not listed meet the rows by an exchange of their own."""
    side = bins.select("bin", "part", "bin_start")
    sided = rows.join(F.broadcast(side) if listed else side, "bin")
    return sided.repartitionById(parts, F.col("part"))


def finish_bins(dealt: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Edges and offsets inside each bin; `part` leads all keys, so nothing moves again."""
    order = [c for c in ("bucket", "key", "rid") if c in dealt.columns]
    rank = F.row_number().over(Window.partitionBy("part", "bin").orderBy(*order))
    edges = dealt.withColumn("pos", F.col("bin_start") + rank - 1).drop("bin_start")
    lead = ["part", "bin", "bucket", "pos", "key"]
    edges = edges.select(*lead, *[c for c in edges.columns if c not in lead])
    offsets = edges.groupBy("part", "bin", "bucket").agg(F.min("pos").alias("start"), F.count("*").alias("len"))
    return edges, offsets


def split_hot(rows: DataFrame, hot: Sequence[int]) -> tuple[DataFrame, DataFrame]:
    """Rows outside and inside the hot buckets, a checked number that goes to every executor."""
    if not hot:
        return rows, rows.where("false")
    side = F.broadcast(rows.sparkSession.createDataFrame([(b,) for b in hot], "bucket bigint"))
    return rows.join(side, "bucket", "left_anti").select(*rows.columns), rows.join(side, "bucket", "left_semi").select(*rows.columns)


def place(rows: DataFrame, counts: dict[int, int] | DataFrame, layout: Layout, spec: BuildSpec, hot: dict[int, int], weights: dict[int, int] | None = None, size: int | None = None, parts: dict[int, int] | None = None) -> CsrIndex:
    """An index of bucketed rows whose bins are counted (or stand in a table, see wide_bins); weights size the parts (or parts tells them), hot buckets are kept in pieces."""
    spark = rows.sparkSession
    listed = isinstance(counts, dict)
    bins = bins_table(spark, counts, layout, weights, parts) if listed else counts
    sized = replace(layout, n=layout.n if size is None else size)
    if not hot:
        edges, offsets = finish_bins(reorganise(rows, bins, layout.parts, listed))
        return CsrIndex(edges, offsets, bins, sized, spec)
    cold, warm = split_hot(rows, list(hot))
    own = {r["bucket"]: r["n"] for r in warm.groupBy("bucket").agg(F.count("*").alias("n")).collect()}  # at most MOST_HOT
    by_bin: dict[int, list[tuple[int, int]]] = {}
    for b, n in sorted(own.items()):
        by_bin.setdefault(b // layout.width, []).append((b, n))
    jumps = F.broadcast(spark.createDataFrame(list(by_bin.items()), "bin bigint, jumps array<struct<b: bigint, n: bigint>>"))
    marked = cold.join(jumps, "bin", "left")
    edges, _ = finish_bins(reorganise(marked, bins, layout.parts, listed))
    # rows of hot buckets in front of this one
    jump = F.aggregate(F.filter("jumps", lambda h: h["b"] < F.col("bucket")), F.lit(0).cast("bigint"), lambda total, h: total + h["n"])
    edges = edges.withColumn("pos", F.col("pos") + F.coalesce(jump, F.lit(0))).drop("jumps")
    offsets = edges.groupBy("part", "bin", "bucket").agg(F.min("pos").alias("start"), F.count("*").alias("len"))
    spots = F.broadcast(spark.createDataFrame([(b // layout.width, b) for b in own], "bin bigint, hot bigint"))
    before = {r["hot"]: r["n"] for r in cold.join(spots, "bin").where("bucket < hot").groupBy("hot").agg(F.count("*").alias("n")).collect()}
    begin = starts(counts.items()) if listed else {r["bin"]: r["bin_start"] for r in bins.join(jumps, "bin", "left_semi").collect()}  # bins of hot buckets
    first = {}
    for k, inside in by_bin.items():
        at = begin[k]
        for b, n in inside:
            first[b] = at + before.get(b, 0)
            at += n
    heads = spark.createDataFrame([(b, first[b], n) for b, n in own.items()] or [(-1, 0, 0)], "bucket bigint, start bigint, len bigint")
    ranked = hot_chunks(warm, spec.hot_limit(), own).join(F.broadcast(heads.select("bucket", "start")), "bucket")
    spread = ranked.withColumn("pos", F.col("start") + F.col("rank")).withColumn("part", F.lit(layout.parts)).select(*edges.columns)
    more = heads.where("bucket >= 0").select(F.lit(layout.parts).alias("part"), F.floor(F.col("bucket") / F.lit(layout.width)).cast("bigint").alias("bin"), "bucket", "start", "len")
    return CsrIndex(edges.unionByName(spread), offsets.unionByName(more), bins, sized, spec, tuple(sorted(hot.items())))


def build_binned(df: DataFrame, key: str | Sequence[str], rid: str | None = None, spec: BuildSpec = BuildSpec(), payload: Sequence[str] = (), layout: Layout | None = None) -> CsrIndex:
    """Groups rows into bins first; rows of a bin are placed inside one partition."""
    rows = rows_of(df, key, None if spec.payload == "key" else rid, () if spec.payload == "key" else payload)
    layout = layout or resolve(rows.count(), spec)
    rows = bucketed(rows, layout, spec)
    return place_counted(rows, layout, spec)


def place_counted(rows: DataFrame, layout: Layout, spec: BuildSpec) -> CsrIndex:
    """place() of rows whose bins are counted here."""
    if layout.bins <= MOST_LISTED:
        counts = count_bins(rows)
        return place(rows, counts, layout, spec, hot_buckets(rows, counts, spec.hot_limit()))
    total = rows.count()
    hot = hot_buckets(rows, {-1: total}, spec.hot_limit(), everywhere=True)
    return place(rows, wide_bins(rows, layout, total), layout, spec, hot)


def build_single_sweep(df: DataFrame, key: str | Sequence[str], rid: str | None = None, spec: BuildSpec = BuildSpec(), payload: Sequence[str] = (), layout: Layout | None = None) -> CsrIndex:
    """Counts, prefixes and places by bucket alone: rows of neighbouring buckets end in any partition."""
    rows = rows_of(df, key, None if spec.payload == "key" else rid, () if spec.payload == "key" else payload)
    layout = layout or resolve(rows.count(), spec)
    rows = bucketed(rows, layout, spec)
    counts = rows.groupBy("bin", "bucket").agg(F.count("*").alias("len"))
    offsets = exclusive_prefix(counts, "bin", "bucket", "len").withColumn("part", F.lit(0))
    order = [c for c in ("key", "rid") if c in rows.columns]
    placed = rows.join(offsets.select("bucket", "start"), "bucket")
    rank = F.row_number().over(Window.partitionBy("bucket").orderBy(*order))
    edges = placed.withColumn("pos", F.col("start") + rank - 1).withColumn("part", F.lit(0)).drop("start")
    lead = ["part", "bin", "bucket", "pos", "key"]
    edges = edges.select(*lead, *[c for c in edges.columns if c not in lead])
    bins = counts.groupBy("bin").agg(F.sum("len").alias("n"))
    bins = exclusive_prefix(bins.withColumn("one", F.lit(0)), "one", "bin", "n", "bin_start").select("bin", F.lit(0).alias("part"), "n", "bin_start")
    return CsrIndex(edges, offsets.select("part", "bin", "bucket", "start", "len"), bins, layout, spec)


def build_tiered(df: DataFrame, key: str | Sequence[str], rid: str | None = None, spec: BuildSpec = BuildSpec(), payload: Sequence[str] = (), tier_bins: int = 64, store=None) -> CsrIndex:
    """For more bins than one exchange can hold: a first exchange deals coarse tiers of `tier_bins` bins, a second one deals the bins of each tier.

    store: writes and rereads a DataFrame (None: both exchanges run in one job). With it, the tiers lie on disk before the second pass, so a lost
    executor costs a part of one pass only. Bin counts of the second tier come from the reorganised rows.
    """
    rows = rows_of(df, key, rid, payload)
    fine = resolve(rows.count(), spec)
    tiers = max(1, min(-(-fine.bins // tier_bins), MOST_PARTS))
    wide = replace(fine, bins=tiers, width=fine.width * -(-fine.bins // tiers), parts=tiers)
    coarse = bucketed(rows, wide, spec)
    first = reorganise(coarse, bins_table(df.sparkSession, count_bins(coarse), wide), wide.parts).select(*rows.columns)
    dealt = bucketed(store(first) if store else first, fine, spec)
    return place_counted(dealt, fine, spec)


def hot_chunks(rows: DataFrame, limit: int, sizes: dict[int, int] | None = None) -> DataFrame:
    """Rows (bucket, key, rid...) with rank, from 0 in each bucket, and chunk, of at most `limit` rows each.

    sizes: rows of the buckets over the limit, a checked number that goes to every executor (None: they are counted here). Their rows are dealt by a hash of all columns to as many pieces as chunks are needed, each piece is counted and ranked alone, and a
    small prefix over the pieces gives the first rank, so no task sorts a whole bucket. The order inside a bucket is by piece, not by key.
    Rows that are equal in every column can't be told apart and share a piece.
    """
    if sizes is None:
        found = bucket_counts(rows).where(F.col("n") > limit).limit(MOST_HOT + 1).collect()
        if len(found) > MOST_HOT:
            raise ValueError(f"over {MOST_HOT} hot buckets; raise the limit")
        sizes = {r["bucket"]: r["n"] for r in found}
    cuts = rows.sparkSession.createDataFrame([(b, -(-n // limit)) for b, n in sizes.items()] or [(-1, 1)], "bucket bigint, pieces bigint")
    pieces = F.coalesce("pieces", F.lit(1).cast("bigint"))
    dealt = rows.join(F.broadcast(cuts), "bucket", "left").withColumn("piece", F.pmod(F.xxhash64(*rows.columns), pieces)).drop("pieces")
    small = dealt.groupBy("bucket", "piece").agg(F.count("*").alias("m"))
    first = small.withColumn("first", F.sum("m").over(Window.partitionBy("bucket").orderBy("piece")) - F.col("m")).select("bucket", "piece", "first")
    rank = F.row_number().over(Window.partitionBy("bucket", "piece").orderBy(*[c for c in ("key", "rid") if c in rows.columns])) - 1
    ranked = dealt.withColumn("local", rank).join(first, ["bucket", "piece"]).withColumn("rank", F.col("first") + F.col("local"))
    return ranked.withColumn("chunk", F.floor(F.col("rank") / F.lit(limit)).cast("bigint")).drop("piece", "local", "first")

"""Mixing sources to target weights by a multivariate-hypergeometric splitting tree.

Targets: sources share the whole size by weight; a target stops at `most_passes` times its source's size and
the excess is shared again. Each source's rows are dealt by a keyed hash to blocks, the blocks are put in
a keyed random order, and the mix takes whole passes over the source plus a prefix of that order; rows of the one
block where the quota ends are ordered by hash and taken while they fit, and one more row, of the size nearest to
what is still missing, completes the quota where that brings the sum nearer to the target.
The drawn blocks of all sources are then split among output shards: at each tree node the exact block counts
are divided between its two halves by one multivariate hypergeometric draw, until each leaf holds its own
count of each source. Leaves draw disjoint runs of the permuted blocks; rows are shuffled inside a shard only.

What the driver holds: sources x shards integers, for at most `most_sources` sources; more raise an error. Tables with a row per source
or block are stored first and joined without a hint, so they are broadcast only where their known size is small. Blocks per source are
bounded, so no task orders a whole source. Draws depend on the seed and on row values alone: reruns agree.

Null text: size 0. Null source: a source of its own, last in order. Empty table: empty result. Equal rows get
equal hashes, hence tie order is broken by row number inside the block; each counts by itself.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, Window, functions as F

from .shared import fresh, store

WORDS = r"[^\x20\x09-\x0D]+"


@dataclass(frozen=True)
class MixPlan:
    weights: tuple[float, ...] = (5.0, 2.0, 1.0)  # by source in code-point order, repeating
    most_passes: float = 3.0
    shards: int = 64
    blocks: int = 4096  # per source, at most
    seed: int = 20
    most_sources: int = 200_000  # the driver holds shards numbers for each


def targets(sizes: dict[str | None, int], plan: MixPlan) -> dict[str | None, float]:
    """Water-filling: each source's words in the mix."""
    order = sorted((s for s in sizes if s is not None)) + ([None] if None in sizes else [])
    weight = {s: plan.weights[i % len(plan.weights)] for i, s in enumerate(order)}
    left, open_sources, target = float(sum(sizes.values())), list(order), {}
    while open_sources:
        total = sum(weight[s] for s in open_sources)
        over = [s for s in open_sources if left * weight[s] / total > plan.most_passes * sizes[s]]
        if not over:
            target |= {s: left * weight[s] / total for s in open_sources}
            break
        for s in over:
            target[s] = plan.most_passes * sizes[s]
        left -= sum(target[s] for s in over)
        open_sources = [s for s in open_sources if s not in set(over)]
    return target


def split_tree(counts: np.ndarray, shards: int, seed: int) -> np.ndarray:
    """counts: blocks by source -> (shards, sources), each row summing to an equal share of the blocks.

    Every node draws with a generator of its own (seed, first shard, last shard), so any subtree can be redrawn alone.
    """
    out = np.zeros((shards, len(counts)), np.int64)
    total = int(counts.sum())
    share = np.diff(np.arange(shards + 1) * total // shards)
    todo = [(0, shards, counts.astype(np.int64))]
    while todo:
        lo, hi, own = todo.pop()
        if hi - lo == 1:
            out[lo] = own
            continue
        mid = (lo + hi) // 2
        left = int(share[lo:mid].sum())
        drawn = np.random.default_rng([seed, lo, hi]).multivariate_hypergeometric(own, left, method="marginals")
        todo += [(lo, mid, drawn), (mid, hi, own - drawn)]
    return out


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORDS)), F.lit(0)).cast("long")


def mix(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", source: str = "source", plan: MixPlan = MixPlan(), keep: list[str] | None = None) -> DataFrame:
    """keep columns (default: all of docs) + size, source_size, target, passes, taken, shards (array<int>, one entry per copy).

    taken = size * passes. Columns of docs that bear an added name are replaced.
    """
    added = ["size", "source_size", "target", "passes", "taken", "shards"]
    keep = [c for c in (docs.columns if keep is None else keep) if c.lower() not in added]
    names = [*docs.columns, *added]
    src, key, tag = (fresh(names, n) for n in ("_src", "_key", "_tag"))
    spark = docs.sparkSession
    # salt 1 deals rows to blocks, salt 2 orders blocks, salt 3 orders rows of a block
    sized = docs.select(*[F.col(f"`{c}`") for c in keep], F.col(f"`{source}`").cast("string").alias(src), word_count(F.col(f"`{text}`")).alias("size"), F.xxhash64(F.lit(plan.seed), F.col(f"`{doc_id}`").cast("string"), F.xxhash64(F.col(f"`{text}`").cast("string"))).alias(key))
    sized = store(sized.withColumn(tag, F.monotonically_increasing_id()))
    totals = [tuple(r) for r in sized.groupBy(src).agg(F.count("*"), F.sum("size")).limit(plan.most_sources + 1).collect()]  # one row per source
    if len(totals) > plan.most_sources:
        raise ValueError(f"over {plan.most_sources} sources; group them before mixing")
    if not totals:
        empty = sized.select(*[sized[c] for c in keep], "size", F.lit(0).cast("long").alias("source_size"), F.lit(0.0).alias("target"), F.lit(0).cast("long").alias("passes"), F.lit(0).cast("long").alias("taken"), F.array(F.lit(0)).alias("shards"))
        return empty
    order = sorted(totals, key=lambda r: (r[0] is None, r[0] or ""))
    goal = targets({s: int(n) for s, _, n in order}, plan)
    table = [(i, s, int(n), int(size), goal[s], max(1, min(plan.blocks, int(n)))) for i, (s, n, size) in enumerate(order)]
    sources = spark.createDataFrame(table, "_s int, _name string, _n long, source_size long, target double, _blocks int")
    named = sized.join(sources, sized[src].eqNullSafe(sources["_name"])).withColumn("_block", F.pmod(F.xxhash64(F.lit(1), key), F.col("_blocks")).cast("int"))
    # one row per block: at most `blocks` per source
    by_block = named.groupBy("_s", "_block").agg(F.sum("size").alias("_size"), F.first("target").alias("target"), F.first("source_size").alias("source_size"))
    at = Window.partitionBy("_s").orderBy(F.xxhash64(F.lit(2), F.lit(plan.seed), "_s", "_block"), "_block")
    whole = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(F.lit(0))
    part = F.col("target") - F.col("_whole") * F.col("source_size")
    blocks = by_block.withColumn("_place", F.row_number().over(at) - 1).withColumn("_before", F.sum("_size").over(at) - F.col("_size")).withColumn("_whole", whole)
    # the rest of the quota that falls into this block: all of it, a part, or nothing
    blocks = store(blocks.withColumn("_quota", F.least(F.greatest(part - F.col("_before"), F.lit(0.0)), F.col("_size").cast("double"))))
    per_source = blocks.groupBy("_s").agg(F.max("_whole"), F.count(F.when(F.col("_quota") > 0, 1)), F.count("*")).collect()
    drawn = {s: (int(w), int(more), int(n)) for s, w, more, n in per_source}
    counts = np.array([drawn[i][0] * drawn[i][2] + drawn[i][1] for i in range(len(table))], np.int64)
    shards = max(1, min(plan.shards, int(counts.sum()) or 1))
    ends = np.cumsum(split_tree(counts, shards, plan.seed), axis=0)  # by shard: where its run of a source's drawn blocks ends
    runs = spark.createDataFrame([(i, [int(x) for x in ends[:, i]], drawn[i][1], drawn[i][2]) for i in range(len(table))], "_r int, _ends array<long>, _more long, _nb long")
    edge = store(blocks.where("_quota > 0 and _quota < _size").select(F.col("_s").alias("_es"), F.col("_block").alias("_eb"), "_quota"))  # one row per source
    cut = Window.partitionBy("_s").orderBy(F.xxhash64(F.lit(3), key), tag)
    cut_rows = named.join(edge, (named["_s"] == edge["_es"]) & (named["_block"] == edge["_eb"])).withColumn("_upto", F.sum("size").over(cut))
    cut_rows = store(cut_rows.where(F.col("_upto") <= F.col("_quota")).select(F.col(tag).alias("_cut_tag")))
    places = blocks.select(F.col("_s").alias("_bs"), F.col("_block").alias("_bb"), "_place", "_whole", (F.col("_quota") >= F.col("_size")).alias("_full"), F.col("_quota").alias("_q"))
    rows = named.join(places, (named["_s"] == places["_bs"]) & (named["_block"] == places["_bb"])).join(cut_rows, named[tag] == cut_rows["_cut_tag"], "left")
    rows = rows.withColumn("_fits", ((F.col("_q") > 0) & F.col("_full")) | F.col("_cut_tag").isNotNull())
    # what is still missing of each quota is left to the one undrawn row whose size is nearest to it
    gap = F.first("target") - F.first(F.col("_whole") * F.col("source_size")) - F.sum(F.when(F.col("_fits"), F.col("size")).otherwise(0))
    gaps = store(rows.groupBy("_s").agg(gap.alias("_gap")).select(F.col("_s").alias("_gs"), "_gap"))
    missed = F.abs(F.col("_gap") - F.col("size"))
    spare = rows.where(~F.col("_fits")).join(gaps, F.col("_s") == F.col("_gs")).where(missed < F.col("_gap"))
    fill = store(spare.groupBy("_s").agg(F.min_by(tag, F.struct(missed, F.xxhash64(F.lit(3), key), tag)).alias("_fill_tag")).select(F.col("_s").alias("_fs"), "_fill_tag"))
    rows = rows.join(fill, (F.col("_s") == F.col("_fs")) & (F.col(tag) == F.col("_fill_tag")), "left").join(runs, named["_s"] == runs["_r"])
    # a source's drawn blocks are numbered: the partial pass first (the row that fills it up counts to its last block), then whole passes
    partial = F.when(F.col("_fits"), F.array(F.col("_place").cast("long"))).when(F.col("_fill_tag").isNotNull(), F.array(F.greatest(F.col("_more") - 1, F.lit(0)))).otherwise(F.array().cast("array<long>"))
    passes = F.when(F.col("_whole") > 0, F.sequence(F.lit(0).cast("long"), F.col("_whole").cast("long") - 1)).otherwise(F.array().cast("array<long>"))
    numbers = F.concat(partial, F.transform(passes, lambda j: F.col("_more") + j * F.col("_nb") + F.col("_place")))
    shard = F.transform(numbers, lambda p: F.size(F.filter(F.col("_ends"), lambda e: e <= p)).cast("int"))
    rows = rows.withColumn("passes", F.size(numbers).cast("long"))
    return rows.select(*[named[c] for c in keep], "size", "source_size", "target", "passes", (F.col("size") * F.col("passes")).alias("taken"), shard.alias("shards"))


def draw(docs: DataFrame, **options) -> DataFrame:
    """The mix itself: each row of docs once per copy taken, partitioned by output shard and shuffled inside it."""
    columns = docs.columns
    clean = docs.select(*[F.col(f"`{c}`").alias(f"c{i}") for i, c in enumerate(columns)])
    at = {c: f"c{i}" for i, c in enumerate(columns)}
    plan = options.get("plan", MixPlan())
    # the mix is found on row numbers alone, so that texts move twice: to their copies' numbers and to their shard
    stored = store(clean.withColumn("_row", F.monotonically_increasing_id()))
    mixed = mix(stored, at[options.get("doc_id", "doc_id")], at[options.get("text", "text")], at[options.get("source", "source")], plan, keep=["_row"])
    drawn = mixed.where(F.size("shards") > 0).select(F.col("_row").alias("_drawn"), "shards")
    copies = stored.join(drawn, F.col("_row") == F.col("_drawn")).select(*clean.columns, F.posexplode("shards").alias("_copy", "_shard"))
    rank = F.xxhash64(F.lit(plan.seed), F.lit(4), at[options.get("doc_id", "doc_id")], "_copy", "_shard")
    spread = copies.repartition(F.col("_shard"), F.pmod(rank, F.lit(16))).sortWithinPartitions("_shard", rank)
    return spread.select(*[F.col(at[c]).alias(c) for c in columns])

"""Cuckoo tables in rounds of whole-table steps."""

from __future__ import annotations

from dataclasses import dataclass
from math import ceil
from uuid import uuid4

from pyspark.sql import DataFrame, functions as F

from ..functions.hashing import HashSpec, bucket_of
from ..sources.storage import forget, shared_folder


@dataclass(frozen=True)
class CuckooTable:
    """placed(key, rid, slot, f) and stash(key, rid); rounds run, claims made over all rounds."""

    placed: DataFrame
    stash: DataFrame
    rounds: int
    claims: int
    slots: int
    functions: int
    parts: int = 1

    def lookup(self, probe: DataFrame) -> DataFrame:
        """probe(key, rid) -> (key, l_rid, r_rid): each row looks at its `functions` slots and at the stash."""
        rows = probe.where("key is not null")
        spots = rows.select("key", F.col("rid").alias("l_rid"), F.explode(F.array_distinct(F.array(*[_slot(i, self.slots, self.parts) for i in range(self.functions)]))).alias("slot"))
        built = self.placed.select(F.col("key").alias("_k"), F.col("rid").alias("r_rid"), "slot")
        hit = spots.join(built, "slot").where(F.col("key") == F.col("_k")).select("key", "l_rid", "r_rid")
        extra = rows.select("key", F.col("rid").alias("l_rid")).join(self.stash.select("key", F.col("rid").alias("r_rid")), "key")
        return hit.unionByName(extra)


def _slot(i: int, slots: int, parts: int = 1):
    if parts == 1:
        return bucket_of([F.col("key")], slots, HashSpec(seed=101 + i))
    return bucket_of([F.col("key")], parts, HashSpec(seed=97)) * (slots // parts) + bucket_of([F.col("key")], slots // parts, HashSpec(seed=101 + i))


def cuckoo_partitioned(keys: DataFrame, load: float, parts: int, functions: int = 4, max_rounds: int = 100) -> CuckooTable:
    """The out-of-core form: the key space is cut into `parts` ranges of slots, each a table of its own that fits one task.

    All functions of a key stay inside its range, so a range is built and probed without any other; the rounds are those of one table.
    """
    n = keys.where("key is not null").count()
    per = max(1, ceil(n / load / parts))
    return cuckoo_build(keys, per * parts, functions, max_rounds, parts=parts)


def cuckoo_build(keys: DataFrame, slots: int, functions: int = 4, max_rounds: int = 100, folder: str | None = None, parts: int = 1) -> CuckooTable:
    """keys(key, rid). In a round every waiting key claims its current function's slot; the smallest rid of the newcomers wins,
    whoever sat there moves on to its next function, and so do the losers. After max_rounds the rest is the stash.

    folder: where rounds are written (None: the session's checkpoint folder); a round's table is deleted once the next one is there.
    parts: ranges of slots that keys never leave.
    """
    spark = keys.sparkSession
    base = f"{folder.rstrip('/')}/cuckoo-{uuid4().hex}" if folder else shared_folder(spark, "cuckoo")

    def written(df: DataFrame, name: str) -> DataFrame:
        df.write.parquet(f"{base}/{name}")
        return spark.read.schema(df.schema).parquet(f"{base}/{name}")

    slot = F.lit(0).cast("bigint")
    for i in range(functions - 1, -1, -1):
        slot = F.when(F.pmod(F.col("f"), F.lit(functions)) == i, _slot(i, slots, parts)).otherwise(slot)
    state = written(keys.where("key is not null").select("key", "rid", F.lit(0).alias("f"), F.lit(True).alias("waiting")), "0")
    rounds = claims = 0
    while rounds < max_rounds:
        n = state.where("waiting").count()
        if not n:
            break
        rounds += 1
        claims += n
        at = state.withColumn("slot", slot)
        # newcomers win over who sits there; among newcomers the smallest rid
        winner = at.groupBy("slot").agg(F.min(F.struct(~F.col("waiting"), "rid")).alias("w")).select("slot", F.col("w.rid").alias("winner"))
        moved = at.join(winner, "slot").withColumn("wins", F.col("rid") == F.col("winner"))
        state = written(moved.select("key", "rid", F.when(F.col("wins"), F.col("f")).otherwise(F.col("f") + 1).cast("int").alias("f"), (~F.col("wins")).alias("waiting")), str(rounds))
        forget(spark, f"{base}/{rounds - 1}")
    return CuckooTable(state.where("not waiting").withColumn("slot", slot).select("key", "rid", "slot", "f"), state.where("waiting").select("key", "rid"), rounds, claims, slots, functions, parts)

"""Linear open addressing in closed form: what every insert and lookup costs, without running one."""

from __future__ import annotations

from math import ceil

from pyspark.sql import DataFrame, Window, functions as F

from ..functions.hashing import HashSpec, bucket_of


def slots_for(n: int, load: float) -> int:
    if not 0 < load < 1:
        raise ValueError("an open-addressing table needs more slots than keys: 0 < load < 1")
    return max(1, ceil(n / load))


def _homes(keys: DataFrame, slots: int, spec: HashSpec, bins: int) -> DataFrame:
    """(bin, slot, n) for every slot; n keys have it as their home."""
    counts = keys.where("key is not null").select(bucket_of([F.col("key")], slots, spec).alias("slot")).groupBy("slot").agg(F.count("*").alias("n"))
    width = ceil(slots / bins)
    return keys.sparkSession.range(slots).select(F.col("id").alias("slot")).join(counts, "slot", "left").select(F.floor(F.col("slot") / width).cast("bigint").alias("bin"), "slot", F.coalesce("n", F.lit(0)).cast("bigint").alias("n"))


def _carried(homes: DataFrame) -> DataFrame:
    """homes + carry: keys pushed past each slot, and came: those pushed into it.

    The carry follows w = max(0, w + n - 1). Inside a bin it comes from a running sum and its running minimum; between bins
    only (sum, minimum) pairs combine, on the driver, twice around since the table is a ring.
    """
    inside = Window.partitionBy("bin").orderBy("slot")
    run = homes.withColumn("s", F.sum(F.col("n") - 1).over(inside))
    run = run.withColumn("m", F.min("s").over(inside.rowsBetween(Window.unboundedPreceding, Window.currentRow)))
    totals = run.groupBy("bin").agg(F.max_by("s", "slot").alias("s"), F.min("s").alias("m")).orderBy("bin").collect()
    enter: dict[int, int] = {}
    w = 0
    for _ in range(2):
        for r in totals:
            enter[r["bin"]] = w
            w = r["s"] + max(w, -r["m"])
    side = homes.sparkSession.createDataFrame(list(enter.items()) or [(0, 0)], "bin bigint, w bigint")
    done = run.join(F.broadcast(side), "bin").withColumn("carry", F.col("s") + F.greatest("w", -F.col("m")))
    return done.withColumn("came", F.coalesce(F.lag("carry").over(inside), "w")).drop("s", "m", "w")


#: Slots that one window runs over, about.
BIN_SLOTS = 4_000_000


def displacement(keys: DataFrame, slots: int, spec: HashSpec = HashSpec(), bins: int = 16) -> DataFrame:
    """keys(key) -> one row: slots, displacement (steps past home over all inserts), worst carry. Independent of insert order."""
    n = keys.where("key is not null").count()
    if n >= slots:
        raise ValueError(f"{n} keys don't fit in {slots} slots")
    return _carried(_homes(keys, slots, spec, max(bins, ceil(slots / BIN_SLOTS)))).agg(F.lit(slots).cast("bigint").alias("slots"), F.sum("carry").cast("bigint").alias("displacement"), F.max("carry").cast("bigint").alias("max_carry"))


def find_first_cost(keys: DataFrame, slots: int, spec: HashSpec = HashSpec(), bins: int = 16) -> DataFrame:
    """One row: slots looked at when each of the distinct keys is sought until its first hit.

    Of unique keys, whatever their order, the walks to the hits add up to the displacement and one slot each.
    """
    unique = keys.where("key is not null").select("key").distinct()
    n = unique.count()
    moved = displacement(unique, slots, spec, bins)
    return moved.select("slots", F.lit(n).cast("bigint").alias("n_keys"), (F.col("displacement") + n).alias("slots_read"))


def miss_cost(keys: DataFrame, slots: int, spec: HashSpec = HashSpec(), bins: int = 16) -> DataFrame:
    """One row: slots looked at when one absent key is sought from every slot, and their mean."""
    read = _walks(keys, slots, spec, max(bins, ceil(slots / BIN_SLOTS)))
    total = F.sum("walk")  # a probe from each slot
    return read.agg(F.lit(slots).cast("bigint").alias("slots"), total.cast("bigint").alias("slots_read"), F.round(total / slots, 6).alias("mean"))


def find_all_cost(keys: DataFrame, slots: int, spec: HashSpec = HashSpec(), bins: int = 16) -> DataFrame:
    """One row: slots looked at when each key scans from its home to the first empty slot."""
    cost = F.col("n") * F.col("walk")
    return _walks(keys, slots, spec, max(bins, ceil(slots / BIN_SLOTS))).agg(F.lit(slots).cast("bigint").alias("slots"), F.coalesce(F.sum(cost), F.lit(0)).cast("bigint").alias("slots_read"))


def _walks(keys: DataFrame, slots: int, spec: HashSpec, bins: int) -> DataFrame:
    """(slot, n, walk): keys whose home it is, and slots from it to the first empty one, both counted."""
    state = _carried(_homes(keys, slots, spec, bins)).withColumn("free_at", F.when((F.col("n") + F.col("came")) == 0, F.col("slot")))
    # backwards, so that the minimum runs along; a frame that ends at the bin's end would be gone through anew for each slot
    backwards = Window.partitionBy("bin").orderBy(F.col("slot").desc()).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    near = state.withColumn("next_free", F.min("free_at").over(backwards))
    first = {r["bin"]: r["f"] for r in state.groupBy("bin").agg(F.min("free_at").alias("f")).collect()}
    order = sorted(first)
    after: dict[int, int] = {}
    seen: int | None = None
    for lap in (slots, 0):
        for b in reversed(order):
            after[b] = seen
            if first[b] is not None:
                seen = first[b] + lap
    side = keys.sparkSession.createDataFrame(list(after.items()) or [(0, 0)], "bin bigint, later bigint")
    return near.join(F.broadcast(side), "bin").select("slot", "n", (F.coalesce("next_free", "later") - F.col("slot") + 1).alias("walk"))


def simulate(homes: list[int], slots: int) -> tuple[list[int | None], int]:
    """Brute force for tests: the table and its total displacement."""
    table: list[int | None] = [None] * slots
    moved = 0
    for i, h in enumerate(homes):
        at = h
        while table[at] is not None:
            at = (at + 1) % slots
            moved += 1
        table[at] = i
    return table, moved

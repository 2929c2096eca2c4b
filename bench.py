"""Headline timings: prints one JSON line. BENCH_SF_DIR (default /root/testdata/sf0.1), BENCH_CPUS (default 8)."""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import DataFrame, SparkSession, functions as F

from bucketcsr.baselines import cuckoo, joins as base_joins, linear
from bucketcsr.measures import degradation, rate, speedup, timed, uniform_keys
from bucketcsr.operators import build, probe
from bucketcsr.plans.params import BuildSpec
from bucketcsr.sources import storage

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
SPEC = BuildSpec(bins=64, parts=8)


def run(df: DataFrame) -> None:
    df.write.format("noop").mode("overwrite").save()


def once(make) -> float:
    began = time.perf_counter()
    run(make())
    return time.perf_counter() - began


def experiments(spark: SparkSession, read, ids: DataFrame, orders: DataFrame) -> dict:
    """Small grids of the paper's experiments; rates in keys a second, one warm-up and one run each. Every probe of a grid returns the same count."""
    n, m = ids.count(), orders.count()
    took = lambda make: timed(make, 1)
    spec = lambda **k: BuildSpec(**({"bins": 64, "parts": 8} | k))
    keyed = lambda df, key, rid: df.select(F.col(key).alias("key"), F.col(rid).alias("rid"))
    out: dict = {}

    # build rate by load, both versions, beside tables for unique keys, linear and cuckoo tables
    out["build_by_load"] = {}
    for load in (0.5, 0.8, 1.0, 2.0, 4.0):
        one = {name: round(rate(n, took(lambda h=how, c=load: h(ids, "l_orderkey", "id", spec(load=c)).edges))) for name, how in (("binned", build.build_binned), ("single_sweep", build.build_single_sweep))}
        if load < 1:
            one["linear_model"] = round(rate(n, took(lambda c=load: linear.displacement(ids.select(F.col("l_orderkey").alias("key")), linear.slots_for(n, c)))))
        out["build_by_load"][str(load)] = one
    unique = keyed(orders, "o_orderkey", "o_orderkey")
    out["build_unique_keys"] = {
        "binned": round(rate(m, took(lambda: build.build_binned(orders, "o_orderkey", "o_orderkey", spec()).edges))),
        "unique_only": round(rate(m, took(lambda: base_joins.unique_table(orders, "o_orderkey")))),
    }
    began = time.perf_counter()
    table = cuckoo.cuckoo_build(unique, linear.slots_for(m, 0.5), max_rounds=8)
    seconds = time.perf_counter() - began
    out["build_unique_keys"] |= {"cuckoo_8_rounds": round(rate(m, seconds)), "cuckoo_claims": table.claims}
    out["speedup_over_cuckoo"] = round(speedup(m / out["build_unique_keys"]["binned"], seconds), 2)

    # build rate by appearances, and what a linear table would have to walk
    out["build_by_appearance"] = {}
    for r in (0.125, 1, 8, 32):
        keys = uniform_keys(ids, "id", r).withColumn("rid", F.lit(0).cast("bigint"))
        walked = linear.displacement(keys, linear.slots_for(n, 0.5)).first()["displacement"]
        out["build_by_appearance"][str(r)] = {"binned": round(rate(n, took(lambda k=keys: build.build_binned(k, "key", "rid", spec()).edges))), "linear_steps_per_key": round(walked / n, 3)}
    by_r = out["build_by_appearance"]
    out["loss_at_32_appearances"] = round(degradation(by_r["32"]["binned"], by_r["1"]["binned"]), 3)

    # build rate by bins and by size
    out["build_by_bins"], out["build_by_size"] = {}, {}
    for bins in (1, 16, 256, 4096):
        out["build_by_bins"][str(bins)] = round(rate(n, took(lambda b=bins: build.build_binned(ids, "l_orderkey", "id", BuildSpec(bins=b, parts=8)).edges)))
    for size in ("sf0.001", "sf0.01", "sf0.1"):
        path = os.path.join(os.path.dirname(SF_DIR.rstrip("/")), size, "lineitem.parquet")
        if os.path.exists(path):
            rows = spark.read.parquet(path).withColumn("id", F.monotonically_increasing_id())
            out["build_by_size"][size] = round(rate(rows.count(), took(lambda r=rows: build.build_binned(r, "l_orderkey", "id", spec()).edges)))

    # probes of a stored index by load: row by row, list against list, and the share of the second index
    out["probe_by_load"] = {}
    for load in (0.5, 1.0, 4.0):
        path = storage.shared_folder(spark, "bench")
        storage.save(build.build_binned(orders, "o_orderkey", "o_orderkey", spec(load=load)), path)
        stored = storage.load(spark, path)
        pairs = lambda df: df.agg(F.count("*").alias("n_pairs"))
        lookup = lambda s=stored: pairs(probe.lookup_probe(s, ids, "l_orderkey", "id"))
        first = lambda s=stored: pairs(probe.lookup_probe(s, ids, "l_orderkey", "id", "first"))
        second = lambda s=stored: probe.align(s, ids, "l_orderkey", "id").edges
        both = lambda s=stored: pairs(probe.cobucket_probe(probe.align(s, ids, "l_orderkey", "id"), s))
        assert lookup().first() == both().first() == first().first()
        whole, part = took(both), took(second)
        out["probe_by_load"][str(load)] = {"lookup_all": round(rate(n, took(lookup))), "lookup_first": round(rate(n, took(first))), "cobucket_all": round(rate(n, whole)), "second_index_share": round(part / whole, 2)}
        storage.forget(spark, path)

    # self-probes by appearances, counted: row by row against list by list
    out["probe_by_appearance"] = {}
    for r in (1, 8, 32):
        keys = uniform_keys(ids, "id", r).withColumn("rid", F.lit(0).cast("bigint"))
        rows = lambda k=keys: base_joins.multicore_join(k.select("key"), k.select("key"), "key").agg(F.count("*").alias("n_pairs"))
        lists = lambda k=keys: probe.cobucket_count(k, k, "key", "key")
        assert rows().first() == lists().first()
        out["probe_by_appearance"][str(r)] = {"rows": round(rate(2 * n, took(rows))), "lists": round(rate(2 * n, took(lists)))}

    # two equal inputs, counted only
    lines = read("lineitem")
    a, b = (lines.where(f"l_returnflag = '{f}'").select(F.col("l_partkey").alias("key")) for f in "AR")
    size = a.count() + b.count()
    out["equal_size_join"] = {"lists": round(rate(size, took(lambda: probe.cobucket_count(a, b, "key", "key")))), "multicore": round(rate(size, took(lambda: base_joins.multicore_join(a, b, "key").groupBy().count())))}
    return out


def main() -> None:
    spark = SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", CPUS).config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    read = lambda name: spark.read.parquet(f"{SF_DIR}/{name}.parquet")
    lines, orders = read("lineitem"), read("orders")
    n_lines, n_orders = lines.count(), orders.count()
    ids = lines.withColumn("id", F.monotonically_increasing_id())
    tables = [storage.save_lists_table(ix, f"bench_lists_{k}", 8) for k, ix in enumerate(probe.build_pair(lines, orders, "l_orderkey", "o_orderkey", spec=SPEC))]
    cases = {
        "build_binned": (n_lines, lambda: build.build_binned(ids, "l_orderkey", "id", SPEC).edges),
        "build_single_sweep": (n_lines, lambda: build.build_single_sweep(ids, "l_orderkey", "id", SPEC).edges),
        "build_load_half": (n_lines, lambda: build.build_binned(ids, "l_orderkey", "id", BuildSpec(load=0.5, bins=64, parts=8)).offsets),
        "build_load_2": (n_lines, lambda: build.build_binned(ids, "l_orderkey", "id", BuildSpec(load=2.0, bins=64, parts=8)).offsets),
        "build_load_4": (n_lines, lambda: build.build_binned(ids, "l_orderkey", "id", BuildSpec(load=4.0, bins=64, parts=8)).offsets),
        "cobucket_count": (n_lines + n_orders, lambda: probe.cobucket_count(lines, orders, "l_orderkey", "o_orderkey", SPEC)),
        "cobucket_count_indexed": (n_lines + n_orders, lambda: probe.cobucket_probe(*probe.build_pair(lines, orders, "l_orderkey", "o_orderkey", spec=SPEC), mode="count")),
        "cobucket_count_stored": (n_lines + n_orders, lambda: tables[0].join(tables[1].withColumnRenamed("n", "m"), ["bucket", "key"]).agg(F.sum(F.col("n") * F.col("m")))),
        "lookup_count": (n_lines, lambda: probe.lookup_probe(build.build_binned(orders, "o_orderkey", "o_orderkey", SPEC), lines, "l_orderkey", None, "count")),
        "self_join_partkey_count": (2 * n_lines, lambda: probe.cobucket_count(lines, lines, "l_partkey", "l_partkey", SPEC)),
        "multicore_join_count": (n_lines + n_orders, lambda: base_joins.multicore_join(lines.select(F.col("l_orderkey").alias("key")), orders.select(F.col("o_orderkey").alias("key")), "key").groupBy().count()),
        "multicore_self_join_count": (2 * n_lines, lambda: base_joins.multicore_join(lines.select(F.col("l_partkey").alias("key")), lines.select(F.col("l_partkey").alias("key")), "key").groupBy().count()),
    }
    for r in (1, 2, 8, 32):
        keys = uniform_keys(ids, "id", r).withColumn("rid", F.lit(0).cast("bigint"))
        cases[f"build_uniform_r{r}"] = (n_lines, lambda k=keys: build.build_binned(k, "key", None, SPEC).offsets)
    seconds, rates = {}, {}
    for name, (rows, make) in cases.items():
        once(make)  # warm-up
        took = sorted(once(make) for _ in range(3))[1]
        seconds[name], rates[name] = round(took, 3), round(rows / took)
    more = experiments(spark, read, ids, orders)
    for k in range(2):
        spark.sql(f"drop table if exists bench_lists_{k}")
    print(json.dumps({"metric": "total_median_seconds", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "keys_per_sec": rates, "experiments": more, "sf": os.path.basename(SF_DIR.rstrip("/")).removeprefix("sf")}))
    spark.stop()


if __name__ == "__main__":
    main()

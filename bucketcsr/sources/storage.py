"""Indexes on disk: <path>/edges, /offsets, /bins, /lists (rows by key) and /meta, or bucketed tables that join without an exchange."""

from __future__ import annotations

import atexit
import json
from dataclasses import asdict
from uuid import uuid4

from pyspark.sql import DataFrame, SparkSession

from ..functions.hashing import HashSpec
from ..operators.build import CsrIndex
from ..operators.probe import key_lists
from ..plans.params import BuildSpec, Layout

VERSION = 2


def _meta(index: CsrIndex) -> str:
    return json.dumps({"version": VERSION, "layout": asdict(index.layout), "hot": index.hot, "spec": asdict(index.spec), "key_type": index.edges.schema["key"].dataType.json()})


def save(index: CsrIndex, path: str) -> None:
    """Files are sorted by bin and bucket, so row-group statistics prune point lookups."""
    spark = index.edges.sparkSession
    index.edges.sortWithinPartitions("bin", "bucket", "pos").write.parquet(f"{path}/edges")
    index.offsets.sortWithinPartitions("bin", "bucket").write.parquet(f"{path}/offsets")
    index.bins.write.parquet(f"{path}/bins")
    key_lists(index).write.parquet(f"{path}/lists")
    spark.createDataFrame([(_meta(index),)], "value string").coalesce(1).write.text(f"{path}/meta")


def load(spark: SparkSession, path: str) -> CsrIndex:
    meta = json.loads(spark.read.text(f"{path}/meta").first()[0])
    if meta["version"] != VERSION:
        raise ValueError(f"index version {meta['version']}, {VERSION} is read")
    spec = meta["spec"] | {"hash": HashSpec(**meta["spec"]["hash"])}
    read = lambda name: spark.read.parquet(f"{path}/{name}")
    return CsrIndex(read("edges"), read("offsets"), read("bins"), Layout(**meta["layout"]), BuildSpec(**spec), tuple(map(tuple, meta["hot"])), read("lists"))


def save_table(index: CsrIndex, name: str, buckets: int) -> DataFrame:
    """Edges as a table bucketed by bin; two such tables of one layout and bucket count join on (bin, bucket, key) in place.

    Needs spark.sql.requireAllClusterKeysForCoPartition=false in the session that joins them.
    """
    index.edges.drop("part").write.bucketBy(buckets, "bin").sortBy("bin", "bucket").mode("overwrite").saveAsTable(name)
    return index.edges.sparkSession.table(name)


def save_lists_table(index: CsrIndex, name: str, buckets: int) -> DataFrame:
    """(bucket, key, n) as a table bucketed by both; two such tables of one bucket range and file count meet without an exchange."""
    key_lists(index).write.bucketBy(buckets, "bucket", "key").sortBy("bucket", "key").mode("overwrite").saveAsTable(name)
    return index.edges.sparkSession.table(name)


def shared_folder(spark: SparkSession, kind: str) -> str:
    """A new folder's path that driver and executors share; on this machine's disk only where nothing but it runs tasks."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named and not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    path = f"{(named or 'file:///tmp/bucketcsr-tables').rstrip('/')}/{kind}-{uuid4().hex}"
    _made.append((spark, path))
    return path


#: Folders of this process, deleted when it ends.
_made: list[tuple[SparkSession, str]] = []


@atexit.register
def _forget_all() -> None:
    for spark, path in _made:
        try:
            forget(spark, path)
        except Exception:  # noqa: BLE001  the session may have ended before the interpreter
            return


def forget(spark: SparkSession, path: str) -> None:
    """Deletes a folder that nothing reads any more."""
    place = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(place, True)


def read_any(spark: SparkSession, path: str, kind: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    """Parquet, ORC, CSV, JSON or text; text-like kinds take a schema instead of guessing one over all rows."""
    if kind not in ("parquet", "orc", "csv", "json", "text"):
        raise ValueError(f"unknown kind {kind!r}")
    reader = spark.read.options(**options)
    return (reader.schema(schema) if schema else reader).format(kind).load(path)

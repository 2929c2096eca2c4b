"""What the text operators share: stored intermediate tables, batch slicing, dirty-schema helpers."""

from __future__ import annotations

import atexit
import getpass
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, functions as F, types as T

#: Text bytes that one Python step works on at a time; a longer single text forms a step alone.
STEP_BYTES = 1 << 20

_stored: list[tuple[SparkSession, str]] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; a private one only where the session names none and runs on this machine alone."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named and not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    return f"{(named or f'file:///tmp/bucketcsr-{getpass.getuser()}').rstrip('/')}/tables"


def forget(spark: SparkSession, path: str) -> None:
    """Deletes a stored table that nothing reads any more."""
    jvm = spark.sparkContext._jvm
    place = jvm.org.apache.hadoop.fs.Path(path)
    place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(place, True)


def _forget_all() -> None:
    for spark, path in _stored:
        try:
            forget(spark, path)
        except Exception:  # noqa: BLE001  the session may have ended before the interpreter
            return


atexit.register(_forget_all)


def store(df: DataFrame, partition_by: list[str] | None = None) -> DataFrame:
    """Writes df as a Parquet table in the shared folder and reads it back.

    Cuts the lineage: a lost executor costs only the tasks that ran on it, never an earlier stage.
    """
    return store_at(df, partition_by)[0]


def store_at(df: DataFrame, partition_by: list[str] | None = None) -> tuple[DataFrame, str]:
    """As store(), with the path for forget()."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{uuid.uuid4().hex}"
    writer = df.write.option("compression", "zstd")
    (writer.partitionBy(*partition_by) if partition_by else writer).parquet(path)
    _stored.append((spark, path))
    fields = list(df.schema.fields)
    if partition_by:
        fields = [f for f in fields if f.name not in partition_by] + [f for f in fields if f.name in partition_by]
    return spark.read.schema(T.StructType(fields)).parquet(path), path


#: Bitmaps of row numbers of at most so many bytes are sent to every executor; a bitmap has 4,096 bytes.
BITMAP_BYTES = 64 << 20


def numbered(rows: DataFrame, number: str, chosen: DataFrame, chosen_number: str, most: int = BITMAP_BYTES) -> DataFrame:
    """Rows whose number, given by monotonically_increasing_id, stands in chosen. They stay where they are: one bit per row goes to them (over `most` bytes: a join)."""
    of = F.col(chosen_number)
    bits = chosen.groupBy(F.bitmap_bucket_number(of).alias("_bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(of)).alias("_bits"))
    bits = store(bits)
    if bits.count() * 4096 > most:
        return rows.join(chosen, rows[number] == chosen[chosen_number], "left_semi")
    at = F.bitmap_bit_position(rows[number])
    byte = F.conv(F.hex(F.substring(F.col("_bits"), F.floor(at / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
    met = rows.join(F.broadcast(bits), F.bitmap_bucket_number(rows[number]) == F.col("_bucket"))
    return met.where(byte.bitwiseAND(F.pow(F.lit(2), at % 8).cast("int")) != 0).select(*[rows[c] for c in rows.columns])


def fresh(columns: list[str], name: str) -> str:
    """A column name that clashes with none of the given ones, in any case."""
    taken = {c.lower() for c in columns}
    while name.lower() in taken:
        name += "_"
    return name


def slices(batch: pa.RecordBatch, column: str | int, most: int = STEP_BYTES) -> Iterator[pa.RecordBatch]:
    """Cuts a record batch so that each part holds about `most` bytes of the column's text."""
    i = batch.schema.get_field_index(column) if isinstance(column, str) else column
    sizes = pc.fill_null(pc.binary_length(batch.column(i)), 0).to_numpy(zero_copy_only=False)
    begin, total = 0, 0
    for k, n in enumerate(sizes.tolist()):
        if k > begin and total + n > most:
            yield batch.slice(begin, k - begin)
            begin, total = k, 0
        total += n
    if begin < batch.num_rows:
        yield batch.slice(begin)


def map_text(df: DataFrame, column: str, add: list[T.StructField], make: Callable[[pa.Array], list[pa.Array]], keep: list[str] | None = None) -> DataFrame:
    """Appends columns that `make` computes from whole texts, batch by batch.

    keep: the columns that go along (default: all); the text goes along only if it is among them.
    """
    keep = df.columns if keep is None else keep
    text_at = len(keep)
    source = df.select(*[df[c] for c in keep], df[column].cast("string").alias(fresh(keep, "_text")))
    schema = T.StructType([df.schema[c] for c in keep] + add)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pa.set_memory_pool(pa.system_memory_pool())  # gives memory back between steps
        names = [f.name for f in schema.fields]
        for batch in batches:
            for part in slices(batch, text_at):
                made = make(part.column(text_at))
                yield pa.RecordBatch.from_arrays([part.column(i) for i in range(text_at)] + made, names=names)

    return source.mapInArrow(run, schema)


def deal_tiles(rows: DataFrame, group: list[str], member: str, tile: int) -> DataFrame:
    """rows of groups of two or more, dealt to tiles (group..., one, two), with `mine` their chunk.

    A group of over `tile` rows is cut into chunks by a hash of `member`; each row goes to one tile for every chunk it must meet,
    so every pair of a group's rows meets in exactly one tile and no tile holds more than two chunks. Of groups with the very same members (told by number, ends and 128 bits of
    hash) only one is dealt, since the others hold no pair that it lacks.
    """
    of = [F.bit_xor(F.xxhash64(member)).alias("_x"), F.bit_xor(F.xxhash64(F.lit(1), member)).alias("_y"), F.min(member).alias("_lo"), F.max(member).alias("_hi")]
    sizes = rows.groupBy(*group).agg(F.count("*").alias("_n"), *of).where("_n > 1").withColumn("_chunks", F.ceil(F.col("_n") / tile).cast("int"))
    sizes = sizes.groupBy("_n", "_x", "_y", "_lo", "_hi").agg(F.min(F.struct(*group, "_chunks")).alias("_g"))
    sizes = store(sizes.select(*[F.col(f"_g.{c}").alias(f"_g_{c}") for c in group], "_g._chunks"))
    joined = rows.join(sizes, [rows[c] == sizes[f"_g_{c}"] for c in group])
    mine = F.pmod(F.xxhash64(member), F.col("_chunks")).cast("int")
    dealt = joined.withColumn("mine", mine).withColumn("_peer", F.explode(F.sequence(F.lit(0), F.col("_chunks") - 1)))
    dealt = dealt.withColumns({"one": F.least("mine", "_peer"), "two": F.greatest("mine", "_peer")})
    return dealt.drop("_peer", "_chunks", *[f"_g_{c}" for c in group])

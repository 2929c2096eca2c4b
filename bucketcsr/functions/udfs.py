"""The hash as SQL and Arrow functions, an aggregate of bucket lengths, and a table function over bins."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import SparkSession, functions as F, types as T


@F.arrow_udf(T.LongType())
def mix32_arrow(key: pa.Array) -> pa.Array:
    """mix32 over Arrow arrays; null stays null."""
    low = pc.bit_wise_and(key.cast(pa.int64()), (1 << 31) - 1)
    return pc.bit_wise_and(pc.add(pc.multiply(low, 2654435769), pc.shift_right(low, 15)), (1 << 32) - 1)


@F.pandas_udf(T.LongType())
def csr_sum_sq(lengths: pd.Series) -> int:
    """Sum of squared bucket lengths as a grouped aggregate; the lengths of a group are gathered, so group by bin."""
    return int((lengths.astype("int64") ** 2).sum())


class BucketScan:
    """For the rows of a partition, ordered by bucket: one row per bucket with its number of rows."""

    def __init__(self) -> None:
        self.bucket, self.n = None, 0

    def eval(self, row) -> Iterator[tuple]:
        if row["bucket"] != self.bucket:
            if self.n:
                yield self.bucket, self.n
            self.bucket, self.n = row["bucket"], 0
        self.n += 1

    def terminate(self) -> Iterator[tuple]:
        if self.n:
            yield self.bucket, self.n


def register(spark: SparkSession) -> None:
    """csr_bucket(k, v) and csr_bin(k, v, width) in SQL, mix32 as an Arrow function, bucket_scan as a table function."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION csr_bucket(k BIGINT, v BIGINT) RETURNS BIGINT RETURN pmod(CAST(hash(k) AS BIGINT), v)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION csr_bin(k BIGINT, v BIGINT, width BIGINT) RETURNS BIGINT RETURN CAST(floor(pmod(CAST(hash(k) AS BIGINT), v) / width) AS BIGINT)")
    spark.udf.register("mix32", mix32_arrow)
    spark.udtf.register("bucket_scan", F.udtf(BucketScan, returnType="bucket bigint, n bigint"))

"""Minwise hashing of token shingles with b-bit components."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F


def _hash(seed: int, shingle: Column) -> Column:
    """A 60-bit number from md5, the same in any SQL engine."""
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), shingle)), 1, 15), 16, 10).cast("bigint")


def signatures(docs: DataFrame, doc_id: str, text: str, k: int = 8, shingle: int = 2, bits: int | None = None) -> DataFrame:
    """(doc_id, component, value): the smallest hash of the text's distinct word shingles under each of k seeds."""
    # the words are bound once: a lambda would split the text again for every shingle
    grams = F.transform(
        F.array(F.split(F.col(text), " ")),
        lambda w: F.transform(F.sequence(F.lit(1), F.greatest(F.size(w) - shingle + 1, F.lit(1))), lambda i: F.array_join(F.slice(w, i, shingle), " ")),
    )[0]
    rows = docs.where(F.col(text).isNotNull()).select(F.col(doc_id).alias("doc_id"), F.explode(F.array_distinct(grams)).alias("g"))
    least = rows.groupBy("doc_id").agg(*[F.min(_hash(i, F.col("g"))).alias(f"h{i}") for i in range(k)])
    value = (lambda c: F.pmod(c, F.lit(1 << bits))) if bits else (lambda c: c)
    return least.select("doc_id", F.posexplode(F.array(*[value(F.col(f"h{i}")) for i in range(k)])).alias("component", "value"))


def estimate(equal: Column, k: int, bits: int | None = None) -> Column:
    """Similarity from the number of equal components; b-bit components agree by chance once in 2^b."""
    share = equal / F.lit(k)
    chance = 0.0 if bits is None else 2.0**-bits
    return F.greatest(F.lit(0.0), (share - chance) / (1 - chance))

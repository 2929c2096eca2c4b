"""Keys to buckets: hash families, bucket numbers, and the same hash in plain SQL for checks."""

from __future__ import annotations

from collections.abc import Callable, Sequence
from dataclasses import dataclass
from itertools import count

from pyspark.sql import Column, DataFrame, functions as F, types as T

#: Above this many buckets a 32-bit hash can't reach them all.
WIDE = 1 << 31

FAMILIES = ("murmur32", "xx64", "md5_60", "identity", "mix32")


@dataclass(frozen=True)
class HashSpec:
    """Which hash maps a key to a bucket; seed counts for murmur32 and xx64 only (None: the built-in start value)."""

    family: str = "murmur32"
    seed: int | None = None

    def __post_init__(self) -> None:
        if self.family not in FAMILIES:
            raise ValueError(f"unknown hash family {self.family!r}; choose one of {FAMILIES}")

    def value(self, *keys: Column) -> Column:
        lead = [] if self.seed is None else [F.lit(self.seed)]
        if self.family == "murmur32":
            return F.hash(*lead, *keys)
        if self.family == "xx64":
            return F.xxhash64(*lead, *keys)
        text = F.concat_ws("\x1f", *[k.cast("string") for k in keys])
        if self.family == "md5_60":
            return F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("bigint")
        if len(keys) > 1:
            raise ValueError(f"{self.family} takes one integer key")
        if self.family == "identity":
            return keys[0].cast("bigint")
        return mix32(keys[0])


def mix32(key: Column) -> Column:
    """A multiplicative mixer of the low 31 bits; products stay below 2^63."""
    low = F.pmod(key.cast("bigint"), F.lit(1 << 31))
    return F.pmod(low * F.lit(2654435769) + F.shiftright(low, 15), F.lit(1 << 32))


def normal_key(df: DataFrame, key: str) -> Column:
    """The key in the form that is hashed and compared: integers as BIGINT, NaN and zero unified, others as they are."""
    kind = df.schema[key].dataType
    if isinstance(kind, T.IntegralType):
        return F.col(f"`{key}`").cast("bigint")
    if isinstance(kind, (T.FloatType, T.DoubleType)):
        d = F.col(f"`{key}`").cast("double")
        return F.when(F.isnan(d), F.lit(float("nan"))).when(d == 0, F.lit(0.0)).otherwise(d)
    if isinstance(kind, T.MapType):
        raise TypeError("a map can't be a key")
    return F.col(f"`{key}`")


def bucket_of(keys: Sequence[Column], v: int, spec: HashSpec = HashSpec()) -> Column:
    if v > WIDE and spec.family in ("murmur32", "mix32"):
        raise ValueError(f"{v} buckets need a 64-bit family")
    return F.pmod(spec.value(*keys).cast("bigint"), F.lit(v).cast("bigint"))


def with_bucket(df: DataFrame, keys: str | Sequence[str], v: int, spec: HashSpec = HashSpec(), name: str = "bucket") -> DataFrame:
    """df + bucket (bigint): a narrow projection."""
    keys = [keys] if isinstance(keys, str) else list(keys)
    return df.withColumn(name, bucket_of([normal_key(df, k) for k in keys], v, spec))


# --- the same in SQL ---------------------------------------------------------------------------------------------

_names = count()


def _let(value: str, body: Callable[[str], str]) -> str:
    """Binds a value to a name inside one SQL expression."""
    name = f"q{next(_names)}"
    return f"list_transform([{value}], lambda {name}: {body(name)})[1]"


def _word(h: str, k: str) -> str:
    """Folds one 32-bit word into the state."""
    m = 4294967296
    return _let(f"({k} * 3432918353) % {m}", lambda a: _let(f"((({a} * 32768) % {m} + {a} // 131072) * 461845907) % {m}", lambda b: _let(f"xor({h}, {b})", lambda c: f"(((({c} * 8192) % {m} + {c} // 524288) * 5) + 3864292196) % {m}")))


def murmur_sql(*keys: str, seed: int | None = None) -> str:
    """A DuckDB expression equal to Spark's hash() over BIGINT expressions, as a signed BIGINT."""
    m = 4294967296
    state = "42::UBIGINT" if seed is None else f"{_literal_hash(seed)}::UBIGINT"
    for key in keys:
        low, high = f"((({key})::HUGEINT + 18446744073709551616) % {m})::UBIGINT", f"(((({key})::HUGEINT + 18446744073709551616) % 18446744073709551616) // {m})::UBIGINT"
        state = _let(_word(_word(state, low), high), lambda h: _let(f"xor({h}, 8::UBIGINT)", lambda a: _let(f"(xor({a}, {a} // 65536) * 2246822507) % {m}", lambda b: _let(f"(xor({b}, {b} // 8192) * 3266489909) % {m}", lambda c: f"xor({c}, {c} // 65536)"))))
    return _let(state, lambda h: f"(CASE WHEN {h} >= 2147483648 THEN {h}::BIGINT - {m} ELSE {h}::BIGINT END)")


def _literal_hash(seed: int) -> int:
    """Spark's hash of an INT literal, unsigned."""
    m = 1 << 32
    k = (seed % m) * 3432918353 % m
    k = ((k << 15) % m | k >> 17) * 461845907 % m
    h = 42 ^ k
    h = (((h << 13) % m | h >> 19) * 5 + 3864292196) % m ^ 4
    h = (h ^ h >> 16) * 2246822507 % m
    h = (h ^ h >> 13) * 3266489909 % m
    return h ^ h >> 16


def bucket_sql(keys: str | Sequence[str], v: str, seed: int | None = None) -> str:
    """The bucket of bucket_of() with the default family, for a scalar SQL expression v."""
    keys = [keys] if isinstance(keys, str) else keys
    return f"((({murmur_sql(*keys, seed=seed)}) % ({v}) + ({v})) % ({v}))::BIGINT"

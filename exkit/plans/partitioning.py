"""Partitioners: each adds an INT ``reduce_id`` that depends on the row's content and a seed only.

A retried task therefore sends every row where its first attempt sent it.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SPAN = 1 << 32


def prefix(hex_text: Column) -> Column:
    """The first eight hexadecimal digits as a number."""
    return F.conv(F.substring(hex_text, 1, 8), 16, 10).cast("long")


def portable_hash(*keys: Column) -> Column:
    """A hash that other engines compute alike: the first eight digits of the keys' md5."""
    return prefix(F.md5(F.concat_ws(",", *[k.cast("string") for k in keys])))


def by_hash(df: DataFrame, keys: Sequence[str], r: int, salt: int = 0, portable: bool = False) -> DataFrame:
    columns = [F.col(k) for k in keys]
    if portable:
        h = portable_hash(*columns, *([F.lit(salt)] if salt else []))
        return df.withColumn("reduce_id", (h % r).cast("int"))
    return df.withColumn("reduce_id", F.pmod(F.xxhash64(*columns, F.lit(salt)), F.lit(r)).cast("int"))


def equal_width(hex_key: Column, r: int) -> Column:
    """Range id of a uniform hexadecimal key; null goes to range 0."""
    return F.coalesce(F.floor(prefix(hex_key) * r / SPAN), F.lit(0)).cast("int")


def by_range(df: DataFrame, key: str, r: int, bounds: Sequence | None = None) -> DataFrame:
    """Ordered ranges: equal width for uniform hexadecimal keys, or by ``bounds`` (r - 1 of them, in order)."""
    if bounds is None:
        return df.withColumn("reduce_id", equal_width(F.col(key), r))
    above = [F.when(F.col(key) >= F.lit(b), 1).otherwise(0) for b in bounds]
    return df.withColumn("reduce_id", sum(above, F.lit(0)).cast("int"))


def sampled_bounds(df: DataFrame, key: str, r: int, accuracy: int = 10_000) -> list:
    """r - 1 bounds of about equal shares, from a mergeable sketch; nothing but the bounds reaches the driver."""
    if r < 2:
        return []
    shares = F.array(*[F.lit(i / r) for i in range(1, r)])
    found = df.agg(F.percentile_approx(key, shares, accuracy).alias("b")).first()["b"]
    return list(found or [])


def random_order(seed: int, epoch: int, pk: Column) -> Column:
    return F.md5(F.concat_ws("-", F.lit(seed), F.lit(epoch), pk.cast("string")))


def at_random(df: DataFrame, r: int, seed: int, epoch: int, pk: str) -> DataFrame:
    return df.withColumn("reduce_id", (prefix(random_order(seed, epoch, F.col(pk))) % r).cast("int"))


def virtual_map(df: DataFrame, pk: str, m: int) -> DataFrame:
    """A logical map task per row, for tables that come as a single split."""
    return df.withColumn("map_id", F.pmod(F.col(pk), F.lit(m)).cast("int"))

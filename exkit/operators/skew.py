"""Skew: splitting what is too large, salting, recombining."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from exkit.plans.partitioning import portable_hash
from exkit.staging import stage


def split_oversized(df: DataFrame, part_col: str, key: str, limit: float, fanout: int = 2, measure: Column | None = None, max_depth: int = 8, row_id: Column | None = None) -> DataFrame:
    """Adds ``part_path`` and ``depth``: parts over ``limit`` are split again and again by another hash of the key.

    The data is counted once, by part and key; the splitting itself works on
    that small staged table, and only keys whose part was split come back as a
    lookup. Rows move when the caller repartitions by ``part_path``. A part with
    a single key can not be split by its key; with ``row_id`` it is split by
    hashes of its rows, otherwise it stays.
    """
    part, own = F.col(part_col).cast("string"), df
    digits = F.lit("")
    if row_id is not None:
        own = own.withColumn("_row", row_id)
        digits = F.concat(*[(portable_hash(F.lit(d), F.col("_row")) % fanout).cast("string") for d in range(1, max_depth + 1)])
    own = own.withColumns({"_part": part, "_digits": digits}).drop("_row")
    counted = own.groupBy("_part", F.col(key).alias("_key"), "_digits").agg(F.sum(F.lit(1) if measure is None else measure).alias("n"))
    now = stage(counted.withColumns({"part_path": F.col("_part"), "depth": F.lit(0)}), "split")
    for d in range(1, max_depth + 1):
        heavy = now.groupBy("part_path").agg(F.sum("n").alias("t"), (F.min("_key") == F.max("_key")).alias("one_key")).where(F.col("t") > limit)
        heavy = (heavy if row_id is not None else heavy.where("NOT one_key")).select("part_path", "one_key")
        if heavy.isEmpty():
            break
        by_key = (portable_hash(F.lit(d), F.col("_key")) % fanout).cast("string")
        step = F.when(F.col("one_key"), F.substring("_digits", d, 1)).otherwise(by_key)
        split = F.col("one_key").isNotNull()
        now = now.join(heavy, "part_path", "left").withColumns({
            "depth": F.when(split, F.lit(d)).otherwise(F.col("depth")),
            "part_path": F.when(split, F.concat_ws(".", "part_path", step)).otherwise(F.col("part_path")),
        }).drop("one_key")
        now = stage(now, "split")
    moved = now.where("depth > 0").select(F.col("_part").alias("_p"), "_key", F.col("_digits").alias("_d"), "part_path", "depth")
    same = own["_part"].eqNullSafe(F.col("_p")) & own[key].eqNullSafe(F.col("_key")) & (own["_digits"] == F.col("_d"))
    out = own.join(moved, same, "left").withColumns({"part_path": F.coalesce("part_path", "_part"), "depth": F.coalesce("depth", F.lit(0))})
    return out.drop("_part", "_digits", "_p", "_key", "_d")


def split_hot_keys(df: DataFrame, key: str, row_id: Column, fanout: int = 8) -> DataFrame:
    """Adds ``split``: rows of one key dealt over ``fanout`` parts by a hash of the row."""
    return df.withColumn("split", (portable_hash(row_id) % fanout).cast("int"))


def recombine(parts: DataFrame, keys: Sequence[str], sums: Sequence[str]) -> DataFrame:
    """Second level of a split aggregation: partial sums (counts included) add up."""
    return parts.groupBy(*keys).agg(*[F.sum(c).alias(c) for c in sums])


def salted_agg(df: DataFrame, keys: Sequence[str], aggs: dict[str, Column], row_id: Column, salts: int = 8) -> DataFrame:
    """Group-by in two levels; ``aggs`` are sums or counts by output name."""
    first = split_hot_keys(df, keys[0], row_id, salts).groupBy(*keys, "split").agg(*[c.alias(n) for n, c in aggs.items()])
    return recombine(first, keys, list(aggs))


def salted_join(left: DataFrame, right: DataFrame, on: str, row_id: Column, salts: int = 8) -> DataFrame:
    """Join of a skewed left side: its rows are salted, the right side is copied once for each salt."""
    salted = left.withColumn("salt", (portable_hash(row_id) % salts).cast("int"))
    copies = right.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return salted.join(copies, [on, "salt"]).drop("salt")


def rebalance_table(df: DataFrame, keys: Sequence[str] = ()) -> DataFrame:
    """Even partitions of the advisory size; heavy keys are split by AQE."""
    return df.hint("rebalance", *[F.col(k) for k in keys])

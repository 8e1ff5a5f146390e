"""Online aggregation: answers that get better with every round, and how far they still are from the end."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from exkit.plans.partitioning import portable_hash


def rounds_by_time(df: DataFrame, ts: str, origin: str = "2024-01-01") -> DataFrame:
    """Arrival order: a round a day. Partials are biased if the data drifts."""
    return df.withColumn("round", F.datediff(F.to_date(ts), F.lit(origin).cast("date")).cast("int"))


def rounds_by_hash(df: DataFrame, pk: str, rounds: int) -> DataFrame:
    """Random order: partials are unbiased samples."""
    return df.withColumn("round", (portable_hash(F.col(pk)) % rounds).cast("int"))


def aggregate(df: DataFrame, keys: Sequence[str], sums: dict[str, Column], round_col: str = "round") -> DataFrame:
    """Every round's running answer: one row per key and round from the key's first round on.

    Rows are aggregated by round and key first, so the running sum sees as many
    rows as there are rounds and keys, whatever the input's size.
    """
    part = df.groupBy(round_col, *keys).agg(*[c.alias(n) for n, c in sums.items()])
    span = part.groupBy(*keys).agg(F.min(round_col).alias("lo"))
    rounds = part.select(round_col).distinct()
    grid = span.join(F.broadcast(rounds), rounds[round_col] >= F.col("lo")).drop("lo")
    so_far = W.partitionBy(*keys).orderBy(round_col).rowsBetween(W.unboundedPreceding, 0)
    full = grid.join(part, [round_col, *keys], "left")
    return full.select(round_col, *keys, *[F.sum(F.coalesce(F.col(n), F.lit(0))).over(so_far).alias(n) for n in sums])


def top_by(running: DataFrame, group: Sequence[str], item: str, weight: str, k: int) -> DataFrame:
    """The k heaviest items of each group; equal weights in the order of the item."""
    rank = F.row_number().over(W.partitionBy(*group).orderBy(F.desc(weight), F.asc(item)))
    return running.withColumn("rnk", rank).where(F.col("rnk") <= k)


def scale(partials: DataFrame, sums: Sequence[str], done: Column) -> DataFrame:
    """Partial totals over the share of the input they stand for."""
    return partials.withColumns({n: F.col(n) / done for n in sums})


def stream(events: DataFrame, keys: Sequence[str], sums: dict[str, Column]) -> DataFrame:
    """The unbounded form: run with output mode ``complete`` or ``update``."""
    return events.groupBy(*keys).agg(*[c.alias(n) for n, c in sums.items()])

"""Connected components by alternating star contractions; edges and labels stay distributed."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from exkit.staging import stage


def _print(edges: DataFrame) -> tuple:
    r = edges.agg(F.count(F.lit(1)).alias("n"), F.sum(F.shiftright(F.xxhash64("u", "v"), 16)).alias("s")).first()
    return r["n"], r["s"]


def components(edges: DataFrame) -> DataFrame:
    """(id, component) for every id in ``edges`` (u, v): component is the least id it is connected to.

    Each round points every node at the least id in its neighbourhood, first
    towards greater neighbours, then towards smaller ones; it ends when the edge
    set no longer changes, which takes rounds in the logarithm of the size. Each
    round is a written table, so a lost executor repeats one round at most.
    """
    e = stage(edges.where("u <> v").select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct(), "cc")
    before = _print(e)
    while before[0]:
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("m").alias("u"), "v").where("u <> v").distinct()
        large = stage(large, "cc")
        low = large.groupBy("v").agg(F.min("u").alias("m"))
        small = large.join(low, "v").select(F.col("m").alias("u"), F.explode(F.array("u", "v")).alias("v")).where("u <> v").distinct()
        e = stage(small, "cc")
        now = _print(e)
        if now == before:
            break
        before = now
    return e.select(F.col("v").alias("id"), F.col("u").alias("component")).unionByName(e.select("u").distinct().select(F.col("u").alias("id"), F.col("u").alias("component")))

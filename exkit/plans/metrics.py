"""Measures: blocks, bytes, skew, divergence of partial answers, mixing of an order, lines of code."""

from __future__ import annotations

import json
from collections.abc import Iterable
from pathlib import Path

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def row_bytes(df: DataFrame) -> Column:
    """Bytes of a row by formula: 8 for a number or time, the UTF-8 length for a string."""
    size = F.lit(0).cast("long")
    for f in df.schema:
        size = size + (F.coalesce(F.octet_length(f.name), F.lit(0)).cast("long") if f.dataType.typeName() == "string" else F.lit(8).cast("long"))
    return size


def ledger(df: DataFrame, stage: str, src: str, dst: str, round_col: str | None = None, size: Column | None = None) -> DataFrame:
    """One row per block: stage, round, src, dst, n_rows, n_bytes."""
    by = [(F.col(round_col) if round_col else F.lit(0)).cast("int").alias("round"), F.col(src).cast("int").alias("src"), F.col(dst).cast("int").alias("dst")]
    held = df.select(*by, (row_bytes(df) if size is None else size).alias("b"))
    out = held.groupBy("round", "src", "dst").agg(F.count(F.lit(1)).alias("n_rows"), F.sum("b").alias("n_bytes"))
    return out.select(F.lit(stage).alias("stage"), "round", "src", "dst", "n_rows", "n_bytes")


def ledger_summary(blocks: DataFrame) -> DataFrame:
    return blocks.groupBy("stage").agg(F.count(F.lit(1)).alias("n_blocks"), F.round(F.avg("n_rows"), 6).alias("avg_rows"), F.max("n_rows").alias("max_rows"), F.sum("n_bytes").alias("n_bytes"))


def skew_report(df: DataFrame, part_col: str, limit: int | None = None) -> DataFrame:
    sizes = df.groupBy(part_col).agg(F.count(F.lit(1)).alias("n"))
    over = F.sum((F.col("n") > limit).cast("long")) if limit is not None else F.lit(0).cast("long")
    return sizes.agg(
        F.count(F.lit(1)).alias("parts"), F.max("n").alias("max_rows"), F.round(F.avg("n"), 6).alias("mean_rows"),
        F.round(F.max("n") / F.avg("n"), 6).alias("ratio"), F.round(F.stddev_pop("n") / F.avg("n"), 6).alias("cv"), over.alias("over_limit"),
    )


def kl(final: DataFrame, partial: DataFrame, keys: list[str], value: str, by: list[str], alpha: float = 0.0) -> DataFrame:
    """Divergence of partial shares from final ones for each group ``by`` of ``partial``: by..., kl, unseen.

    A final key that the partial answer has not seen makes it infinite, unless
    ``alpha`` is added to every partial value.
    """
    final = final.select(*keys, F.col(value).cast("double").alias("f")).where("f > 0")
    total = final.agg(F.sum("f").alias("ft"), F.count(F.lit(1)).alias("fk"))
    groups = partial.select(*by).distinct()
    want = groups.join(F.broadcast(total)).join(final)
    have = partial.select(*by, *keys, F.col(value).cast("double").alias("v"))
    both = want.join(have, [*by, *keys], "left").withColumn("v", F.coalesce("v", F.lit(0.0)) + alpha)
    sums = both.groupBy(*by).agg(F.sum("v").alias("vt"))
    rows = both.join(sums, by)
    p, q = F.col("f") / F.col("ft"), F.col("v") / F.col("vt")
    term = F.when(F.col("v") > 0, p * F.log(p / q))
    unseen = F.sum((F.col("v") <= 0).cast("long"))
    out = rows.groupBy(*by).agg(F.sum(term).alias("s"), unseen.alias("unseen"))
    return out.select(*by, F.when(F.col("unseen") > 0, F.lit(float("inf"))).otherwise(F.round("s", 6)).alias("kl"), "unseen")


def first_round_below(divergence: DataFrame, eps: float = 0.08, round_col: str = "round") -> DataFrame:
    return divergence.where(F.col("kl") <= eps).agg(F.min(round_col).alias(round_col))


def mixing(df: DataFrame, orig: str, new: str, label: str) -> DataFrame:
    """How far an order was mixed: mean displacement over n, share of neighbours kept, runs of equal labels.

    Neighbours are found by joining positions, so no task sees the whole order.
    """
    pos = df.select(F.col(orig).alias("o"), F.col(new).alias("p"), F.col(label).alias("l"))
    nxt = pos.select(F.col("p").alias("p"), F.col("o").alias("o2"), F.col("l").alias("l2")).withColumn("p", F.col("p") - 1)
    both = pos.join(nxt, "p", "left")
    n = F.count(F.lit(1))
    return both.agg(
        F.round(F.avg(F.abs(F.col("o") - F.col("p"))) / n, 6).alias("displacement"),
        F.round(F.sum((F.col("o2") == F.col("o") + 1).cast("int")) / n, 6).alias("adjacent_kept"),
        (F.sum((F.col("l2") != F.col("l")).cast("long")) + 1).alias("label_runs"),
    )


def batch_entropy(df: DataFrame, batch: str, label: str) -> DataFrame:
    """Mean entropy (nats) of labels inside batches."""
    n = df.groupBy(batch, label).agg(F.count(F.lit(1)).alias("n")).withColumn("t", F.sum("n").over(W.partitionBy(batch)))
    share = F.col("n") / F.col("t")
    return n.groupBy(batch).agg(-F.sum(share * F.log(share)).cast("double").alias("h")).agg(F.round(F.avg("h"), 6).alias("entropy"))


def event_totals(paths: Iterable[Path]) -> dict[str, float]:
    """Shuffle, spill and output bytes of finished tasks in uncompressed event logs."""
    out = {"shuffle_written": 0, "shuffle_read": 0, "disk_spill": 0, "memory_spill": 0, "written": 0, "tasks": 0, "failed": 0}
    for path in paths:
        for line in path.open():
            if '"SparkListenerTaskEnd"' not in line:
                continue
            e = json.loads(line)
            m = e.get("Task Metrics") or {}
            read = m.get("Shuffle Read Metrics", {})
            out["shuffle_written"] += m.get("Shuffle Write Metrics", {}).get("Shuffle Bytes Written", 0)
            out["shuffle_read"] += read.get("Remote Bytes Read", 0) + read.get("Local Bytes Read", 0)
            out["disk_spill"] += m.get("Disk Bytes Spilled", 0)
            out["memory_spill"] += m.get("Memory Bytes Spilled", 0)
            out["written"] += m.get("Output Metrics", {}).get("Bytes Written", 0)
            out["tasks"] += 1
            out["failed"] += e["Task End Reason"]["Reason"] != "Success"
    return out


def write_amplification(totals: dict[str, float], input_bytes: float) -> float:
    return (totals["shuffle_written"] + totals["disk_spill"] + totals["written"]) / input_bytes


def progress(spark) -> list[dict]:
    """Share of finished tasks of each active stage, now."""
    tracker = spark.sparkContext.statusTracker()
    infos = [tracker.getStageInfo(s) for s in tracker.getActiveStageIds()]
    return [{"stage": i.stageId, "name": i.name, "done": i.numCompletedTasks / max(1, i.numTasks)} for i in infos if i]


def loc_of(text: str) -> int:
    """Lines that hold code: no blank lines, no comments, no docstring lines."""
    n, inside = 0, False
    for line in text.splitlines():
        s = line.strip()
        marks = s.count('"""')
        if inside or s.startswith('"""'):
            inside = inside != (marks % 2 == 1)
            continue
        n += bool(s) and not s.startswith("#")
    return n


def loc(*paths: str) -> int:
    return sum(loc_of(Path(p).read_text()) for p in paths)

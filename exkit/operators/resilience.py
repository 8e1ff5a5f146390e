"""Stragglers and failures: duplicates of late jobs, merges with a deadline, repair of lost rounds."""

from __future__ import annotations

from collections.abc import Callable, Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from exkit.plans import control
from exkit.plans.spec import ShuffleSpec
from exkit.strategies.push import merged_at_worker


def suspects(durations: DataFrame, value: str, multiplier: float = 1.5) -> DataFrame:
    """Rows whose duration passes ``multiplier`` times the exact median, with that threshold."""
    limit = durations.agg((F.percentile(value, F.lit(0.5)) * multiplier).alias("threshold"))
    return durations.join(F.broadcast(limit)).where(F.col(value) > F.col("threshold"))


def first_of(spark: SparkSession, make: Callable[[int], object], patience_s: float, copies: int = 2):
    """Result of the first of up to ``copies`` attempts; another starts when patience ends, losers are cancelled.

    Attempts must be idempotent: each gets its number and writes, if at all, to a place of its own.
    """
    running: list[control.FrameFuture] = []
    for i in range(copies):
        running.append(control.submit(spark, lambda i=i: make(i)))
        done, _ = control.wait(running, k=1, timeout=patience_s if i + 1 < copies else None)
        if done:
            break
    done, pending = control.wait(running, k=1)
    for f in pending:
        control.cancel(spark, f)
    return done[0].result()


def best_effort_merge(df: DataFrame, spec: ShuffleSpec, late: Column | None = None, timeout_s: float | None = None) -> tuple[DataFrame, DataFrame]:
    """(merged, raw): rounds merged in time, and un-merged map output of the others, which goes straight to the reducers.

    ``late`` names late rows by their round (deterministic form). With
    ``timeout_s`` each round's merge is a tagged job; what is not done in time is cancelled.
    """
    mapped = spec.mapped(df).withColumn("round", F.floor(F.col(spec.map_col) / spec.round_maps).cast("int"))
    if timeout_s is not None:
        spark, jobs = df.sparkSession, {}
        for i in range(-(-spec.m // spec.round_maps)):
            own = control.retain(merged_at_worker(mapped.where(F.col("round") == i), spec, spec.workers))
            jobs[i] = control.submit(spark, own.count)
        _, pending = control.wait(jobs.values(), k=len(jobs), timeout=timeout_s)
        for f in pending:
            control.cancel(spark, f)
        late = F.col("round").isin([i for i, f in jobs.items() if f in pending])
    late = F.lit(False) if late is None else late
    return merged_at_worker(mapped.where(~late), spec, spec.workers), mapped.where(late)


def reduce_best_effort(merged: DataFrame, raw: DataFrame, spec: ShuffleSpec) -> DataFrame:
    raw = spec.merge_fn(raw) if spec.merge_fn else raw
    both = merged.unionByName(raw, allowMissingColumns=True)
    both = spec.merge_fn(both) if spec.merge_fn else both
    return spec.reduced(both.repartitionById(spec.r, "reduce_id"))


def missing_rounds(manifest: DataFrame, rounds: int) -> list[int]:
    """Rounds without a committed block; only their maps run again."""
    have = {r["round"] for r in manifest.select("round").distinct().collect()}
    return [i for i in range(rounds) if i not in have]


def flaky(df: DataFrame, partition: int = 0) -> DataFrame:
    """Fails the first attempt of one task; for tests on masters that retry tasks."""

    def run(batches):
        from pyspark import TaskContext

        t = TaskContext.get()
        if t.partitionId() == partition and t.attemptNumber() == 0:
            raise RuntimeError("injected failure")
        yield from batches

    return df.mapInArrow(run, df.schema)


def retried(spark: SparkSession, attempts: Sequence[Callable[[], object]]):
    """Run the callables until one does not raise; the last error is raised if all do."""
    error: Exception | None = None
    for a in attempts:
        try:
            return a()
        except Exception as e:  # the next attempt is the remedy
            error = e
    raise error or ValueError("no attempts")

"""Control plane: jobs as futures over Spark's scheduler.

A future holds a lazy DataFrame and, once submitted, the job that materialises
it in a thread of its own under a job tag. The tag is what cancels it.
"""

from __future__ import annotations

import threading
import uuid
from collections.abc import Callable, Iterable, Iterator
from concurrent.futures import FIRST_COMPLETED, CancelledError, Future
from concurrent.futures import wait as futures_wait
from dataclasses import dataclass, field
from time import monotonic

from pyspark import InheritableThread, StorageLevel
from pyspark.sql import DataFrame, SparkSession


@dataclass(eq=False)
class FrameFuture:
    """A DataFrame that may still be computing; passing it on never moves its rows to the driver."""

    df: DataFrame | None
    job: Future | None = None
    tag: str = ""
    cancelled: bool = field(default=False)

    def then(self, fn: Callable[[DataFrame], DataFrame]) -> FrameFuture:
        """Dependent work: runs after this job if there is one, else joins the same plan."""
        if self.job is None or self.df is not None:
            return FrameFuture(fn(self.df))
        out: Future = Future()

        def done(f: Future) -> None:
            try:
                out.set_result(fn(f.result()))
            except BaseException as e:
                out.set_exception(e)

        self.job.add_done_callback(done)
        return FrameFuture(None, out, self.tag)

    def result(self, timeout: float | None = None):
        return self.df if self.job is None else self.job.result(timeout)


def submit(spark: SparkSession, thunk: Callable[[], object], pool: str | None = None, tag: str | None = None) -> FrameFuture:
    """Start ``thunk`` (which runs Spark actions) without waiting for it."""
    sc, name, out = spark.sparkContext, tag or f"exkit-{uuid.uuid4().hex}", Future()
    ff = FrameFuture(None, out, name)

    def work() -> None:
        out.set_running_or_notify_cancel()
        try:
            sc.addJobTag(name)
            if pool:
                sc.setLocalProperty("spark.scheduler.pool", pool)
            out.set_result(thunk())
        except BaseException as e:
            out.set_exception(CancelledError() if ff.cancelled else e)
        finally:
            sc.removeJobTag(name)

    InheritableThread(target=work, daemon=True).start()
    return ff


def fetch(ff: FrameFuture, as_: str = "arrow"):
    """Bring a value to the caller: ``arrow``, ``rows`` or a prefetching row iterator ``iter``."""
    df = ff.result()
    if as_ == "arrow":
        return df.toArrow()
    return df.collect() if as_ == "rows" else df.toLocalIterator(prefetchPartitions=True)


def wait(ffs: Iterable[FrameFuture], k: int = 1, timeout: float | None = None) -> tuple[list[FrameFuture], list[FrameFuture]]:
    """Block until ``k`` of the futures are done or time is up; fetches nothing."""
    ffs, end = list(ffs), None if timeout is None else monotonic() + timeout
    while True:
        done = [f for f in ffs if f.job is None or f.job.done()]
        pending = [f for f in ffs if f not in done]
        left = None if end is None else end - monotonic()
        if len(done) >= min(k, len(ffs)) or not pending or (left is not None and left <= 0):
            return done, pending
        futures_wait([f.job for f in pending], timeout=left, return_when=FIRST_COMPLETED)


def cancel(spark: SparkSession, ff: FrameFuture) -> bool:
    if ff.job is None or ff.job.done():
        return False
    ff.cancelled = True
    spark.sparkContext.cancelJobsWithTag(ff.tag)
    return True


LEVELS = {"disk": StorageLevel.DISK_ONLY, "disk_2": StorageLevel.DISK_ONLY_2, "memory_disk": StorageLevel.MEMORY_AND_DISK, "memory": StorageLevel.MEMORY_ONLY}


def retain(df: DataFrame, level: str = "disk") -> DataFrame:
    """Keep a value's blocks while it is referenced; ``disk_2`` keeps two copies."""
    return df.persist(LEVELS[level])


def release(df: DataFrame) -> None:
    df.unpersist()


class Limiter:
    """At most ``n`` jobs at once."""

    def __init__(self, n: int):
        self._slots = threading.BoundedSemaphore(n)

    def run(self, thunk: Callable[[], object]):
        with self._slots:
            return thunk()


class Rounds:
    """Pipelined rounds: while round i is merged, round i + 1 is mapped; at most ``max_inflight`` merges are out."""

    def __init__(self, spark: SparkSession, max_inflight: int = 1):
        self.spark, self.max_inflight = spark, max_inflight

    def run(self, rounds: Iterable, map_fn: Callable, merge_fn: Callable) -> list:
        out: list[FrameFuture] = []
        for item in rounds:
            mapped = map_fn(item)
            pending = [f for f in out if not f.job.done()]
            if len(pending) >= self.max_inflight:
                wait(pending, k=len(pending) - self.max_inflight + 1)
            out.append(submit(self.spark, lambda item=item, mapped=mapped: merge_fn(item, mapped), pool="merge"))
        wait(out, k=len(out))
        return [f.result() for f in out]


def loop(step: Callable, until: Callable[[object], bool], most: int = 100) -> Iterator:
    """Grow the work at run time: ``step`` gets its own last result."""
    state = None
    for _ in range(most):
        state = step(state)
        yield state
        if until(state):
            return

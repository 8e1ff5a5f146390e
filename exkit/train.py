"""Training fed by a shuffle: the trainer takes reduce partitions as they come."""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field
from time import perf_counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from exkit.operators import randomize
from exkit.plans import control


class SoftmaxSGD:
    """Multinomial logistic regression by mini-batch gradient steps; sensitive to the order of rows, as it should be."""

    def __init__(self, dims: int, classes: int, rate: float = 0.1, batch: int = 32):
        self.w, self.rate, self.batch = np.zeros((dims + 1, classes)), rate, batch

    @staticmethod
    def _wide(x: np.ndarray) -> np.ndarray:
        return np.hstack([x, np.ones((len(x), 1))])

    def partial_fit(self, x: np.ndarray, y: np.ndarray) -> SoftmaxSGD:
        x = self._wide(x)
        for i in range(0, len(x), self.batch):
            xb, yb = x[i : i + self.batch], y[i : i + self.batch]
            z = xb @ self.w
            p = np.exp(z - z.max(1, keepdims=True))
            p /= p.sum(1, keepdims=True)
            p[np.arange(len(yb)), yb] -= 1
            self.w -= self.rate * xb.T @ p / len(xb)
        return self

    def accuracy(self, x: np.ndarray, y: np.ndarray) -> float:
        return float(((self._wide(x) @ self.w).argmax(1) == y).mean()) if len(y) else 0.0


@dataclass
class History:
    seconds: list[float] = field(default_factory=list)
    accuracy: list[float] = field(default_factory=list)
    peak_rows: int = 0


def _chunks(df: DataFrame, rows: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Features and labels, a partition ahead of the trainer at most."""
    x, y = [], []
    for r in df.select("features", "y").toLocalIterator(prefetchPartitions=True):
        x.append(r[0]), y.append(r[1])
        if len(x) == rows:
            yield np.array(x), np.array(y)
            x, y = [], []
    if x:
        yield np.array(x), np.array(y)


def epoch_frame(df: DataFrame, pk: str, mode: str, seed: int, epoch: int, r: int = 8, window_rows: int = 180, ordinal: str = "ordinal", buffer_rows: int = 180) -> DataFrame:
    """The rows of one epoch in the order that ``mode`` gives them."""
    if mode == "full":
        return randomize.full(df, pk, seed, epoch, r)
    if mode == "windowed":
        return randomize.windowed(df, pk, seed, epoch, ordinal, window_rows).repartitionByRange(r, "window").sortWithinPartitions("window", "pos")
    if mode == "partial":
        return randomize.within_partition(df.repartitionByRange(r, ordinal).sortWithinPartitions(ordinal), pk, seed, epoch)
    if mode == "buffered":
        return randomize.buffered(df.repartitionByRange(r, ordinal).sortWithinPartitions(ordinal), seed, epoch, buffer_rows)
    if mode == "none":
        return df.repartitionByRange(r, ordinal).sortWithinPartitions(ordinal)
    raise ValueError(mode)


def fit(df: DataFrame, test: tuple[np.ndarray, np.ndarray], pk: str, mode: str = "full", epochs: int = 20, seed: int = 1, pipelined: bool = True, rows: int = 512, **how) -> tuple[SoftmaxSGD, History]:
    """Train on ``df`` (features, y, ordinal). Pipelined: epoch e + 1 is shuffled while epoch e trains, partition by partition.

    Not pipelined, the whole shuffled epoch is materialised before training
    starts: the blocking baseline, which holds a copy of the data.
    """
    dims, classes = len(test[0][0]), int(max(test[1])) + 1
    model, history, spark = SoftmaxSGD(dims, classes), History(), df.sparkSession
    make = lambda e: control.retain(epoch_frame(df, pk, mode, seed, e, **how))
    def begin(e: int):
        frame = make(e)
        return frame, control.submit(spark, frame.count)

    ahead = begin(0)
    for e in range(epochs):
        start = perf_counter()
        frame, job = ahead
        if not pipelined:
            job.result()
        if e + 1 < epochs and pipelined:
            job.result()
            ahead = begin(e + 1)
        for x, y in _chunks(frame, rows):
            history.peak_rows = max(history.peak_rows, len(x))
            model.partial_fit(x, y)
        control.release(frame)
        if e + 1 < epochs and not pipelined:
            ahead = begin(e + 1)
        history.seconds.append(perf_counter() - start)
        history.accuracy.append(model.accuracy(*test))
    return model, history


def distributed_epoch(df: DataFrame, model: SoftmaxSGD, workers: int, order: str) -> SoftmaxSGD:
    """Each worker trains a replica on its partition in ``order``; replicas are averaged. One weight row a worker reaches the driver."""
    w, rate, batch = model.w, model.rate, model.batch

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, n = SoftmaxSGD(w.shape[0] - 1, w.shape[1], rate, batch), 0
        own.w = w.copy()
        for b in batches:
            if b.num_rows:
                own.partial_fit(np.array(b.column(0).to_pylist()), np.array(b.column(1).to_pylist()))
                n += b.num_rows
        if n:
            yield pa.RecordBatch.from_arrays([pa.array([n]), pa.array([own.w.reshape(-1).tolist()])], names=["n", "w"])

    rows = df.repartitionById(workers, "part").sortWithinPartitions(order).select("features", "y").mapInArrow(run, "n long, w array<double>").collect()
    total = sum(r["n"] for r in rows)
    out = SoftmaxSGD(w.shape[0] - 1, w.shape[1], rate, batch)
    out.w = sum(np.array(r["w"]).reshape(w.shape) * (r["n"] / total) for r in rows)
    return out


def fit_distributed(df: DataFrame, test: tuple[np.ndarray, np.ndarray], pk: str, mode: str, workers: int = 4, epochs: int = 20, seed: int = 1) -> History:
    """Data-parallel training. ``full``: rows are dealt anew to workers each epoch; ``partial``: they stay, only their order changes."""
    from exkit.plans.partitioning import portable_hash, random_order

    dims, classes = len(test[0][0]), int(max(test[1])) + 1
    model, history = SoftmaxSGD(dims, classes), History()
    n = df.count()
    for e in range(epochs):
        start = perf_counter()
        part = portable_hash(F.lit(seed), F.lit(e), F.col(pk)) % workers if mode == "full" else F.floor(F.col("ordinal") * workers / max(1, n))
        dealt = df.withColumn("part", part.cast("int")).withColumn("_k", random_order(seed, e, F.col(pk)))
        model = distributed_epoch(dealt, model, workers, "_k")
        history.seconds.append(perf_counter() - start)
        history.accuracy.append(model.accuracy(*test))
    return history


def to_arrays(rows: Iterable) -> tuple[np.ndarray, np.ndarray]:
    x, y = zip(*[(r["features"], r["y"]) for r in rows], strict=True)
    return np.array(x), np.array(y)

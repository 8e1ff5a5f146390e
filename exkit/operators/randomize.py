"""Random shuffles for training, from a permutation of everything to none beyond a buffer."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from exkit.plans.partitioning import at_random, prefix, random_order


def numbered(df: DataFrame, order: list[str], buckets_of: str, name: str) -> DataFrame:
    """A global ordinal without a single-task sort: ``buckets_of`` is a column whose order agrees with ``order``.

    Ordinals are the rows of the buckets before plus the rank inside the bucket.
    """
    sizes = df.groupBy(buckets_of).agg(F.count(F.lit(1)).alias("_n"))
    before = sizes.withColumn("_before", F.coalesce(F.sum("_n").over(W.orderBy(buckets_of).rowsBetween(W.unboundedPreceding, -1)), F.lit(0))).drop("_n")
    inside = F.row_number().over(W.partitionBy(buckets_of).orderBy(*order))
    return df.withColumn("_i", inside).join(before, buckets_of).withColumn(name, (F.col("_before") + F.col("_i") - 1).cast("long")).drop("_i", "_before")


def full(df: DataFrame, pk: str, seed: int, epoch: int, r: int = 8) -> DataFrame:
    """A fresh uniform permutation of all rows, as reduce partitions to be consumed one at a time."""
    keyed = at_random(df, r, seed, epoch, pk).withColumn("_k", random_order(seed, epoch, F.col(pk)))
    return keyed.repartitionById(r, "reduce_id").sortWithinPartitions("reduce_id", "_k", pk).drop("_k")


def full_positions(df: DataFrame, pk: str, seed: int, epoch: int, buckets: int = 256) -> DataFrame:
    """The permutation with its positions: ``pos`` from 0."""
    k = random_order(seed, epoch, F.col(pk))
    keyed = df.withColumn("_k", k).withColumn("_b", F.floor(prefix(F.col("_k")) * buckets / (1 << 32)).cast("int"))
    return numbered(keyed, ["_k", pk], "_b", "pos").drop("_k", "_b")


def windowed(df: DataFrame, pk: str, seed: int, epoch: int, ordinal: str, window_rows: int) -> DataFrame:
    """Permutes inside consecutive windows of ``window_rows`` rows of the stored order; no row leaves its window."""
    w = F.floor(F.col(ordinal) / window_rows).cast("int")
    keyed = df.withColumn("window", w).withColumn("_k", random_order(seed, epoch, F.col(pk)))
    inside = F.row_number().over(W.partitionBy("window").orderBy("_k", pk)) - 1
    return keyed.withColumn("pos", (F.col("window").cast("long") * window_rows + inside).cast("long")).drop("_k")


def within_partition(df: DataFrame, pk: str, seed: int, epoch: int) -> DataFrame:
    """Permutes inside each input partition as it was loaded: no exchange."""
    return df.withColumn("_k", random_order(seed, epoch, F.col(pk))).sortWithinPartitions("_k", pk).drop("_k")


def buffered(df: DataFrame, seed: int, epoch: int, buffer_rows: int) -> DataFrame:
    """A loader's bounded buffer: each row that comes out is drawn from a full buffer, and the next row takes its place."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rng, held = np.random.default_rng([seed, epoch]), None
        for b in batches:
            held = pa.Table.from_batches([b]) if held is None else pa.concat_tables([held, pa.Table.from_batches([b])])
            if held.num_rows > buffer_rows:
                # a drawn row can come only from the rows that were in the buffer when it was drawn
                order, pool, nxt = [], list(range(buffer_rows)), buffer_rows
                while nxt < held.num_rows:
                    i = int(rng.integers(0, len(pool)))
                    order.append(pool[i])
                    pool[i], nxt = nxt, nxt + 1
                yield from held.take(order).combine_chunks().to_batches()
                held = held.take(pool)
        if held is not None and held.num_rows:
            yield from held.take(rng.permutation(held.num_rows)).combine_chunks().to_batches()

    return df.mapInArrow(run, df.schema)

"""Merging before the transfer: the outputs of F neighbouring maps become one set of R blocks.

Without a merge function, F input partitions are read by one task (``coalesce``
moves no rows), which writes R blocks instead of F x R. With one, rows of equal
(merge_id, reduce_id) are combined below the exchange; map outputs of a merge
group share a task, so the combiner needs no exchange of its own beyond Spark's
partial aggregation.
"""

from __future__ import annotations

from pyspark.sql import DataFrame

from exkit.plans.spec import ShuffleSpec


def premerge(df: DataFrame, spec: ShuffleSpec, f: int | None = None) -> DataFrame:
    f = f or spec.merge_factor
    groups = max(1, -(-spec.m // f))
    mapped = spec.mapped(df).coalesce(groups)
    if spec.merge_fn:
        mapped = spec.merge_fn(mapped)
    return spec.reduced(mapped.repartitionById(spec.r, "reduce_id"))

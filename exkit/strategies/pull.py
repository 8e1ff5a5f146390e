"""Plain shuffle: every reducer fetches its block of every map output. One exchange, M x R blocks."""

from __future__ import annotations

from pyspark.sql import DataFrame

from exkit.plans.spec import ShuffleSpec


def pull(df: DataFrame, spec: ShuffleSpec) -> DataFrame:
    return spec.reduced(spec.mapped(df).repartitionById(spec.r, "reduce_id"))

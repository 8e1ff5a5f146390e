"""Shuffle strategies: the same map, merge and reduce functions, carried out in different ways.

For one spec every strategy returns the same rows with the same ``reduce_id``;
blocks, disk traffic, time and durability differ.
"""

from __future__ import annotations

from pyspark.sql import DataFrame

from exkit.plans.spec import ShuffleSpec
from exkit.strategies.premerge import premerge
from exkit.strategies.pull import pull
from exkit.strategies.push import push, push_inline
from exkit.strategies.stream_rounds import stream_rounds

STRATEGIES = ("pull", "premerge", "push_durable", "push_lean", "push_inline", "stream_rounds")


def shuffle(df: DataFrame, spec: ShuffleSpec) -> DataFrame:
    """Run ``spec`` by the strategy it names."""
    if spec.strategy == "pull":
        return pull(df, spec)
    if spec.strategy == "premerge":
        return premerge(df, spec)
    if spec.strategy == "push_inline":
        return push_inline(df, spec)
    if spec.strategy in ("push_durable", "push_lean"):
        return push(df, spec.with_(keep_map_output=spec.strategy == "push_durable"))
    if spec.strategy == "stream_rounds":
        return stream_rounds(df, spec)
    raise ValueError(f"unknown strategy {spec.strategy!r}; one of {', '.join(STRATEGIES)}")


__all__ = ["STRATEGIES", "premerge", "pull", "push", "push_inline", "shuffle", "stream_rounds"]

"""Push shuffle in two levels: map outputs go to the worker that owns their reducers, are merged there, then reduced.

``push_inline`` is one lazy plan. ``push`` works in rounds: while the merge of
one round writes its blocks, the maps of the next one run (where the input of a
round can be read by itself, see ``rounds``; else all is mapped in one job, and
the merges follow). Each input row is read once. Merged blocks are on
shared storage; the un-merged map output is kept until the end
(``keep_map_output``, doubles the intermediate bytes and survives a lost merge)
or dropped with its round (a lost merge re-runs that round's maps only).
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from exkit.plans import control
from exkit.plans.planner import push_layout
from exkit.plans.spec import ShuffleSpec
from exkit.sources.blocks import Block, read_blocks, write_blocks
from exkit.staging import bytes_of, new_path
from exkit.strategies.rounds import MapRounds


def _to_worker(df: DataFrame, workers: int, r: int) -> DataFrame:
    return df.withColumn("worker", F.expr(f"cast(reduce_id * {workers} div {r} as int)"))


def merged_at_worker(mapped: DataFrame, spec: ShuffleSpec, workers: int) -> DataFrame:
    """Rows at the worker of their reducer, combined or in reducer and key order there."""
    at = _to_worker(mapped, workers, spec.r).repartitionById(workers, "worker")
    at = spec.merge_fn(at) if spec.merge_fn else at.sortWithinPartitions("reduce_id", *spec.sort_keys)
    return at.drop("worker")


def push_inline(df: DataFrame, spec: ShuffleSpec) -> DataFrame:
    layout = push_layout(spec.m, spec.r, spec.workers, spec.round_maps)
    merged = merged_at_worker(spec.mapped(df), spec, layout.workers)
    return spec.reduced(merged.repartitionById(spec.r, "reduce_id"))


def push(df: DataFrame, spec: ShuffleSpec, on_round=None, on_event=None, ledger: dict | None = None) -> DataFrame:
    """``on_round(i)`` is called when a round is merged, ``on_event(what, i)`` at each start and end of a map and merge.

    ``ledger`` gets what was written: the manifest under ``blocks``, and the
    bytes of map output and blocks on storage when the last round is merged.
    """
    spark, layout = df.sparkSession, push_layout(spec.m, spec.r, spec.workers, spec.round_maps)
    root, maps = new_path(spark, "blocks"), MapRounds(df, spec, layout.rounds)
    tell = on_event or (lambda what, i: None)

    def map_round(i: int) -> DataFrame:
        tell("map", i)
        own = maps(i)
        tell("mapped", i)
        return own

    def merge_round(i: int, own: DataFrame) -> list[Block]:
        tell("merge", i)
        done = write_blocks(merged_at_worker(own, spec, layout.workers), root, i)
        if not spec.keep_map_output:
            maps.drop(i)
        if on_round:
            on_round(i)
        tell("merged", i)
        return done

    manifests = control.Rounds(spark).run(range(layout.rounds), map_round, merge_round)
    blocks = [b for m in manifests for b in m]
    if ledger is not None:
        ledger |= {"blocks": blocks, "map_bytes": bytes_of(spark, maps.root), "block_bytes": bytes_of(spark, root)}
    maps.drop()
    # a reduce partition is one task of the reader; the sort merges its rounds' runs
    return spec.reduced(read_blocks(spark, blocks, merged_at_worker(maps.mapped, spec, layout.workers).schema))

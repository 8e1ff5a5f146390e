"""What a shuffle is asked to do, whatever strategy carries it out."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame

Step = Callable[[DataFrame], DataFrame]


@dataclass(frozen=True)
class ShuffleSpec:
    """``partition`` adds ``reduce_id``; the other functions map row sets to row sets.

    ``merge_fn`` combines rows of equal reduce_id before they travel further and
    must be associative and commutative; ``sort_keys`` order a reduce partition.
    ``map_col`` names the logical map task where rounds and merges need it.
    ``round_input`` gives the input of a round, where it can be read by itself.
    """

    r: int
    partition: Step
    m: int = 16
    map_fn: Step | None = None
    merge_fn: Step | None = None
    reduce_fn: Step | None = None
    sort_keys: tuple[str, ...] = ()
    map_col: str = "map_id"
    strategy: str = "pull"
    merge_factor: int = 4
    workers: int = 4
    round_maps: int = 4
    keep_map_output: bool = False
    round_input: Callable[[int], DataFrame] | None = None

    def with_(self, **changes) -> ShuffleSpec:
        return replace(self, **changes)

    def mapped(self, df: DataFrame) -> DataFrame:
        return self.partition(self.map_fn(df) if self.map_fn else df)

    def reduced(self, df: DataFrame) -> DataFrame:
        if self.sort_keys:
            df = df.sortWithinPartitions("reduce_id", *self.sort_keys)
        return self.reduce_fn(df) if self.reduce_fn else df

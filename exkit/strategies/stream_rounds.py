"""Rounds with reducer state: every round refines the reducers' states, and a statistic of all states can be published.

State and rounds are tables: a round's partial aggregate is joined to the state
so far by the reducer's keys, so state size is the number of keys, not of rows.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame

from exkit.plans.spec import ShuffleSpec
from exkit.staging import stage
from exkit.strategies.rounds import MapRounds


def stream_rounds(
    df: DataFrame, spec: ShuffleSpec, on_partial: Callable[[int, DataFrame], None] | None = None, until: Callable[[int, DataFrame], bool] | None = None
) -> DataFrame:
    """Final result after all rounds (or after ``until`` says stop).

    With ``merge_fn`` (associative, commutative, and closed over its own output)
    the state is its running combination; without, states are the rows so far,
    which are written once. Each input row is read once.
    """
    rounds = -(-spec.m // spec.round_maps)
    maps, state, parts = MapRounds(df, spec, rounds), None, []
    for i in range(rounds):
        own = maps(i)
        if not spec.merge_fn:  # rows are only added: a round's output stays where it is
            parts.append(own)
            state = reduce(DataFrame.unionByName, parts)
        else:
            part = spec.merge_fn(own)
            state = stage(part if state is None else spec.merge_fn(state.unionByName(part)), f"state-{i}")
            maps.drop(i)
        if on_partial:
            on_partial(i, state)
        if until and until(i, state):
            break
    return spec.reduced(state.repartitionById(spec.r, "reduce_id"))

"""Every query of the package outside ``llm``, with its SQL where SQL can express it."""

from __future__ import annotations

from exkit import workloads
from exkit.functions import scalar, user_defined
from exkit.operators import relational
from exkit.streaming import streams

QUERIES: dict = {}
SQL: dict[str, str] = {}
for _part in (workloads, relational, scalar, user_defined, streams):
    QUERIES |= _part.BOOK.queries
    SQL |= _part.BOOK.sql


def flagship(spark, sf_dir: str):
    return QUERIES["record_sort_push_inline"](spark, sf_dir)

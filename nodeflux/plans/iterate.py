"""Hop loops: the driver declares one hop at a time and cuts the lineage every few hops."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame

from .storage import cut, discard

#: Hops in one job. Their shuffles run without a driver round trip; lineage stays short.
HOPS_PER_CUT = 4


def repeat(state: DataFrame, step: Callable[[DataFrame, int], DataFrame], times: int, every: int = HOPS_PER_CUT, name: str = "hop") -> DataFrame:
    """step(state, i) for i = 0 .. times - 1, with a table written after every few steps."""
    written = None
    for i in range(times):
        state = step(state, i)
        if (i + 1) % every == 0 and i + 1 < times:
            fresh = cut(state, name)
            if written is not None:
                discard(written)
            state = written = fresh
    return state

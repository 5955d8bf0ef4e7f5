"""Loop driver: a plan for each round, lineage cut by a written table, stop by a scalar."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame

from evigraph.runtime import written


def run(state: DataFrame, step: Callable[[DataFrame, int], DataFrame], rounds: int, done: Callable[[DataFrame, DataFrame], bool] | None = None, cut: int = 4) -> tuple[DataFrame, int]:
    """Apply ``step`` up to ``rounds`` times; every ``cut`` rounds the state is written and, if given, ``done(old, new)`` is asked."""
    held = state
    for i in range(1, rounds + 1):
        state = step(state, i)
        if i % cut == 0 or i == rounds:
            state = written(state, "round")
            if done is not None and done(held, state):
                return state, i
            held = state
    return state, rounds

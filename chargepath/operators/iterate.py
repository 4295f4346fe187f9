"""Rounds over a table until nothing is open."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame

from chargepath.operators.search import cut_size


def iterate(state: DataFrame, step: Callable[[DataFrame, int], DataFrame], is_open: str, every: int = 1, most: int | None = None) -> tuple[DataFrame, int]:
    """(last state, rounds): state = step(state, round) while a row fulfils ``is_open``.

    Every ``every`` rounds the state is cut in the checkpoint folder, so the plan
    does not grow. ``most`` rounds raise an error: a guard, not an answer.
    """
    state, k = cut_size(state), 0
    while not state.where(is_open).isEmpty():
        if most is not None and k >= most:
            raise RuntimeError(f"still open after {most} rounds")
        k += 1
        state = step(state, k)
        if k % every == 0:
            state = cut_size(state)
    return cut_size(state), k

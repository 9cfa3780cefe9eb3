"""Loops over DataFrame states: lineage is cut at a fixed cadence, the stop test is a few scalars."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame

from .state import materialise


@dataclass
class IterationReport:
    rounds: int = 0
    converged: bool = False
    status: str = "max_iter"
    history: list[dict] = field(default_factory=list)


def fixpoint(state: DataFrame, step: Callable[[DataFrame, int], DataFrame], measure: Callable[[DataFrame, int], dict], stop: Callable[[dict], str | None], *, max_iter: int, every: int = 1, name: str = "state") -> tuple[DataFrame, IterationReport]:
    """Applies step until stop(measure(state)) gives a status. Every `every` rounds the state is written and measured;
    between them the plan grows. measure returns scalars alone."""
    report = IterationReport()
    state = materialise(state, name)
    for k in range(max_iter):
        state = step(state, k)
        report.rounds = k + 1
        if (k + 1) % every and k + 1 < max_iter:
            continue
        state = materialise(state, name)
        seen = measure(state, k)
        report.history.append(seen)
        if status := stop(seen):
            report.status, report.converged = status, status == "converged"
            return state, report
    return state, report

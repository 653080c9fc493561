"""Loops shared by all fits: stopping, traces, generic soft and hard EM, several starts."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from contextlib import contextmanager
from dataclasses import dataclass, field
from typing import Any, Protocol

from pyspark.sql import DataFrame, SparkSession

TRACE = "run_id string, iter int, elapsed_s double, entropy double, moved long"


@dataclass
class Stop:
    """Ends a fit: relative change below tol for `patience` rounds, or max_iter rounds, or a time budget."""

    tol: float = 1e-6
    patience: int = 2
    max_iter: int = 50
    time_budget_s: float | None = None

    def reached(self, entropies: list[float], elapsed: float) -> bool:
        if len(entropies) > self.max_iter or (self.time_budget_s is not None and elapsed >= self.time_budget_s):
            return True
        tail = entropies[-self.patience - 1 :]
        return len(tail) > self.patience and all(abs(a - b) <= self.tol * max(1.0, abs(a)) for a, b in zip(tail, tail[1:]))


@dataclass
class Trace:
    """Entropy after each round; round 0 is the start."""

    run_id: str = "run"
    rows: list[tuple] = field(default_factory=list)
    began: float = field(default_factory=time.monotonic)

    def add(self, entropy: float, moved: int = 0) -> None:
        self.rows.append((self.run_id, len(self.rows), self.elapsed(), float(entropy), int(moved)))

    @property
    def entropies(self) -> list[float]:
        return [r[3] for r in self.rows]

    def elapsed(self) -> float:
        return time.monotonic() - self.began

    @contextmanager
    def untimed(self) -> Iterator[None]:
        """What runs inside doesn't count as elapsed: measuring, as opposed to fitting."""
        paused = time.monotonic()
        try:
            yield
        finally:
            self.began += time.monotonic() - paused

    def to_df(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows, TRACE)

    def write(self, spark: SparkSession, path: str) -> None:
        """Append to a parquet sink partitioned by run and round."""
        self.to_df(spark).write.mode("append").partitionBy("run_id", "iter").parquet(path)


class EMProblem(Protocol):
    """Soft: expect gives responsibilities, maximise a new state. Hard: assign and fit play those parts."""

    def expect(self, state: dict[str, DataFrame]) -> Any: ...

    def maximise(self, state: dict[str, DataFrame], expected: Any) -> dict[str, DataFrame]: ...

    def entropy(self, state: dict[str, DataFrame]) -> float: ...


@dataclass
class Fit:
    state: dict[str, Any]
    trace: Trace


def run_em(problem: EMProblem, state: dict[str, Any], stop: Stop, run_id: str = "em") -> Fit:
    """Alternate expectation and maximisation from a start until `stop`."""
    trace = Trace(run_id)
    trace.add(problem.entropy(state))
    while not stop.reached(trace.entropies, trace.elapsed()):
        state = problem.maximise(state, problem.expect(state))
        trace.add(problem.entropy(state))
    return Fit(state, trace)


run_hard_em = run_em


def multi_start(fit: Callable[[int], Fit], seeds: list[int]) -> Fit:
    """The fit with the lowest final entropy; the earliest seed among equals."""
    return min((fit(seed) for seed in seeds), key=lambda f: f.trace.entropies[-1])

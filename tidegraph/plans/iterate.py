"""Iteration: vertex state that is replaced or patched, and the loop that runs a step until nothing changes."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, Observation, functions as F

from tidegraph.runtime import Scratch, materialize
from tidegraph.plans.layout import BROADCAST_ROWS, counted, sized

__all__ = ["BROADCAST_ROWS", "MAX_PATCHES", "SWITCH_AT", "RunReport", "VertexState", "counted", "fixpoint", "sized"]

#: Up to so many updates in a round patch the vertex relation; more replace it.
SWITCH_AT = 5_000
#: Patches that readers merge; more become one.
MAX_PATCHES = 3


@dataclass
class RunReport:
    """What a run did, round by round: ``round, seconds, updates, applied``, and phase times in seconds."""

    rounds: list[dict] = field(default_factory=list)
    phases: dict[str, float] = field(default_factory=dict)
    converged: bool = False
    groups: list[str] = field(default_factory=list)

    def begin_round(self, spark, k: int) -> float:
        """Name the jobs from here on after round ``k``, so that their figures can be found; returns the time."""
        self.groups.append(f"round-{k}-{time.time_ns()}")
        spark.sparkContext.setJobGroup(self.groups[-1], f"round {k}")
        return time.time()

    def as_rows(self) -> list[tuple]:
        return [(r["round"], r["updates"], r["seconds"], r["applied"]) for r in self.rounds]


class VertexState:
    """``(id, value)`` under updates. ``how``: replace, patch, auto (by SWITCH_AT) or cost (by what either would write and read).

    Files cannot be updated in place, so a patch is an overlay that readers merge with the base; a few patches become one,
    and an overlay beyond the limit is folded into a new base. What is merged or folded is dropped, but for the latest
    delta; ``keep_deltas`` leaves all of them to the caller.
    """

    def __init__(self, base: DataFrame, how: str = "auto", switch_at: int = SWITCH_AT, keep_deltas: bool = False):
        self.base = materialize(base, "state")
        self.how, self.switch_at, self.keep_deltas = how, switch_at, keep_deltas
        self.overlay: list[tuple[Scratch, int]] = []
        self._rows: int | None = None

    @property
    def overlay_rows(self) -> int:
        return sum(n for _, n in self.overlay)

    def _newest(self) -> DataFrame:
        """The overlay's latest value of each id."""
        if len(self.overlay) == 1:
            return self.overlay[0][0].df
        rows = self.overlay[0][0].df.withColumn("at", F.lit(0))
        for k, (delta, _) in enumerate(self.overlay[1:], 1):
            rows = rows.unionByName(delta.df.withColumn("at", F.lit(k)))
        return rows.groupBy("id").agg(F.max_by("value", "at").alias("value"))

    def current(self) -> DataFrame:
        if not self.overlay:
            return self.base.df
        newest = sized(self._newest().withColumnRenamed("value", "new"), self.overlay_rows)
        return self.base.df.join(newest, "id", "left").select("id", F.coalesce("new", "value").alias("value"))

    def _patch(self, updates: int) -> bool:
        if self.how == "cost":
            if self._rows is None:
                self._rows = self.base.df.count()
            return (self.overlay_rows + updates) * 4 < self._rows
        return self.how == "patch" or (self.how == "auto" and self.overlay_rows + updates < self.switch_at)

    def apply(self, delta: Scratch, updates: int) -> str:
        """Take over ``delta(id, value)``; returns what was done."""
        self.overlay.append((delta, updates))
        if self._patch(updates):
            if len(self.overlay) > MAX_PATCHES:
                merged = materialize(self._newest(), "overlay")
                self._leave(delta)
                self.overlay = [(merged, self.overlay_rows)]
            return "patch"
        folded = materialize(self.current(), "state")
        self.base.drop()
        self._leave(delta)
        self.base, self.overlay = folded, []
        return "replace"

    def _leave(self, latest: Scratch) -> None:
        for old, _ in self.overlay:
            if old is not latest and not (self.keep_deltas and old.path.rsplit("/", 1)[-1].startswith("delta")):
                old.drop()

    def release(self, delta: Scratch) -> None:
        """Drop a delta that is no frontier any more, unless it is part of the overlay."""
        if all(delta is not x for x, _ in self.overlay):
            delta.drop()


def fixpoint(state: VertexState, frontier: DataFrame, step: Callable[[DataFrame, int, DataFrame, int], DataFrame], max_rounds: int, quiet_rounds: int = 1) -> RunReport:
    """Run ``step(frontier, its rows, current state, round) -> delta(id, value)`` until ``quiet_rounds`` rounds change nothing.

    Each delta is written and counted in one job and becomes the next frontier; only the count reaches the driver.
    """
    report = RunReport()
    rows, quiet, before = 0, 0, None
    for k in range(1, max_rounds + 1):
        began = report.begin_round(state.base.spark, k)
        delta, updates = counted(step(frontier, rows, state.current(), k), "delta")
        applied = state.apply(delta, updates) if updates else "none"
        report.rounds.append({"round": k, "seconds": time.time() - began, "updates": updates, "applied": applied})
        frontier, rows = delta.df, updates
        if before is not None:
            state.release(before)
        before = delta
        quiet = 0 if updates else quiet + 1
        if quiet >= quiet_rounds:
            report.converged = True
            break
    return report

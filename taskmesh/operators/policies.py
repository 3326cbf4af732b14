"""How much work each node does in a round, as columns: budget (coordinate steps), theta (accuracy asked), dropped.

Policies read n (points of the task), and speed and comm_scale of a node profile where there is one. All draws are
``portable_uniform`` of seed, outer step, round and task, so they are the same on any cluster.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

from taskmesh.functions.draws import portable_uniform

NO_LIMIT = 1 << 30


@dataclass(frozen=True)
class Plan:
    budget: Column
    theta: Column
    dropped: Column


def _no() -> Column:
    return F.lit(False)


@dataclass(frozen=True)
class WorkBudget:
    """The same work for every node: a number of steps, or of passes over its own points."""

    steps: int | None = None
    passes: float | None = None

    def plan(self, outer: int, round_: int, least: int, seed: int) -> Plan:
        budget = F.lit(self.steps) if self.steps is not None else F.greatest(F.lit(1), F.round(F.col("n") * F.lit(float(self.passes or 1.0))))
        return Plan(budget.cast("int"), F.lit(0.0), _no())


@dataclass(frozen=True)
class FixedAccuracy:
    """Every node works until its own accuracy is theta, however long that takes."""

    theta: float = 0.1
    max_passes: int = 100

    def plan(self, outer: int, round_: int, least: int, seed: int) -> Plan:
        return Plan((F.col("n") * self.max_passes).cast("int"), F.lit(float(self.theta)), _no())


@dataclass(frozen=True)
class ClockPolicy:
    """Steps that fit into a cycle after the answer's way is paid; a node that can do none is dropped."""

    cycle: float
    step_cost: float
    comm_cost: float = 0.0

    def plan(self, outer: int, round_: int, least: int, seed: int) -> Plan:
        left = F.lit(float(self.cycle)) - F.col("comm_scale") * float(self.comm_cost)
        steps = F.floor(left * F.col("speed") / float(self.step_cost))
        return Plan(F.greatest(F.lit(0), steps).cast("int"), F.lit(0.0), steps < 1)


@dataclass(frozen=True)
class Heterogeneity:
    """Steps drawn between a share and all of the smallest task's points: from a tenth ('high') or from nine tenths ('low')."""

    level: str = "high"

    def plan(self, outer: int, round_: int, least: int, seed: int) -> Plan:
        low = 0.1 if self.level == "high" else 0.9
        u = portable_uniform("work", seed, outer, round_, F.col("task_id"))
        return Plan(F.greatest(F.lit(1), F.floor(F.lit(float(least)) * (F.lit(low) + F.lit(1 - low) * u))).cast("int"), F.lit(0.0), _no())


@dataclass(frozen=True)
class DropPolicy:
    """Each node drops out of a round with probability p, of its own accord; what it may have computed is discarded."""

    p: float

    def plan(self, outer: int, round_: int, least: int, seed: int) -> Plan:
        return Plan(F.lit(NO_LIMIT), F.lit(0.0), portable_uniform("drop", seed, outer, round_, F.col("task_id")) < self.p)


@dataclass(frozen=True)
class NeverSends:
    """Some nodes are never heard from."""

    tasks: tuple[int, ...]

    def plan(self, outer: int, round_: int, least: int, seed: int) -> Plan:
        return Plan(F.lit(NO_LIMIT), F.lit(0.0), F.col("task_id").isin(list(self.tasks)))


@dataclass(frozen=True)
class Composed:
    """The least budget, the strictest accuracy that any part asks, dropped if any part says so."""

    parts: tuple

    def plan(self, outer: int, round_: int, least: int, seed: int) -> Plan:
        plans = [p.plan(outer, round_, least, seed) for p in self.parts]
        budget, theta, dropped = plans[0].budget, plans[0].theta, plans[0].dropped
        for p in plans[1:]:
            budget, theta, dropped = F.least(budget, p.budget), F.greatest(theta, p.theta), dropped | p.dropped
        return Plan(budget, theta, dropped)


def compose(*parts) -> Composed:
    return Composed(tuple(parts))

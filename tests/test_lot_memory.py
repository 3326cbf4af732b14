"""Weights of a lot reach the blocks by file, and the rounds of tasks that stand alone are one pass over them."""

import numpy as np

from taskmesh.operators import batched
from taskmesh.operators.losses import Hinge
from taskmesh.operators.relations import IndependentRelation
from tests.fixtures import six_tasks


def test_rounds_of_lone_tasks_are_passes(spark, monkeypatch):
    tasks = six_tasks(spark)
    problem = batched.masked(tasks, batched.trial_parts(tasks, 2, 3), 2)
    configs = [batched.Config(t, f, lam) for t in range(2) for f in (0, -1) for lam in (0.1, 1.0)]
    alone = [IndependentRelation(lam2=c.lam) for c in configs]
    rounds = []
    stored = batched.materialise
    monkeypatch.setattr(batched, "materialise", lambda df, name: rounds.append(name) or stored(df, name))
    monkeypatch.setattr(spark, "createDataFrame", None)  # no weights through the JVM's heap
    found, _ = batched.fit_configs(problem, configs, alone, Hinge(), 1, 3)
    assert rounds == ["configs"]
    steps = [batched.fit_configs(problem, configs, alone, Hinge(), 3, 1)[0], batched.fit_configs(problem, configs, alone, Hinge(), 1, 1, passes=3)[0]]
    assert all(np.allclose(found, s, atol=1e-9) for s in steps)
    assert batched.held_errors(problem, configs, found).count()

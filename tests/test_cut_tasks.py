"""Tasks that are cut into several blocks do what they do as one block."""

import numpy as np

from taskmesh.operators import frames, policies
from taskmesh.operators.baselines import minibatch_sdca, minibatch_sgd
from taskmesh.operators.losses import Hinge
from taskmesh.operators.relations import ClusterRelation
from taskmesh.operators.solver import prepare, update_weights
from tests.fixtures import six_tasks

RELATION = ClusterRelation(lam1=1.0, lam2=0.5, clusters=(0, 1, 0, 1, 0, 1))


def both(spark):
    tasks = six_tasks(spark, sizes=(4, 9, 50, 7, 61, 12)).cache()
    return prepare(frames.pack(tasks), 2), prepare(frames.pack(tasks, 5), 4)


def same(one, cut):
    assert (cut.problem.blocks > 1).any() and np.allclose(one.weights, cut.weights, atol=1e-9)
    assert np.allclose([h["primal"] for h in one.history], [h["primal"] for h in cut.history], atol=1e-9)
    steps = [[(r["round"], r["task_id"], r["steps"]) for r in fit.round_log] for fit in (one, cut)]
    assert sorted(steps[0]) == sorted(steps[1])


def test_sdca_samples_whole_tasks(spark):  # F5
    one, cut = (minibatch_sdca(p, RELATION, Hinge(), batch=8, scale=2.0, rounds=3) for p in both(spark))
    same(one, cut)
    assert np.allclose([h["dual"] for h in one.history], [h["dual"] for h in cut.history], atol=1e-9)


def test_sgd_samples_whole_tasks(spark):  # F6
    same(*(minibatch_sgd(p, RELATION, Hinge(), batch=8, eta=0.05, rounds=3) for p in both(spark)))


def test_one_pass_is_one_step_a_row(spark):  # 50 * (7 / 50), as a float, is more than 7
    sizes = (25, 41, 43, 50, 51, 82)
    problem = prepare(frames.pack(six_tasks(spark, sizes=sizes), 7), 4)
    fit = update_weights(problem, RELATION, Hinge(), 1, policies.compose(policies.WorkBudget(passes=1), policies.DropPolicy(0.0)))
    assert [r["steps"] for r in fit.round_log] == list(sizes)

"""Weights that stay with the blocks are those that the driver works out, and rounds do not multiply with the tasks."""

import numpy as np
import pytest

from taskmesh.operators import batched
from taskmesh.operators.losses import Hinge, Logistic
from taskmesh.operators.relations import ClusterRelation, IndependentRelation
from taskmesh.plans import experiments
from tests.fixtures import six_tasks

CONFIGS = [batched.Config(t, f, lam) for t in range(2) for f in (0, -1) for lam in (0.1, 1.0)]


def multitask(lam):
    return experiments.FirstIndependent(lam2=1.1 * lam, then=ClusterRelation(lam1=lam, lam2=0.1 * lam, k=2, starts=3))


def errors(problem, weights):
    return {(r.config, r.base): (r.n, r.wrong) for r in batched.held_errors(problem, CONFIGS, weights).collect()}


@pytest.mark.parametrize("block_rows", [4096, 8])
@pytest.mark.parametrize("learn", [False, True])
def test_spread_weights_give_the_same_errors(spark, monkeypatch, block_rows, learn):
    tasks = six_tasks(spark, real=True)
    problem = batched.masked(tasks, batched.trial_parts(tasks, 2, 3), 2, block_rows=block_rows)
    relations = [multitask(c.lam) if learn else IndependentRelation(lam2=c.lam) for c in CONFIGS]
    given = (problem, CONFIGS, relations, Hinge(), 3 if learn else 1, 2, 2, learn)
    weights, _ = batched.fit_configs(*given)
    monkeypatch.setattr(batched, "LOT_CELLS", 10)
    stored, store = [], batched.materialise
    monkeypatch.setattr(batched, "materialise", lambda df, name: stored.append(name) or store(df, name))
    spread, _ = batched.fit_configs(*given)
    assert isinstance(spread, batched.Spread) and len(stored) <= (6 if learn else 2)
    assert errors(problem, spread) == errors(problem, weights)


def test_lots_do_not_multiply_with_tasks(spark, monkeypatch):
    tasks = six_tasks(spark, real=True)
    monkeypatch.setattr(batched, "LOT_CELLS", 60)  # two configurations of six tasks and five features
    stored, store = [], batched.materialise
    monkeypatch.setattr(batched, "materialise", lambda df, name: stored.append(name) or store(df, name))
    out = experiments.compare_models(tasks, lambdas=(0.1, 1.0), folds=2, trials=2, clusters=2, models=("local", "multitask"))
    assert out.count() == 4
    assert stored.count("configs") <= 10 and stored.count("masked") == 1 and stored.count("tasks") == 1


@pytest.mark.parametrize("loss", [Hinge(), Logistic()])
def test_blocks_beside_one_another_change_nothing(loss):
    rng = np.random.default_rng(5)
    sizes, c, d = (3, 40, 17), 4, 6
    xs, ys = [rng.random((n, d)) - 0.4 for n in sizes], [np.where(rng.random(n) < 0.5, 1.0, -1.0) for n in sizes]
    masks, w, curve = [rng.random((n, c)) < 0.7 for n in sizes], rng.random((3, c, d)) - 0.5, rng.random((3, c)) + 0.1
    together = np.zeros((3, max(sizes), c))
    batched.passes_together(loss, batched._filled(xs), batched._filled(ys), batched._filled(masks), together, w, curve, 2)
    for k, n in enumerate(sizes):
        alone = np.zeros((n, c))
        batched.passes_of(loss, xs[k], ys[k], masks[k], alone, w[k], curve[k], 2)
        assert np.allclose(together[k, :n], alone, atol=1e-10) and not together[k, n:].any()

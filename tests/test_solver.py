"""The solver against exact optima, invariants, limits, policies and the negative controls."""

import numpy as np
import pytest

from taskmesh.operators import frames, policies
from taskmesh.operators.baselines import fit_global, fit_local, fixed_accuracy, minibatch_sdca, minibatch_sgd
from taskmesh.operators.losses import Hinge, Squared
from taskmesh.operators.measures import assumption_report, measured_theta, rounds_bound_smooth, simulated_time, smooth_constant, straggler_report
from taskmesh.operators.relations import ClusterRelation, CovarianceRelation, IndependentRelation, MeanRelation
from taskmesh.operators.solver import State, fit_multitask, prepare, run_round, update_weights
from tests.fixtures import arrays, dense_squared_optimum, six_tasks

CLUSTERS = ClusterRelation(lam1=1.0, lam2=0.2, clusters=(0, 1, 0, 1, 0, 1))


@pytest.fixture(scope="module")
def hinge(spark):
    return prepare(frames.pack(six_tasks(spark)), 2)


@pytest.fixture(scope="module")
def real(spark):
    return prepare(frames.pack(six_tasks(spark, real=True)), 2)


def test_squared_loss_reaches_the_dense_optimum(spark, real):
    fit = update_weights(real, CLUSTERS, Squared(), 25, policies.WorkBudget(passes=3))
    want = dense_squared_optimum(arrays(six_tasks(spark, real=True)), CLUSTERS.gram(6))
    assert np.abs(fit.weights - want).max() < 1e-3
    assert 0 <= fit.history[-1]["gap"] < 1e-3


def test_gap_is_positive_and_the_dual_falls(hinge):
    fit = update_weights(hinge, CLUSTERS, Hinge(), 12, policies.WorkBudget(passes=2))
    gaps, duals = [h["gap"] for h in fit.history], [h["dual"] for h in fit.history]
    assert min(gaps) > -1e-9 and gaps[-1] < 0.1 * gaps[0]
    assert all(b <= a + 1e-9 for a, b in zip(duals, duals[1:], strict=False))


def test_shared_vectors_are_what_duals_say(hinge):
    fit = update_weights(hinge, CLUSTERS, Hinge(), 2)
    packed = {r.task_id: np.array(r.xs) for r in hinge.packed.collect()}
    for r in fit.state.duals.collect():
        a = np.array(r.alpha)
        assert np.allclose(packed[r.task_id].T @ a, fit.state.v[r.task_id])


def test_unsafe_sigma_is_noticed(real):
    with pytest.raises(ArithmeticError):
        update_weights(real, MeanRelation(6, 50.0, 0.01), Squared(), 12, policies.WorkBudget(passes=5), sigma=0.05)


def test_blocks_of_one_task_still_converge(spark):
    tasks = six_tasks(spark, real=True)
    fit = update_weights(prepare(frames.pack(tasks, block_rows=8), 2), CLUSTERS, Squared(), 30, policies.WorkBudget(passes=3))
    assert np.abs(fit.weights - dense_squared_optimum(arrays(tasks), CLUSTERS.gram(6))).max() < 2e-2
    assert fit.history[-1]["gap"] < 0.05 * fit.history[0]["gap"]


def test_strong_mean_relation_is_the_global_model(spark):
    tasks = six_tasks(spark, real=True)
    data = arrays(tasks)
    w = dense_squared_optimum(data, MeanRelation(6, 1e7, 0.1).gram(6))
    fit = fit_global(tasks, Squared(), 0.6, rounds=2, block_rows=4096, passes=100)
    assert np.abs(w - fit.weights[0]).max() < 1e-4


def test_local_models_by_group_and_by_rounds_agree(spark, hinge):
    one = {r.task_id: np.array(r.w) for r in fit_local(six_tasks(spark), Hinge(), 0.5, passes=300).collect()}
    fit = update_weights(hinge, IndependentRelation(lam2=0.5), Hinge(), 6, policies.WorkBudget(passes=50))
    assert all(np.abs(one[t] - fit.weights[k]).max() < 1e-3 for k, t in enumerate(hinge.tasks))


def test_dropped_nodes_change_nothing_and_silent_ones_spoil_the_solution(real):
    m = len(real.tasks)
    everyone, entry, log = run_round(real, State(np.zeros((m, real.d))), CLUSTERS, Squared(), policies.NeverSends(tuple(real.tasks)), np.full(m, 3.0), 0, 0)
    assert not everyone.v.any() and all(r["dropped"] and r["theta"] == 1.0 and r["comm_elems"] == 0 for r in log)
    work = policies.WorkBudget(passes=3)
    best = update_weights(real, CLUSTERS, Squared(), 20, work).history[-1]["dual"]
    dropping = update_weights(real, CLUSTERS, Squared(), 40, policies.compose(work, policies.DropPolicy(0.5))).history[-1]["dual"]
    silent = update_weights(real, CLUSTERS, Squared(), 20, policies.compose(work, policies.NeverSends((4,)))).history[-1]["dual"]
    assert dropping - best < 1e-3 < 1e-2 < silent - best


def test_fixed_accuracy_is_reached_and_varies_in_work(spark, real):
    m = len(real.tasks)
    sigma = CLUSTERS.sigma(m) * real.blocks
    start = State(np.zeros((m, real.d)))
    after, _, log = run_round(real, start, CLUSTERS, Squared(), policies.FixedAccuracy(0.2), sigma, 0, 0)
    assert max(measured_theta(real, start, after, CLUSTERS, Squared(), sigma).values()) <= 0.2 + 1e-9
    assert len({r["steps"] for r in log}) > 1
    same, _, _ = run_round(real, start, CLUSTERS, Squared(), policies.NeverSends(tuple(real.tasks)), sigma, 0, 0)
    assert set(measured_theta(real, start, same, CLUSTERS, Squared(), sigma).values()) == {1.0}


def test_aggregation_parameter(real):
    full = update_weights(real, CLUSTERS, Squared(), 10, policies.WorkBudget(passes=2))
    half = update_weights(real, CLUSTERS, Squared(), 10, policies.WorkBudget(passes=2), gamma=0.5)
    assert half.history[-1]["gap"] < half.history[0]["gap"] and full.history[-1]["gap"] < 1.0


def test_alternation_never_raises_the_objective_and_learns_clusters(spark):
    problem = prepare(frames.pack(six_tasks(spark, sizes=(30,) * 6)), 2)
    fit = fit_multitask(problem, ClusterRelation(lam1=0.5, lam2=0.05, k=2), Hinge(), outer=3, rounds=8, policy=policies.WorkBudget(passes=3))
    assert fit.relation.clusters == (0, 1, 0, 1, 0, 1)
    for i in (1, 2):
        inside = [h for h in fit.history if h["outer"] == i]
        assert inside[-1]["primal"] <= inside[0]["primal"] + 1e-6
    learned = fit_multitask(problem, CovarianceRelation(lam1=0.05, lam2=0.05), Hinge(), outer=2, rounds=4)
    assert np.isclose(np.trace(learned.relation.omega), 1.0)


def test_minibatch_methods_move_towards_the_optimum_but_slower(hinge):
    best = update_weights(hinge, CLUSTERS, Hinge(), 12, policies.WorkBudget(passes=3))
    sdca = minibatch_sdca(hinge, CLUSTERS, Hinge(), batch=4, scale=2.0, rounds=12)
    sgd = minibatch_sgd(hinge, CLUSTERS, Hinge(), batch=4, eta=0.05, rounds=12)
    assert sdca.history[-1]["gap"] < sdca.history[0]["gap"] and sgd.history[-1]["primal"] < sgd.history[0]["primal"]
    assert best.history[-1]["primal"] <= min(sdca.history[-1]["primal"], sgd.history[-1]["primal"]) + 1e-6


def test_reports_and_bounds(hinge, real):
    elastic = update_weights(hinge, CLUSTERS, Hinge(), 4, policies.WorkBudget(steps=6))
    fixed = fixed_accuracy(hinge, CLUSTERS, Hinge(), 0.1, 4)
    ratio = lambda f: straggler_report(f.log_frame()).agg({"ratio": "max"}).first()[0]
    assert ratio(elastic) == pytest.approx(1.5, abs=0.51) and ratio(fixed) > 2
    times = {r.round: r.sim_time for r in simulated_time(elastic.log_frame(), 10.0).collect()}
    assert times[3] == pytest.approx(4 * times[0])
    dropped = update_weights(hinge, CLUSTERS, Hinge(), 4, policies.DropPolicy(0.4))
    assert 0 < assumption_report(dropped.log_frame()).first().p_max <= 1
    s = smooth_constant(real, CLUSTERS, 1.0, CLUSTERS.sigma(6))
    assert rounds_bound_smooth(int(real.points.sum()), 1e-3, 0.5, s) > 20

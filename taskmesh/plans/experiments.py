"""The experiments: model comparison, stragglers over networks, systems heterogeneity, dropped nodes, and a check of limits."""

from __future__ import annotations

import math
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from taskmesh.operators import batched, policies
from taskmesh.operators.baselines import fixed_accuracy, minibatch_sdca, minibatch_sgd, tune
from taskmesh.operators.losses import Hinge, Loss
from taskmesh.operators.measures import NETWORKS, curve, simulated_time
from taskmesh.operators.relations import ClusterRelation, IndependentRelation, Relation
from taskmesh.operators.solver import FitResult, Problem, StopRule, fit_multitask, update_weights

LAMBDAS = (1e-5, 1e-4, 1e-3, 1e-2, 0.1, 1.0, 10.0)
DROPS = (0.0, 0.1, 0.25, 0.5, 0.75, 0.9)


@dataclass(frozen=True)
class FirstIndependent(IndependentRelation):
    """The first step of an alternation: no relation yet; the weights then say which one follows."""

    then: Relation = field(default_factory=ClusterRelation)

    def update(self, w):
        return self.then.update(w)


def compare_models(
    tasks: DataFrame, lambdas: tuple[float, ...] = LAMBDAS, folds: int = 5, trials: int = 10, clusters: int = 3, outer: int = 3, rounds: int = 4, passes: int = 2, loss: Loss | None = None, seed: int = 0,
    models: tuple[str, ...] = ("global", "local", "multitask"),
) -> DataFrame:
    """model, trial, lam, error: the test error, averaged over tasks, of the model with the penalty that cross-validation picks
    (ties: the larger). Each trial splits every task anew, 75 to 25, and its training rows into folds; all of a model's penalties,
    folds and trials train together. One penalty is searched: the multi-task model has lam between tasks and a tenth of it on
    all weights, and learns ``clusters`` groups between its outer steps."""

    def multitask(lam: float, m: int) -> Relation:
        return FirstIndependent(lam2=1.1 * lam, then=ClusterRelation(lam1=lam, lam2=0.1 * lam, k=clusters, starts=3, seed=seed))

    alone = lambda lam, m: IndependentRelation(lam2=lam)
    known = {"global": (True, False, alone), "local": (False, False, alone), "multitask": (False, True, multitask)}
    return batched.compare(tasks, {name: known[name] for name in models}, lambdas, folds, trials, loss or Hinge(), outer, rounds, passes, seed)


def long_run(problem: Problem, relation: Relation, loss: Loss, gap: float = 1e-6, rounds: int = 60) -> FitResult:
    """The reference optimum: rounds with full local work until the gap is small."""
    return update_weights(problem, relation, loss, rounds, policies.WorkBudget(passes=10), stop=StopRule(gap))


def _best(problem: Problem, relation: Relation, loss: Loss) -> float:
    return -long_run(problem, relation, loss, rounds=30).history[-1]["dual"]


def driver_times(fit: FitResult, rho: float) -> dict[int, float]:
    """Simulated time after each round of a run, from its log on the driver (a row a task and round)."""
    cost: dict[int, float] = {}
    for r in fit.round_log:
        cost[r["round"]] = max(cost.get(r["round"], 0.0), r["flops"] + rho * r["comm_elems"])
    out, total = {}, 0.0
    for h in sorted(cost):
        total += cost[h]
        out[h] = total
    return out


def time_to(fit: FitResult, rho: float, best: float, epsilon: float) -> float:
    """Simulated time until the primal is within epsilon of the optimum; never: later than all that reach it, by what is left."""
    times = driver_times(fit, rho)
    for h in fit.history:
        if h["primal"] - best <= epsilon:
            return times.get(h["round"] - 1, 0.0)
    return 1e30 * (1.0 + min(1e6, min((h["primal"] for h in fit.history if math.isfinite(h["primal"])), default=1e6) - best))


def candidates(problem: Problem, relation: Relation, loss: Loss, rounds: int) -> dict[str, dict[str, FitResult]]:
    """Runs of every method over its own grid: work, accuracy, batch and scale, batch and step. One run serves all networks."""
    least = int(problem.points.min())
    batches = sorted({max(1, least // 2), max(1, least)})
    out: dict[str, dict[str, FitResult]] = {"elastic": {}, "fixed": {}, "sdca": {}, "sgd": {}}
    for times in (1, 4):
        out["elastic"][f"steps={times * least}"] = update_weights(problem, relation, loss, rounds, policies.WorkBudget(steps=times * least), run="elastic")
    for theta in (0.5, 0.1):
        out["fixed"][f"theta={theta}"] = fixed_accuracy(problem, relation, loss, theta, rounds, run="fixed")
    for batch in batches:
        for scale in sorted({min(2.0, batch), max(1.0, batch / 4)}):
            out["sdca"][f"batch={batch} scale={scale}"] = minibatch_sdca(problem, relation, loss, batch=batch, scale=scale, rounds=rounds, run="sdca")
        for eta in (0.05, 0.01, 0.002):
            out["sgd"][f"batch={batch} eta={eta}"] = minibatch_sgd(problem, relation, loss, batch=batch, eta=eta, rounds=rounds, run="sgd")
    return out


def straggler_curves(problem: Problem, relation: Relation, loss: Loss, rounds: int = 10, networks: dict[str, float] | None = None, best: float | None = None, reach: float = 0.2) -> DataFrame:
    """network, run, setting, round, sim_time, suboptimality of the primal: elastic and fixed accuracy, mini-batch SDCA and SGD, each
    with the setting that first comes within ``reach`` of the start's suboptimality on that network."""
    best = best if best is not None else _best(problem, relation, loss)
    found = candidates(problem, relation, loss, rounds)
    start = next(iter(found["elastic"].values())).history[0]["primal"] - best
    out = None
    for network, rho in (networks or NETWORKS).items():
        for runs in found.values():
            name, fit, _ = tune({n: (lambda f=f: f) for n, f in runs.items()}, lambda f, rho=rho: time_to(f, rho, best, reach * start))
            one = curve(fit.history_frame(), simulated_time(fit.log_frame(), rho), best).withColumn("network", F.lit(network)).withColumn("setting", F.lit(name))
            out = one if out is None else out.unionByName(one)
    return out


def _curves(fits: list[FitResult], networks: dict[str, float], best: float, profile: DataFrame | None = None) -> DataFrame:
    """The same runs priced for each network: costs change times only."""
    history, log = fits[0].history_frame(), fits[0].log_frame()
    for f in fits[1:]:
        history, log = history.unionByName(f.history_frame()), log.unionByName(f.log_frame())
    out = None
    for name, rho in networks.items():
        one = curve(history, simulated_time(log, rho, profile), best).withColumn("network", F.lit(name))
        out = one if out is None else out.unionByName(one)
    return out


def heterogeneity_curves(problem: Problem, relation: Relation, loss: Loss, rounds: int = 10, best: float | None = None, rho: float = 100.0, eta: float = 0.01) -> DataFrame:
    """High and low variability of local work: the elastic solver, mini-batch SDCA and SGD; fixed accuracy, which does not vary, beside."""
    best = best if best is not None else _best(problem, relation, loss)
    batch = int(problem.points.min())
    fits = [fixed_accuracy(problem, relation, loss, 0.1, rounds, run="fixed")]
    for level in ("high", "low"):
        policy = policies.Heterogeneity(level)
        fits.append(update_weights(problem, relation, loss, rounds, policy, run=f"elastic_{level}"))
        fits.append(minibatch_sdca(problem, relation, loss, batch=batch, scale=2.0, rounds=rounds, policy=policy, run=f"sdca_{level}"))
        fits.append(minibatch_sgd(problem, relation, loss, batch=batch, eta=eta, rounds=rounds, policy=policy, run=f"sgd_{level}"))
    return _curves(fits, {"lte": rho}, best)


def drop_curves(
    problem: Problem, relation: Relation, loss: Loss, ps: tuple[float, ...] = DROPS, silent: tuple[int, ...] = (), rounds: int = 10, outer: int = 1, passes: float = 2.0, best: float | None = None
) -> DataFrame:
    """run, outer, round, suboptimality, primal, gap for drop probabilities, and for nodes that never send. outer: 1 for a single
    update of the weights, whose suboptimality is the dual's; more for the whole alternation, whose suboptimality is that of the
    primal at the end of the run without drops, since its relation changes on the way."""
    work = policies.WorkBudget(passes=passes)
    cases = {f"p={p}": policies.compose(work, policies.DropPolicy(p)) if p else work for p in ps}
    if silent:
        cases["silent"] = policies.compose(work, policies.NeverSends(silent))
    fits = {name: update_weights(problem, relation, loss, rounds, policy, run=name) if outer == 1 else fit_multitask(problem, relation, loss, outer, rounds, policy, run=name) for name, policy in cases.items()}
    column = "dual" if outer == 1 else "primal"
    if best is None:
        best = long_run(problem, relation, loss, rounds=30).history[-1]["dual"] if outer == 1 else next(iter(fits.values())).history[-1]["primal"]
    history = None
    for f in fits.values():
        history = f.history_frame() if history is None else history.unionByName(f.history_frame())
    return history.select("run", "outer", "round", (F.col(column) - best).alias("suboptimality"), "primal", "gap")

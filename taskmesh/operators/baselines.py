"""What the solver is compared with: one global model, local models, fixed accuracy, mini-batch SGD and mini-batch SDCA."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from taskmesh.operators.frames import pack
from taskmesh.operators.local import block_arrays, sampled_rows, solve_block
from taskmesh.operators.losses import Loss
from taskmesh.operators.policies import FixedAccuracy, WorkBudget
from taskmesh.operators.relations import IndependentRelation, PooledRelation, Relation
from taskmesh.operators.solver import FitResult, Problem, State, attach, prepare, update_weights, with_picks
from taskmesh.operators.vector_aggregates import vector_sum
from taskmesh.sources import discard, materialise


def fit_global(tasks: DataFrame, loss: Loss, lam: float, rounds: int = 20, block_rows: int = 512, passes: float = 1.0) -> FitResult:
    """All points in one task; its blocks are solved in parallel, with sigma the number of blocks. Packing cuts the task by draws,
    so the table is neither sorted nor gathered in one place."""
    pooled = tasks.select(F.lit(0).cast("long").alias("task_id"), F.xxhash64("task_id", "row_id").alias("row_id"), "features", "label")
    return update_weights(prepare(pack(pooled, block_rows)), PooledRelation(lam2=lam), loss, rounds, WorkBudget(passes=passes))


def fit_local(tasks: DataFrame, loss: Loss, lam: float, passes: int = 50) -> DataFrame:
    """Every task by itself, in one grouped pass and no exchange of models: task_id, w. A task is one group here; large
    tasks go through ``update_weights`` with an independent relation, which cuts them into blocks."""
    curve = 0.5 / lam

    def solve(table: pa.Table) -> pa.Table:
        table = table.sort_by("row_id").combine_chunks()
        y = table.column("label").to_numpy()
        x = np.array(table.column("features").to_pylist(), float)
        norms = (x * x).sum(axis=1)
        alpha, dv, _, _ = solve_block(loss, x, y, norms, np.zeros(len(y)), np.zeros(x.shape[1]), curve, passes * len(y), 0.0, np.arange(len(y)))
        return pa.table({"task_id": table.column("task_id")[:1], "w": pa.array([(curve * dv).tolist()], pa.list_(pa.float64()))})

    return tasks.select("task_id", "row_id", "features", "label").groupBy("task_id").applyInArrow(solve, "task_id long, w array<double>")


def fit_local_rounds(problem: Problem, loss: Loss, lam: float, rounds: int = 20, passes: float = 1.0) -> FitResult:
    """Local models by rounds, for tasks of any size."""
    return update_weights(problem, IndependentRelation(lam2=lam), loss, rounds, WorkBudget(passes=passes), run="local")


def fixed_accuracy(problem: Problem, relation: Relation, loss: Loss, theta: float = 0.1, rounds: int = 20, **options) -> FitResult:
    """The solver that this one generalises: one accuracy for all nodes and rounds."""
    return update_weights(problem, relation, loss, rounds, FixedAccuracy(theta), run=options.pop("run", "fixed"), **options)


def minibatch_sdca(problem: Problem, relation: Relation, loss: Loss, batch: int = 16, scale: float = 1.0, rounds: int = 20, **options) -> FitResult:
    """Dual steps of ``batch`` sampled points of each task, all from the same model, scaled by scale / batch (1 <= scale <= batch)."""
    return update_weights(problem, relation, loss, rounds, options.pop("policy", None) or WorkBudget(passes=1.0), gamma=scale / batch, stale=batch, run=options.pop("run", "sdca"), **options)


def minibatch_sgd(problem: Problem, relation: Relation, loss: Loss, batch: int = 16, eta: float = 0.1, rounds: int = 20, seed: int = 0, policy=None, decay: str = "root", run: str = "sgd") -> FitResult:
    """Primal steps: each task samples ``batch`` points; its subgradient, scaled to all of its points, and 2 A w make the step,
    of length eta / sqrt(h) or eta / h."""
    m = len(problem.tasks)
    a = relation.gram(m)
    w = np.zeros((m, problem.d))
    policy = policy or WorkBudget(passes=1.0)
    place = problem.place
    history, log = [], []
    schema = "task_id long, g array<double>, loss double, sampled int, dropped boolean, n int"
    for h in range(rounds + 1):
        rows = attach(problem, State(np.zeros_like(w)), w, np.ones(m), np.ones(m))
        plan = policy.plan(0, h, int(problem.points.min()), seed)
        rows = rows.withColumn("budget", F.greatest(F.lit(1), plan.budget)).withColumn("dropped", plan.dropped)
        rows = with_picks(problem, rows, batch, seed, h)

        def step(batches: Iterator[pa.RecordBatch], h: int = h) -> Iterator[pa.RecordBatch]:
            for b in batches:
                out: list[list] = [[] for _ in range(6)]
                get = {n: b.column(n).to_pylist() for n in ("task_id", "block_id", "n", "budget", "dropped", "picked")}
                for k, (x, y, model) in enumerate(block_arrays(b)):
                    z = x @ model
                    size = max(1, min(batch, get["budget"][k], get["n"][k]))  # of the whole task, in one block or many
                    drawn = get["picked"][k]
                    some = sampled_rows(len(y), (seed, h, get["task_id"][k], get["block_id"][k]))[:size] if drawn is None else np.array(drawn, int)
                    gone = get["dropped"][k]
                    g = np.zeros(len(model)) if gone else x[some].T @ loss.subgradient(z[some], y[some]) * (get["n"][k] / size)
                    for column, value in zip(out, (get["task_id"][k], g, float(np.sum(loss.value(z, y))), 0 if gone else len(some), gone, len(y)), strict=True):
                        column.append(value)
                kinds = (pa.int64(), pa.list_(pa.float64()), pa.float64(), pa.int32(), pa.bool_(), pa.int32())
                yield pa.RecordBatch.from_arrays([pa.array(v, k) for v, k in zip(out, kinds, strict=True)], ["task_id", "g", "loss", "sampled", "dropped", "n"])

        stepped = materialise(rows.select("task_id", "block_id", "xs", "ys", "w", "n", "budget", "dropped", "picked").mapInArrow(step, schema), "sgd")
        sums = stepped.groupBy("task_id").agg(F.sum("loss").alias("loss"), F.sum("sampled").alias("sampled"), F.max("dropped").alias("dropped"), F.sum("n").alias("n"))
        done = sums.join(vector_sum(stepped, ["task_id"], "g"), "task_id").orderBy("task_id").collect()  # d numbers per task, bounded by DRIVER_CELLS
        discard(stepped)
        primal = relation.penalty(w) + sum(r.loss for r in done)
        history.append({"run": run, "outer": 0, "round": h, "primal": primal, "dual": float("nan"), "gap": float("nan")})
        if h == rounds:
            break
        grad, silent = 2 * (a @ w), np.zeros(m, bool)
        for r in done:
            k = place[r.task_id]
            grad[k] += np.array(r.g)
            silent[k] |= r.dropped
            log.append({"run": run, "outer": 0, "round": h, "task_id": r.task_id, "points": r.n, "steps": r.sampled, "theta": float("nan"), "dropped": r.dropped,
                        "flops": 4.0 * problem.d * r.sampled, "comm_elems": 0 if r.dropped else 2 * problem.d})
        grad[silent] = 0.0
        w = w - eta / (np.sqrt(h + 1.0) if decay == "root" else h + 1.0) * grad
    return FitResult(w, relation, problem, State(np.zeros_like(w)), history, log)


def tune(runs: dict[str, Callable[[], FitResult]], time_of: Callable[[FitResult], float]) -> tuple[str, FitResult, dict[str, float]]:
    """The configuration with the least time to target (ties: the first); all of their times."""
    fits = {name: run() for name, run in runs.items()}
    times = {name: time_of(fit) for name, fit in fits.items()}
    best = min(times, key=lambda n: (times[n], list(times).index(n)))
    return best, fits[best], times

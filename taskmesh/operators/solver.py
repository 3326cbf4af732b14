"""The elastic-accuracy solver: rounds with a fixed relation, and the full alternation with a learned one.

A round joins each block with its task's weights, works on the block's own duals, and brings back one vector per block,
summed by task. Features stay where packing put them; what crosses the network is the duals' own row and d numbers per
task each way. Every round is written to the shared folder before its vectors are used: duals and the shared vectors
then come from one and the same computation, and a lost executor costs a re-read, not a second, different round.

Tasks in several blocks are parallel parts: their sigma is multiplied by the number of blocks of that task.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from taskmesh.functions.draws import uniform_for
from taskmesh.operators import frames
from taskmesh.operators.local import arrow_pass, least_draws
from taskmesh.operators.losses import Loss
from taskmesh.operators.policies import NO_LIMIT, WorkBudget
from taskmesh.operators.relations import Relation
from taskmesh.sources import discard, materialise

#: Numbers (tasks times features) that may be on the driver at once; beyond, use ``relations.mix_frame``.
DRIVER_CELLS = 10_000_000


@dataclass
class Problem:
    """Packed blocks in place, their tasks in order, and d. Read once, used by every round and method."""

    spark: SparkSession
    packed: DataFrame
    tasks: list[int]
    points: np.ndarray
    blocks: np.ndarray
    d: int
    largest: np.ndarray
    places: DataFrame | None = None  # of the rows of cut tasks, once a mini-batch asks for them

    @property
    def place(self) -> dict[int, int]:
        return {t: k for k, t in enumerate(self.tasks)}


def prepare(packed: DataFrame, partitions: int | None = None) -> Problem:
    """packed: as ``frames.pack`` makes it. The one place where features are dealt out."""
    spark = packed.sparkSession
    packed = materialise(packed, "blocks")
    width = partitions or int(spark.conf.get("spark.sql.shuffle.partitions"))
    stats = packed.groupBy("task_id").agg(
        F.sum(F.size("ys")).alias("n"), F.count("*").alias("b"), F.max(F.size(F.col("xs")[0])).alias("d"), F.max(F.array_max("norms")).alias("r")
    ).orderBy("task_id")
    rows = stats.collect()  # a row per task; bounded with the weights
    d = max((r.d for r in rows), default=0)
    if len(rows) * d > DRIVER_CELLS:
        raise ValueError(f"{len(rows)} tasks of {d} features; more than {DRIVER_CELLS} numbers on the driver")
    dealt = packed.repartition(width, "task_id", "block_id").persist()
    return Problem(spark, dealt, [r.task_id for r in rows], np.array([r.n for r in rows]), np.array([r.b for r in rows]), d, np.array([r.r for r in rows]))


@dataclass
class State:
    """duals: a stored table (None: all zero). v: the shared vectors, a row per task."""

    v: np.ndarray
    duals: DataFrame | None = None
    stored: DataFrame | None = None  # the table of the round that duals are a part of


@dataclass
class FitResult:
    weights: np.ndarray
    relation: Relation
    problem: Problem
    state: State
    history: list[dict] = field(default_factory=list)
    round_log: list[dict] = field(default_factory=list)
    average: np.ndarray | None = None

    def weights_frame(self) -> DataFrame:
        return vectors_frame(self.problem, self.weights, "w")

    def history_frame(self) -> DataFrame:
        schema = "run string, outer int, round int, primal double, dual double, gap double"
        return self.problem.spark.createDataFrame([tuple(h[c] for c in ("run", "outer", "round", "primal", "dual", "gap")) for h in self.history], schema)

    def log_frame(self) -> DataFrame:
        schema = "run string, outer int, round int, task_id long, points int, steps int, theta double, dropped boolean, flops double, comm_elems long"
        names = ("run", "outer", "round", "task_id", "points", "steps", "theta", "dropped", "flops", "comm_elems")
        return self.problem.spark.createDataFrame([tuple(r[c] for c in names) for r in self.round_log], schema)


def vectors_frame(problem: Problem, x: np.ndarray, name: str) -> DataFrame:
    return problem.spark.createDataFrame([(t, [float(a) for a in row]) for t, row in zip(problem.tasks, x, strict=True)], f"task_id long, {name} array<double>")


def attach(problem: Problem, state: State, w: np.ndarray, kappa: np.ndarray, sigma: np.ndarray, profile: DataFrame | None = None) -> DataFrame:
    """Blocks with duals, weights, curvature and n: all small sides, at most DRIVER_CELLS numbers, come by broadcast."""
    rows = [(t, [float(a) for a in w[k]], float(kappa[k]), float(sigma[k]), int(problem.points[k])) for k, t in enumerate(problem.tasks)]
    small = problem.spark.createDataFrame(rows, "task_id long, w array<double>, kappa double, sigma double, n int")
    out = problem.packed.join(F.broadcast(small), "task_id")
    if profile is None:
        out = out.withColumn("speed", F.lit(1.0)).withColumn("comm_scale", F.lit(1.0))
    else:
        out = out.join(F.broadcast(profile.select("task_id", "speed", "comm_scale")), "task_id", "left").fillna(1.0, ["speed", "comm_scale"])
    if state.duals is None:
        return out.withColumn("alpha", F.array_repeat(F.lit(0.0), F.size("ys")))
    return out.join(state.duals.hint("shuffle_hash"), ["task_id", "block_id"])


def with_picks(problem: Problem, rows: DataFrame, batch: int, seed: int, round_: int) -> DataFrame:
    """Adds picked, the places within each block of the rows that its task samples: the ``batch`` (or budget) least draws of the
    whole task, however many blocks it is cut into. A task of one block draws in its own pass (picked: null). rows: with n and
    the task's budget."""
    if (problem.blocks == 1).all():
        return rows.withColumn("picked", F.lit(None).cast("array<int>"))
    if problem.places is None:
        problem.places = materialise(frames.block_places(problem.packed), "places")
    asked = rows.select("task_id", "block_id", F.least(F.lit(batch), "n", "budget").alias("k")).join(problem.places.hint("shuffle_hash"), ["task_id", "block_id"])
    found = materialise(least_draws(asked, seed, round_), "draws")  # no block sends more rows than its task samples
    chosen = frames.ranked(found, F.col("u")).where(F.col("_rank") <= F.col("k"))
    picks = materialise(chosen.groupBy("task_id", "block_id").agg(F.sort_array(F.collect_list("at")).alias("picked")), "picks")
    discard(found)
    return rows.join(picks.hint("shuffle_hash"), ["task_id", "block_id"], "left").withColumn("picked", F.coalesce("picked", F.array().cast("array<int>")))


def run_round(
    problem: Problem, state: State, relation: Relation, loss: Loss, policy, sigma: np.ndarray, outer: int, round_: int, seed: int = 0,
    gamma: float = 1.0, order: str = "cyclic", profile: DataFrame | None = None, stale: int | None = None, run: str = "fit",
) -> tuple[State, dict, list[dict]]:
    """One round from ``state``. The history entry describes the state it started from; the log has a row per task."""
    m = len(problem.tasks)
    w = relation.mix(state.v)
    rows = attach(problem, state, w, relation.kappa(m), sigma, profile)
    plan = policy.plan(outer, round_, int(problem.points.min()), seed)
    rows = rows.withColumn("dropped", plan.dropped).withColumn("theta", plan.theta).withColumn("budget", plan.budget)
    if stale is not None:
        rows = with_picks(problem, rows, stale, seed, round_)
    share = F.expr("CAST((CAST(budget AS BIGINT) * size(ys) + n - 1) div n AS INT)")  # a task's blocks divide its budget, in whole numbers
    rows = rows.withColumn("budget", F.when(F.col("budget") >= NO_LIMIT, F.col("budget")).otherwise(share))
    done = materialise(arrow_pass(rows, loss, order, seed, round_, gamma, stale), "round")
    per_task = done.groupBy("task_id").agg(
        F.collect_list("dv").alias("dvs"), F.sum("steps").alias("steps"), F.max("theta").alias("theta"), F.max("dropped").alias("dropped"),
        F.sum("loss").alias("loss"), F.sum("conjugate").alias("conjugate"), F.sum("points").alias("points"),
    ) if (problem.blocks == 1).all() else _reduced(done)
    place = problem.place
    dv = np.zeros_like(state.v)
    primal = dual = 0.0
    log = []
    for r in sorted(per_task.collect(), key=lambda r: r.task_id):  # d numbers per task, bounded by DRIVER_CELLS
        dv[place[r.task_id]] = np.sum(np.array(r.dvs), axis=0)
        primal += r.loss
        dual += r.conjugate
        elems = 0 if r.dropped else 2 * problem.d
        log.append(
            {"run": run, "outer": outer, "round": round_, "task_id": r.task_id, "points": r.points, "steps": r.steps, "theta": float(r.theta), "dropped": r.dropped,
             "flops": 4.0 * problem.d * r.steps, "comm_elems": elems}
        )
    primal += relation.penalty(w)
    dual += relation.conjugate(state.v)
    history = {"run": run, "outer": outer, "round": round_, "primal": primal, "dual": dual, "gap": primal + dual}
    return State(state.v + dv, done.select("task_id", "block_id", "alpha"), done), history, log


def _reduced(done: DataFrame) -> DataFrame:
    """Sums by task and coordinate, combined before the shuffle; for tasks of many blocks."""
    from taskmesh.operators.vector_aggregates import vector_sum

    sums = done.groupBy("task_id").agg(
        F.sum("steps").alias("steps"), F.max("theta").alias("theta"), F.max("dropped").alias("dropped"), F.sum("loss").alias("loss"), F.sum("conjugate").alias("conjugate"),
        F.sum("points").alias("points"),
    )
    return sums.join(vector_sum(done, ["task_id"], "dv").select("task_id", F.array("dv").alias("dvs")), "task_id")


@dataclass(frozen=True)
class StopRule:
    gap: float | None = None
    rounds: int = 20

    def holds(self, history: list[dict]) -> bool:
        return self.gap is not None and bool(history) and history[-1]["gap"] <= self.gap


def update_weights(
    problem: Problem, relation: Relation, loss: Loss, rounds: int = 20, policy=None, sigma: str | float = "spectral", gamma: float = 1.0, order: str = "cyclic", seed: int = 0,
    state: State | None = None, outer: int = 0, stop: StopRule | None = None, average_from: int | None = None, profile: DataFrame | None = None, stale: int | None = None,
    monitor: bool = True, run: str = "fit",
) -> FitResult:
    """Rounds with the relation fixed. monitor: raises where the dual, minimised, rises by more than rounding although sigma
    should be safe, and with a fixed sigma too, since an unsafe one diverges. average_from: keeps the mean of v over later rounds."""
    m = len(problem.tasks)
    policy = policy or WorkBudget(passes=1.0)
    state = state or State(np.zeros((m, problem.d)))
    parallel = np.ones(m) if stale is not None else problem.blocks  # a mini-batch is stale as a whole, in one block or many
    per_task = relation.sigma(m, sigma, gamma) * parallel
    history, log, total, counted = [], [], np.zeros_like(state.v), 0
    for h in range(rounds):
        new, entry, rows = run_round(problem, state, relation, loss, policy, per_task, outer, h, seed, gamma, order, profile, stale, run)
        history.append(entry)
        log += rows
        if monitor and stale is None and len(history) > 1 and entry["dual"] > history[-2]["dual"] + 1e-6 * (1 + abs(history[-2]["dual"])):
            raise ArithmeticError(f"the dual rose in round {h - 1}: sigma is too small")
        if stop and stop.holds(history):
            break
        if h and state.stored is not None:
            discard(state.stored)  # a round of this run, which the next one has replaced
        state = new
        if average_from is not None and h >= average_from:
            total, counted = total + state.v, counted + 1
    else:
        history.append(measure(problem, state, relation, loss, outer, rounds, run))
    average = relation.mix(total / counted) if counted else None
    return FitResult(relation.mix(state.v), relation, problem, state, history, log, average)


def measure(problem: Problem, state: State, relation: Relation, loss: Loss, outer: int = 0, round_: int = 0, run: str = "fit") -> dict:
    """Primal, dual and gap of a state, by plain column expressions."""
    from taskmesh.functions.vectors import dot

    m = len(problem.tasks)
    w = relation.mix(state.v)
    rows = attach(problem, state, w, relation.kappa(m), np.ones(m))
    points = rows.select("w", F.explode(F.arrays_zip("xs", "ys", "alpha")).alias("z"))
    sums = points.agg(F.sum(loss.value_column(dot("w", "z.xs"), F.col("z.ys"))).alias("p"), F.sum(loss.conjugate_column(F.col("z.alpha"), F.col("z.ys"))).alias("q")).first()
    primal, dual = (sums.p or 0.0) + relation.penalty(w), (sums.q or 0.0) + relation.conjugate(state.v)
    return {"run": run, "outer": outer, "round": round_, "primal": primal, "dual": dual, "gap": primal + dual}


def fit_multitask(
    problem: Problem, relation: Relation, loss: Loss, outer: int = 3, rounds: int | Callable[[int], int] = 10, policy=None, sigma: str | float | Callable = "spectral",
    seed: int = 0, tolerance: float = 0.0, gamma: float = 1.0, profile: DataFrame | None = None, first: Relation | None = None, run: str = "fit",
) -> FitResult:
    """The alternation: weights by rounds, then the relation from the weights, which needs no data. ``first``: the relation of
    the first step (default: independent tasks). Duals and shared vectors are kept across steps: they do not depend on it."""
    from taskmesh.operators.relations import IndependentRelation

    current = first or IndependentRelation(lam2=relation.lam1 + relation.lam2)
    state, history, log, before, fit = None, [], [], None, None
    for i in range(outer):
        h = rounds(i) if callable(rounds) else rounds
        s = sigma(current) if callable(sigma) else sigma
        fit = update_weights(problem, current, loss, h, policy, s, gamma, seed=seed, state=state, outer=i, profile=profile, run=run)
        state = fit.state
        history += fit.history
        log += fit.round_log
        value = history[-1]["primal"]
        if before is not None and abs(before - value) <= tolerance * (1 + abs(before)):
            break
        before = value
        if i + 1 < outer:
            current = relation.update(fit.weights)
    return FitResult(fit.weights, current, problem, state, history, log)


def node_profile(problem: Problem, seed: int = 0, slowest: float = 0.25) -> DataFrame:
    """Speeds and network scales of simulated nodes, by hash."""
    rows = [(t, slowest + (1 - slowest) * uniform_for("speed", seed, t), 0.5 + uniform_for("net", seed, t)) for t in problem.tasks]
    return problem.spark.createDataFrame(rows, "task_id long, speed double, comm_scale double")

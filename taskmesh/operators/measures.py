"""Accuracy and cost: prediction errors, objectives, accuracy of local solutions, bounds on rounds, and simulated time."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from taskmesh.functions.vectors import dot, norm2
from taskmesh.operators.local import _rows, block_arrays, solve_block, subproblem
from taskmesh.operators.losses import Loss
from taskmesh.operators.relations import Relation
from taskmesh.operators.solver import Problem, State, attach, measure
from taskmesh.operators.vector_aggregates import vector_sum

NETWORKS = {"wifi": 10.0, "lte": 100.0, "3g": 1000.0}


def score(points: DataFrame, weights: DataFrame) -> DataFrame:
    """points with z, the product with their task's weights (task_id, w)."""
    return points.join(weights, "task_id").withColumn("z", dot("features", "w"))


def task_error(points: DataFrame, weights: DataFrame) -> DataFrame:
    """Per task the number of points and the share of wrong signs; z = 0 counts as +1."""
    wrong = F.when(F.col("z") >= 0, 1.0).otherwise(-1.0) != F.col("label")
    return score(points, weights).groupBy("task_id").agg(F.count("*").alias("n_test"), F.avg(wrong.cast("double")).alias("error"))


def mean_task_error(errors: DataFrame) -> DataFrame:
    """Tasks weigh alike, whatever their size."""
    return errors.agg(F.avg("error").alias("error"), F.count("*").alias("tasks"))


def summarize_trials(trials: DataFrame) -> DataFrame:
    """Mean and standard error over trials by model. trials: model, trial, error."""
    return trials.groupBy("model").agg(F.avg("error").alias("mean"), (F.stddev_samp("error") / F.sqrt(F.count("*"))).alias("se"), F.count("*").alias("trials"))


def primal_objective(points: DataFrame, weights: DataFrame, relation: Relation, loss: Loss, order: list[int]) -> float:
    total = score(points, weights).agg(F.sum(loss.value_column(F.col("z"), F.col("label")))).first()[0] or 0.0
    by_task = {r.task_id: r.w for r in weights.collect()}
    return total + relation.penalty(np.array([by_task[t] for t in order]))


def optimality(problem: Problem, state: State, relation: Relation, loss: Loss) -> DataFrame:
    """primal, dual and gap of a state: its sums over points are one aggregate, the relation's parts one number each."""
    entry = measure(problem, state, relation, loss)
    return problem.spark.createDataFrame([(entry["primal"], entry["dual"], entry["gap"])], "primal double, dual double, gap double")


def theta_frame(problem: Problem, state: State, after: State, relation: Relation, loss: Loss, sigma: np.ndarray, passes: int = 300) -> DataFrame:
    """task_id, theta of each task's last change: what is left of the local subproblem over what there was; 0 / 0 is 0, and the
    worst block counts. Each block's subproblem is solved nearly exactly where the block is, so it is for probing only."""
    rows = attach(problem, state, relation.mix(state.v), relation.kappa(len(problem.tasks)), sigma)
    rows = rows.join(after.duals.withColumnRenamed("alpha", "moved").hint("shuffle_hash"), ["task_id", "block_id"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            norms, begun, moved = (_rows(b.column(c)) for c in ("norms", "alpha", "moved"))
            curves = b.column("sigma").to_numpy(zero_copy_only=False) * b.column("kappa").to_numpy(zero_copy_only=False)
            found = []
            for k, (x, y, w) in enumerate(block_arrays(b)):
                a, curve, n = begun[k].astype(float), float(curves[k]), len(y)
                best, _, _, _ = solve_block(loss, x, y, norms[k], a, w, curve, passes * n, 1e-12, np.arange(n))
                least, there, left = (subproblem(loss, x, y, a, d, w, curve) for d in (best - a, np.zeros(n), moved[k] - a))
                found.append(0.0 if there - least <= 1e-12 else max(0.0, (left - least) / (there - least)))
            yield pa.RecordBatch.from_arrays([b.column("task_id"), pa.array(found, pa.float64())], ["task_id", "theta"])

    names = ["task_id", "xs", "ys", "norms", "alpha", "moved", "w", "kappa", "sigma"]
    return rows.select(*names).mapInArrow(run, "task_id long, theta double").groupBy("task_id").agg(F.max("theta").alias("theta"))


def measured_theta(problem: Problem, state: State, after: State, relation: Relation, loss: Loss, sigma: np.ndarray, passes: int = 300) -> dict[int, float]:
    """``theta_frame`` as a dictionary, one number a task."""
    return {r.task_id: r.theta for r in theta_frame(problem, state, after, relation, loss, sigma, passes).collect()}


def subproblem_values(rows: DataFrame, loss: Loss) -> DataFrame:
    """task_id, value of each task's local subproblem, inside the JVM. rows: blocks with xs, ys, alpha, delta, w, kappa, sigma."""
    points = rows.select("task_id", "w", (F.col("kappa") * F.col("sigma")).alias("curve"), F.explode(F.arrays_zip("xs", "ys", "alpha", "delta")).alias("p"))
    points = points.select("task_id", "w", "curve", F.col("p.xs").alias("x"), F.col("p.ys").alias("y"), F.col("p.alpha").alias("a"), F.col("p.delta").alias("d"))
    linear = loss.conjugate_column(F.col("a") + F.col("d"), F.col("y")) + F.col("d") * dot("x", "w")
    sums = points.groupBy("task_id").agg(F.sum(linear).alias("linear"), F.max("curve").alias("curve"))
    moved = vector_sum(points.select("task_id", F.transform("x", lambda v: v * F.col("d")).alias("xd")), ["task_id"], "xd")
    return sums.join(moved, "task_id").select("task_id", (F.col("linear") + 0.5 * F.col("curve") * norm2("xd")).alias("value"))


def assumption_report(log: DataFrame) -> DataFrame:
    """Per task the share of dropped rounds and the mean accuracy of the others; then the greatest of both and what they imply."""
    per_task = log.groupBy("task_id").agg(F.avg(F.col("dropped").cast("double")).alias("p"), F.avg(F.when(~F.col("dropped"), F.col("theta"))).alias("theta"))
    top = per_task.agg(F.max("p").alias("p_max"), F.max("theta").alias("theta_max"))
    return top.select("p_max", "theta_max", (F.col("p_max") + (1 - F.col("p_max")) * F.col("theta_max")).alias("theta_bar"))


def smooth_constant(problem: Problem, relation: Relation, mu: float, sigma: float) -> float:
    """s of the bound for smooth losses: mu / (mu + sigma * max kappa * |X|^2), |X|^2 bounded by the sum of squared norms' largest times n."""
    kappa = relation.kappa(len(problem.tasks))
    return mu / (mu + sigma * float((kappa * problem.largest * problem.points).max()))


def rounds_bound_smooth(n: int, epsilon: float, theta_bar: float, s: float) -> int:
    return math.ceil(math.log(n / epsilon) / ((1 - theta_bar) * s))


def rounds_bound_lipschitz(n: int, epsilon: float, theta_bar: float, lipschitz: float, sigma: float, sigma_prime: float, start_gap: float, normalization: str = "printed") -> tuple[int, int]:
    """Rounds before averaging starts, and rounds in all. normalization: 'printed' has the square of n, 'sum' has not."""
    n2 = n * n if normalization == "printed" else 1
    a = lipschitz**2 * sigma * sigma_prime
    h0 = max(0.0, 1 + math.log(max(1e-300, 2 * n2 * start_gap / (4 * a))) / (1 - theta_bar))
    first = math.ceil(h0 + 16 * a / ((1 - theta_bar) * n2 * epsilon))
    return first, first + math.ceil(2 / (1 - theta_bar) * max(1.0, 2 * a / (n2 * epsilon)))


def simulated_time(log: DataFrame, rho: float, profile: DataFrame | None = None) -> DataFrame:
    """Cumulative time by run, outer and round: each round waits for its slowest node's steps and one answer, whose numbers cost rho each."""
    if profile is not None:
        log = log.join(profile.select("task_id", "speed", "comm_scale"), "task_id", "left")
    speed = F.coalesce(F.col("speed"), F.lit(1.0)) if profile is not None else F.lit(1.0)
    net = F.coalesce(F.col("comm_scale"), F.lit(1.0)) if profile is not None else F.lit(1.0)
    node = F.col("flops") / speed + F.lit(float(rho)) * F.col("comm_elems") * net
    per_round = log.groupBy("run", "outer", "round").agg(F.max(node).alias("seconds"), F.sum("comm_elems").alias("comm_elems"), F.sum("flops").alias("flops"))
    time = F.sum("seconds").over(Window.partitionBy("run").orderBy("outer", "round").rowsBetween(Window.unboundedPreceding, 0))
    return per_round.withColumn("sim_time", time)


def curve(history: DataFrame, times: DataFrame, best: float, column: str = "primal", sign: float = 1.0) -> DataFrame:
    """Suboptimality over simulated time; the state after round h is measured at the start of round h + 1."""
    at = times.select("run", "outer", (F.col("round") + 1).alias("round"), "sim_time")
    return history.join(at, ["run", "outer", "round"], "left").select("run", "outer", "round", F.coalesce("sim_time", F.lit(0.0)).alias("sim_time"), (F.col(column) * sign - best).alias("suboptimality"))


def time_to_target(curves: DataFrame, epsilon: float) -> DataFrame:
    """First time and round with a suboptimality of at most epsilon, by run; null if it never is."""
    met = F.col("suboptimality") <= epsilon
    return curves.groupBy("run").agg(F.min(F.when(met, F.col("sim_time"))).alias("sim_time"), F.min(F.when(met, F.col("round"))).alias("rounds"))


def straggler_report(log: DataFrame) -> DataFrame:
    """Per run and round the largest node's work over the median one's."""
    worked = log.where(~F.col("dropped"))
    stats = worked.groupBy("run", "outer", "round").agg(F.max("flops").alias("most"), F.expr("percentile(flops, 0.5)").alias("median"))
    return stats.withColumn("ratio", F.col("most") / F.when(F.col("median") > 0, F.col("median")))


def communication(log: DataFrame) -> DataFrame:
    return log.groupBy("run").agg(F.sum("comm_elems").alias("comm_elems"), F.sum("flops").alias("flops"), F.max("round").alias("last_round"))

"""The local pass: coordinate steps on one block's subproblem, in an Arrow worker or inside the JVM.

A block's row carries its points, duals, the task's weights w, kappa, sigma, a budget and an accuracy. The pass keeps
u = w + sigma * kappa * X * delta, so a step needs one product. Dropped nodes come back unchanged. Both forms take
coordinates in the same order and add in the same order, so they agree to the last digit where Python's sums allow.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from taskmesh.functions.draws import uniform_for
from taskmesh.operators.losses import Loss
from taskmesh.operators.policies import NO_LIMIT

PASS_SCHEMA = (
    "task_id long, block_id int, alpha array<double>, dv array<double>, steps int, theta double, dropped boolean, "
    "loss double, conjugate double, points int, smooth double"
)


def subproblem(loss: Loss, x: np.ndarray, y: np.ndarray, alpha: np.ndarray, delta: np.ndarray, w: np.ndarray, curve: float) -> float:
    """Value without the constant: conjugates, the linear term and half the curvature's square. curve: sigma * kappa."""
    xd = x.T @ delta
    return float(np.sum(loss.conjugate(alpha + delta, y)) + w @ xd + 0.5 * curve * (xd @ xd))


def local_gap(loss: Loss, x: np.ndarray, y: np.ndarray, alpha: np.ndarray, u: np.ndarray) -> float:
    """Primal minus dual value of the local subproblem at the running model: an upper bound of what is left to gain."""
    z = x @ u
    return float(np.sum(loss.value(z, y) + loss.conjugate(alpha, y) + alpha * z))


def solve_block(
    loss: Loss, x: np.ndarray, y: np.ndarray, norms: np.ndarray, alpha: np.ndarray, w: np.ndarray, curve: float, budget: int, theta: float, order: np.ndarray
) -> tuple[np.ndarray, np.ndarray, int, float]:
    """New duals, X * delta, steps taken, and an upper bound of the accuracy reached (0 where accuracy was not asked).
    Without a limit and without an accuracy to reach, it is one pass."""
    if theta <= 0 and budget >= NO_LIMIT:
        budget = len(y)
    alpha, u, steps, n = alpha.copy(), w.astype(float).copy(), 0, len(y)
    start = local_gap(loss, x, y, alpha, u) if theta > 0 else 0.0
    reached = 0.0
    if theta > 0 and start <= 1e-12:
        return alpha, np.zeros_like(u), 0, 0.0
    begun = alpha.copy()
    step = loss.step
    while steps < budget and n:
        for i in order:
            if steps >= budget:
                break
            xi = x[i]
            new = step(float(alpha[i]), float(y[i]), float(xi @ u), curve * float(norms[i]))
            change = new - alpha[i]
            if change:
                u += (curve * change) * xi
                alpha[i] = new
            steps += 1
        if theta > 0:
            # What the pass gained is known; what is left is at most the gap: theta <= left / (gained + left).
            left = local_gap(loss, x, y, alpha, u)
            gained = subproblem(loss, x, y, begun, np.zeros(n), w, curve) - subproblem(loss, x, y, begun, alpha - begun, w, curve)
            reached = max(0.0, left) / max(gained + max(0.0, left), 1e-300)
            if reached <= theta:
                break
    return alpha, x.T @ (alpha - begun), steps, reached


def visiting_order(n: int, order: str, seed: tuple[int, ...]) -> np.ndarray:
    """Rows in order, or in one of the permutations that the seed names."""
    return np.arange(n) if order == "cyclic" else np.random.default_rng([s & 0xFFFFFFFF for s in seed]).permutation(n)


def sampled_rows(n: int, names: tuple[int, ...]) -> np.ndarray:
    """All rows in the order of portable draws by seed, round, task, block and row: the first of them are a sample."""
    return np.argsort([uniform_for("batch", *names, i) for i in range(n)], kind="stable")


def least_draws(rows: DataFrame, seed: int, round_: int) -> DataFrame:
    """rows: task_id, block_id, k, places. Of each block the k rows with the least draws of seed, round, task and place, where the
    draws are those of the whole task as one block: task_id, block_id, k, at (in the block), row_id (the place in the task), u."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            get = {n: b.column(n).to_pylist() for n in ("task_id", "block_id", "k")}
            for task, block, k, places in zip(*get.values(), _rows(b.column("places")), strict=True):
                u = np.array([uniform_for("batch", seed, round_, task, 0, int(i)) for i in places])
                at = np.lexsort((places, u))[:k]
                n = len(at)
                yield pa.RecordBatch.from_arrays(
                    [pa.array([task] * n, pa.int64()), pa.array([block] * n, pa.int32()), pa.array([k] * n, pa.int32()), pa.array(at, pa.int32()), pa.array(places[at], pa.int64()), pa.array(u[at], pa.float64())],
                    ["task_id", "block_id", "k", "at", "row_id", "u"],
                )

    return rows.select("task_id", "block_id", "k", "places").mapInArrow(run, "task_id long, block_id int, k int, at int, row_id long, u double")


def block_arrays(batch: pa.RecordBatch) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Points, labels and weights of each block, as views of the batch's own numbers. Columns: xs, ys, w."""
    points = batch.column("xs").flatten().flatten().to_numpy(zero_copy_only=False).astype(float)
    at = 0
    for y, w in zip(_rows(batch.column("ys")), _rows(batch.column("w")), strict=True):
        n, d = len(y), len(w)
        yield points[at : at + n * d].reshape(n, d), y.astype(float), w.astype(float)
        at += n * d


def _rows(column: pa.Array) -> list[np.ndarray]:
    values, offsets = column.flatten().to_numpy(zero_copy_only=False), column.offsets.to_numpy()
    return [values[a - offsets[0] : b - offsets[0]] for a, b in zip(offsets[:-1], offsets[1:], strict=True)]


def arrow_pass(rows: DataFrame, loss: Loss, order: str = "cyclic", seed: int = 0, round_: int = 0, gamma: float = 1.0, stale: int | None = None) -> DataFrame:
    """rows: task_id, block_id, xs, ys, norms, alpha, w, kappa, sigma, budget, theta, dropped. See PASS_SCHEMA.

    loss, conjugate: sums over the block at the state before the pass. stale: mini-batch form; so many coordinates, drawn
    without replacement, all step from the same model, and their moves are scaled by gamma. picked: the drawn ones, where a
    task is cut into blocks; null: they are drawn here."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            get = {n: b.column(n).to_pylist() for n in ("task_id", "block_id", "kappa", "sigma", "budget", "theta", "dropped")}
            norms, alphas = (_rows(b.column(c)) for c in ("norms", "alpha"))
            picked = [None] * b.num_rows if stale is None else b.column("picked").to_pylist()
            out: list[list] = [[] for _ in range(9)]
            for k, (x, y, w) in enumerate(block_arrays(b)):
                alpha, n, d = alphas[k].astype(float), len(y), len(w)
                z = x @ w
                sums = float(np.sum(loss.value(z, y))), float(np.sum(loss.conjugate(alpha, y)))
                curve = get["sigma"][k] * get["kappa"][k]
                if get["dropped"][k] or not n:
                    new, dv, steps, theta = alpha, np.zeros(d), 0, 1.0
                else:
                    names = (seed, round_, get["task_id"][k], get["block_id"][k])
                    if stale is None:
                        visit = visiting_order(n, order, names)
                        new, dv, steps, theta = solve_block(loss, x, y, norms[k], alpha, w, curve, get["budget"][k], get["theta"][k], visit)
                        new, dv = alpha + gamma * (new - alpha), gamma * dv
                    else:
                        some = sampled_rows(n, names)[: min(stale, n, get["budget"][k])] if picked[k] is None else np.array(picked[k], int)
                        moved = np.array([loss.step(float(alpha[i]), float(y[i]), float(z[i]), curve * float(norms[k][i])) for i in some])
                        delta = np.zeros(n)
                        delta[some] = gamma * (moved - alpha[some])
                        new, dv, steps, theta = alpha + delta, x.T @ delta, len(some), 0.0
                for column, value in zip(out, (new, dv, steps, theta, get["dropped"][k], *sums, n, float(norms[k].max() if n else 0.0)), strict=True):
                    column.append(value)
            vectors = pa.list_(pa.float64())
            kinds = (vectors, vectors, pa.int32(), pa.float64(), pa.bool_(), pa.float64(), pa.float64(), pa.int32(), pa.float64())
            yield pa.RecordBatch.from_arrays(
                [b.column("task_id"), b.column("block_id"), *[pa.array(v, t) for v, t in zip(out, kinds, strict=True)]],
                ["task_id", "block_id", "alpha", "dv", "steps", "theta", "dropped", "loss", "conjugate", "points", "smooth"],
            )

    names = ["task_id", "block_id", "xs", "ys", "norms", "alpha", "w", "kappa", "sigma", "budget", "theta", "dropped"]
    names += [] if stale is None else ["picked"]
    return rows.select(*names).mapInArrow(run, PASS_SCHEMA)


def expression_pass(loss: Loss) -> Column:
    """One pass over the block's rows in order, as an expression over xs, ys, norms, alpha, w, kappa, sigma and budget: a
    struct of u, a (the new duals) and k (steps). It keeps the rows' partitioning and needs no Python."""
    points = F.arrays_zip("xs", "ys", "norms", "alpha")
    curve = F.col("sigma") * F.col("kappa")
    start = F.struct(F.col("w").alias("u"), F.array().cast("array<double>").alias("a"), F.lit(0).alias("k"))

    def step(state: Column, p: Column) -> Column:
        # An array of one number stands for a variable, so the product and the new dual are worked out once a step.
        xu = F.array(F.aggregate(F.zip_with(p["xs"], state["u"], lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x))
        new = F.transform(xu, lambda z: F.when(state["k"] < F.col("budget"), loss.step_column(p["alpha"], p["ys"], z, curve * p["norms"])).otherwise(p["alpha"]))
        moved = lambda n: F.struct(
            F.zip_with(state["u"], p["xs"], lambda a, x: a + curve * (n - p["alpha"]) * x).alias("u"),
            F.concat(state["a"], F.array(n)).alias("a"),
            (state["k"] + F.when(state["k"] < F.col("budget"), 1).otherwise(0)).alias("k"),
        )
        return F.transform(new, moved)[0]

    return F.aggregate(points, start, step)

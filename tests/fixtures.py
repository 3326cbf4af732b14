"""Tiny hash-made task frames."""

import numpy as np

from taskmesh.functions import uniform_for

SIZES = (4, 9, 15, 7, 30, 12)


def six_tasks(spark, d=5, real=False, sizes=SIZES):
    """Six tasks of two true clusters; labels are signs of planted models, or real numbers near them."""
    rows = []
    for t, n in enumerate(sizes):
        base = np.array([uniform_for("base", t % 2, j) - 0.5 for j in range(d)])
        u = base + 0.2 * np.array([uniform_for("own", t, j) - 0.5 for j in range(d)])
        for i in range(n):
            x = np.array([2 * uniform_for("x", t, i, j) - 1 for j in range(d)])
            y = float(x @ u)
            rows.append((t, i, [float(v) for v in x], y * 3 if real else (1.0 if y >= 0 else -1.0)))
    return spark.createDataFrame(rows, "task_id long, row_id long, features array<double>, label double")


def arrays(df):
    by_task = {}
    for r in df.orderBy("task_id", "row_id").collect():
        by_task.setdefault(r.task_id, ([], []))
        by_task[r.task_id][0].append(list(r.features))
        by_task[r.task_id][1].append(r.label)
    return {t: (np.array(x), np.array(y)) for t, (x, y) in by_task.items()}


def dense_squared_optimum(data, gram):
    """The exact weights for squared losses: one linear system over all tasks."""
    m, d = len(data), next(iter(data.values()))[0].shape[1]
    h = 2 * np.kron(gram, np.eye(d))
    g = np.zeros(m * d)
    for k, t in enumerate(sorted(data)):
        x, y = data[t]
        h[k * d : (k + 1) * d, k * d : (k + 1) * d] += x.T @ x
        g[k * d : (k + 1) * d] = x.T @ y
    return np.linalg.solve(h, g).reshape(m, d)

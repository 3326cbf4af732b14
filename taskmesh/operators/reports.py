"""Reports over errors and scores: roll-ups, cubes, ranks, pivots, temporal features, and use of models."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from taskmesh.functions.vectors import dot
from taskmesh.operators.vector_aggregates import vector_mean


def error_rollup(errors: DataFrame, *levels: str) -> DataFrame:
    return errors.rollup(*levels).agg(F.avg("error").alias("error"), F.count("*").alias("tasks"), F.grouping_id().alias("level"))


def error_cube(errors: DataFrame, *levels: str) -> DataFrame:
    return errors.cube(*levels).agg(F.avg("error").alias("error"), F.count("*").alias("tasks"), F.grouping_id().alias("level"))


def error_sets(errors: DataFrame, sets: list[list[str]], columns: list[str]) -> DataFrame:
    return errors.groupingSets([[F.col(c) for c in s] for s in sets], *[F.col(c) for c in columns]).agg(F.avg("error").alias("error"), F.count("*").alias("tasks"))


def rank_tasks(errors: DataFrame) -> DataFrame:
    w = Window.orderBy(F.desc("error"), "task_id")
    ties = Window.orderBy(F.desc("error"))
    return errors.select("task_id", "error", F.row_number().over(w).alias("place"), F.rank().over(ties).alias("rank"), F.dense_rank().over(ties).alias("dense"), F.percent_rank().over(ties).alias("percent"), F.cume_dist().over(ties).alias("cumulative"))


def hardest_tasks(errors: DataFrame, k: int = 10) -> DataFrame:
    return errors.orderBy(F.desc("error"), "task_id").limit(k)


def pivot_errors(errors: DataFrame, models: list[str]) -> DataFrame:
    """task_id by model, errors as they are; models are named, so the plan needs no extra pass."""
    return errors.groupBy("task_id").pivot("model", models).agg(F.first("error"))


def best_config(scored: DataFrame, keys: list[str]) -> DataFrame:
    """The least error by key; of equals, the larger lam."""
    return scored.groupBy(*keys).agg(F.min_by("lam", F.struct("error", -F.col("lam"))).alias("lam"), F.min("error").alias("error"))


def distinct_tasks(df: DataFrame, rsd: float = 0.02) -> DataFrame:
    return df.agg(F.countDistinct("task_id").alias("exact"), F.approx_count_distinct("task_id", rsd).alias("approximate"))


def time_quantiles(log: DataFrame, column: str = "flops", accuracy: int = 10_000) -> DataFrame:
    return log.groupBy("round").agg(F.expr(f"percentile({column}, array(0.5, 0.9, 0.99))").alias("exact"), F.percentile_approx(column, [0.5, 0.9, 0.99], accuracy).alias("approximate"))


def temporal_features(events: DataFrame) -> DataFrame:
    """Previous and next value, a moving mean of three, and a count over the last hour, by user."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    hour = Window.partitionBy("user_id").orderBy(F.unix_seconds(F.col("ts").cast("timestamp"))).rangeBetween(-3600, 0)
    return events.select(
        "event_id", "user_id", F.lag("value").over(w).alias("before"), F.lead("value").over(w).alias("after"), F.avg("value").over(w.rowsBetween(-2, 0)).alias("moving"), F.count("*").over(hour).alias("last_hour")
    )


def dft(values: Column, n: int, k: int) -> Column:
    """Magnitudes of the first k frequencies of an array of n numbers."""
    import math

    def part(trig, f: int) -> Column:
        return F.aggregate(F.zip_with(values, F.array(*[F.lit(trig(2 * math.pi * f * t / n)) for t in range(n)]), lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x)

    return F.array(*[F.sqrt(F.pow(part(math.cos, f), 2) + F.pow(part(math.sin, f), 2)) for f in range(k)])


def predict(points: DataFrame, weights: DataFrame, clusters: DataFrame | None = None) -> DataFrame:
    """z by the task's own weights; a task without any takes its cluster's mean, or the mean of all."""
    everyone = vector_mean(weights.withColumn("_all", F.lit(1)), ["_all"], "w", "w_all").drop("_all")
    out = points.join(weights, "task_id", "left").crossJoin(F.broadcast(everyone))  # one row
    if clusters is not None:
        means = vector_mean(weights.join(clusters, "task_id"), ["cluster_id"], "w", "w_cluster")
        out = out.join(clusters, "task_id", "left").join(means, "cluster_id", "left")
        return out.withColumn("z", dot("features", F.coalesce("w", "w_cluster", "w_all"))).drop("w", "w_cluster", "w_all", "cluster_id")
    return out.withColumn("z", dot("features", F.coalesce("w", "w_all"))).drop("w", "w_all")


def one_vs_rest(scores: DataFrame) -> DataFrame:
    """scores: row_id, class, z. The class with the greatest z (ties: the first by name)."""
    return scores.groupBy("row_id").agg(F.min_by("class", F.struct(-F.col("z"), F.col("class"))).alias("class"))

"""Event streams: windowed features, repeats and late events, per-user state, scoring, and rounds driven by a clock."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle

from taskmesh.functions.vectors import dot


def window_features(events: DataFrame, size: str = "2 days", slide: str | None = None, late: str | None = None) -> DataFrame:
    """Per user and tumbling or sliding window. The same plan serves a batch (late is None) and a stream with a watermark."""
    if late is not None:
        events = events.withWatermark("ts", late)
    window = F.window("ts", size, slide) if slide else F.window("ts", size)
    return events.groupBy("user_id", window.alias("w")).agg(
        F.count("*").alias("n"), F.sum("value").alias("total"), F.min("value").alias("least"), F.max("value").alias("most"),
        F.count_if(F.col("event_type") == "purchase").alias("purchases"),
    ).select("user_id", F.col("w.start").alias("start"), "n", "total", "least", "most", "purchases")


def session_features(events: DataFrame, gap: str = "6 hours", late: str | None = None) -> DataFrame:
    if late is not None:
        events = events.withWatermark("ts", late)
    s = F.session_window("ts", gap)
    return events.groupBy("user_id", s.alias("s")).agg(F.count("*").alias("n"), F.sum("value").alias("total")).select("user_id", F.col("s.start").alias("start"), F.col("s.end").alias("end"), "n", "total")


def deduplicated(events: DataFrame, late: str = "1 day") -> DataFrame:
    """One event for each id within the watermark; state older than that is let go."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def late_events(events: DataFrame, seen_until: DataFrame) -> DataFrame:
    """Batch twin of what a watermark drops: events before the user's limit. seen_until: user_id, until."""
    return events.join(seen_until, "user_id").where(F.col("ts") < F.col("until")).drop("until")


def scored(events: DataFrame, weights: DataFrame, features: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """A stream joined with fixed weights by task: task_id, features in; z and the predicted sign out."""
    return features(events).join(weights, "task_id").withColumn("z", dot("features", "w")).withColumn("predicted", F.when(F.col("z") >= 0, 1.0).otherwise(-1.0))


class RunningMoments(StatefulProcessor):
    """Count, sum and sum of squares of each user's values; a row for each batch that has the user; state ends after silence."""

    def __init__(self, silence_ms: int = 86_400_000) -> None:
        self.silence_ms = silence_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        self.moments = handle.getValueState("moments", "n long, total double, squares double")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:  # noqa: N802, N803
        n, total, squares = self.moments.get() if self.moments.exists() else (0, 0.0, 0.0)
        for part in rows:
            n, total, squares = n + len(part), total + float(part["value"].sum()), squares + float((part["value"] ** 2).sum())
        self.moments.update((n, total, squares))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "mean": [total / n], "variance": [max(0.0, squares / n - (total / n) ** 2)]})

    def close(self) -> None:
        return None


def running_moments(events: DataFrame) -> DataFrame:
    """Needs the RocksDB state store: spark.sql.streaming.stateStore.providerClass."""
    return events.groupBy("user_id").transformWithStateInPandas(RunningMoments(), "user_id long, n long, mean double, variance double", "Update", "ProcessingTime")


def clocked_rounds(answers: DataFrame, step: Callable[[int, list[int]], None], checkpoint: str, cycle: str | None = None):
    """A micro-batch is a clock cycle: tasks whose row arrived and is not dropped take part in the round, others are absent.
    step(round, tasks) runs it; the batch id makes a repeated batch recognisable."""

    def batch(frame: DataFrame, batch_id: int) -> None:
        step(batch_id, sorted(r.task_id for r in frame.where(~F.col("dropped")).select("task_id").distinct().collect()))

    writer = answers.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint)
    return (writer.trigger(processingTime=cycle) if cycle else writer.trigger(availableNow=True)).start()


def dropped_late(query) -> int:
    """Rows that a query's watermark has let go so far, from its progress."""
    return sum(int(s["numRowsDroppedByWatermark"]) for p in query.recentProgress for s in p["stateOperators"])


def solver_rounds(problem, relation, loss, policy, sigma, seed: int = 0):
    """A ``step`` for ``clocked_rounds`` that runs the solver: tasks that did not answer in a cycle are dropped from its round. A batch
    that comes again, after a restart of the stream, is not run twice. Returns the step and the list that its states go to."""
    import numpy as np

    from taskmesh.operators.policies import NeverSends, compose
    from taskmesh.operators.solver import State, run_round

    states, done = [State(np.zeros((len(problem.tasks), problem.d)))], set()

    def step(round_: int, present: list[int]) -> None:
        if round_ in done:
            return
        absent = tuple(t for t in problem.tasks if t not in set(present))
        plan = compose(policy, NeverSends(absent)) if absent else policy
        state, _, _ = run_round(problem, states[-1], relation, loss, plan, sigma, 0, round_, seed)
        done.add(round_)
        states.append(state)

    return step, states


def to_table(stream: DataFrame, path: str, checkpoint: str, mode: str = "append"):
    """All that is there now, to Parquet; a restart goes on from the checkpoint."""
    return stream.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).outputMode(mode).trigger(availableNow=True).start()


def to_memory(stream: DataFrame, name: str, mode: str = "complete"):
    return stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()

"""Many configurations at once, hot tasks, the comparison of models, and rounds driven by a stream."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from taskmesh.functions.registered import register
from taskmesh.operators import batched, frames, joins, policies
from taskmesh.operators.baselines import tune
from taskmesh.operators.losses import Hinge, Logistic, Squared
from taskmesh.operators.measures import primal_objective
from taskmesh.operators.relations import ClusterRelation, IndependentRelation
from taskmesh.operators.solver import prepare, update_weights
from taskmesh.plans import experiments, workloads
from taskmesh.sources import formats
from taskmesh.sources.simulator import NodeSimulator
from taskmesh.streaming import windows
from tests.fixtures import six_tasks

SF = "/root/testdata/sf0.01"


def everything(spark, tasks, trials=1):
    return tasks.select("task_id", "row_id", F.array(*[F.lit(0)] * trials).alias("parts"))


@pytest.mark.parametrize("loss", [Hinge(), Squared(), Logistic()])
def test_one_configuration_is_the_plain_solver(spark, loss):
    tasks = six_tasks(spark)
    relation = ClusterRelation(lam1=1.0, lam2=0.2, clusters=(0, 1, 0, 1, 0, 1))
    problem = batched.masked(tasks, everything(spark, tasks), 1)
    configs = [batched.Config(0, -1, 1.0), batched.Config(0, 0, 1.0)]  # the second holds out all that it could train on
    weights, duals = batched.fit_configs(problem, configs, [relation, relation], loss, 1, 3)
    want = update_weights(prepare(frames.pack(tasks), 2), relation, loss, 3)
    assert np.allclose(weights[0], want.weights, atol=1e-9) and not weights[1].any()
    assert all(b <= a + 1e-9 for a, b in zip(duals, duals[1:], strict=False))


def test_lots_and_blocks_change_nothing(spark):
    tasks = six_tasks(spark, real=True)
    parts = batched.trial_parts(tasks, 2, 3)
    sizes = {(r.task_id, t): sum(p >= 0 for p in ps) for r in parts.groupBy("task_id").agg(F.collect_list("parts").alias("p")).collect() for t, ps in enumerate(zip(*r.p, strict=True))}
    assert sizes[0, 0] == 3 and sizes[4, 1] == 23
    problem = batched.masked(tasks, parts, 2)
    configs = [batched.Config(t, f, lam) for t in range(2) for f in (0, 1, 2, -1) for lam in (0.1, 1.0)]
    assert [len(lot) for lot in batched.lots(problem, configs, cells=6 * 5 * 5)] == [5, 5, 5, 1]
    whole, _ = batched.fit_configs(problem, configs, [IndependentRelation(lam2=c.lam) for c in configs], Squared(), 1, 2)
    some, _ = batched.fit_configs(problem, configs[3:5], [IndependentRelation(lam2=c.lam) for c in configs[3:5]], Squared(), 1, 2)
    assert np.allclose(whole[3:5], some)
    cut = batched.masked(tasks, parts, 2, block_rows=8)
    assert cut.per_task.max() > 1
    close, _ = batched.fit_configs(cut, configs, [IndependentRelation(lam2=c.lam) for c in configs], Squared(), 1, 40)
    best, _ = batched.fit_configs(problem, configs, [IndependentRelation(lam2=c.lam) for c in configs], Squared(), 1, 40)
    assert np.abs(close - best).max() < 0.05


def test_models_compare_as_planted(spark):
    out = experiments.compare_models(workloads.event_window_tasks(spark, SF, planted=True), lambdas=(0.1, 1.0), folds=2, trials=2)
    mean = {r.model: r.error for r in out.groupBy("model").agg(F.avg("error").alias("error")).collect()}
    assert mean["multitask"] < mean["local"] < mean["global"]


def test_a_hot_task_is_spread(spark):
    df = spark.range(20_000).select(F.when(F.col("id") < 19_000, 0).otherwise(1).cast("long").alias("task_id"), F.col("id").alias("row_id"), F.array(F.rand(1)).alias("features"), F.lit(1.0).alias("label"))
    packed = frames.pack(df, 500).select("task_id", F.size("ys").alias("n")).collect()
    hot = [r.n for r in packed if r.task_id == 0]
    assert sum(hot) == 19_000 and len(hot) == 38 and max(hot) < 700
    ranks = frames.ranked(df, frames._shuffled(0, 0), lot=500).where("task_id = 0").select("_rank").collect()
    assert sorted(r._rank for r in ranks) == list(range(1, 19_001))
    train = frames.split(df).groupBy("task_id", "split").count().collect()
    assert {(r.task_id, r.split): r["count"] for r in train}[0, "train"] == 14_250
    assert {r.fold: r["count"] for r in frames.folds(df, 3).where("task_id = 1").groupBy("fold").count().collect()} == {0: 334, 1: 333, 2: 333}


def test_tuning_takes_the_fastest_setting(spark):
    problem = prepare(frames.pack(six_tasks(spark)), 2)
    relation = ClusterRelation(lam1=1.0, lam2=0.2, clusters=(0, 1, 0, 1, 0, 1))
    runs = {f"passes={p}": (lambda p=p: update_weights(problem, relation, Hinge(), 6, policies.WorkBudget(passes=p))) for p in (0.2, 4.0)}
    best = -experiments.long_run(problem, relation, Hinge(), rounds=20).history[-1]["dual"]
    name, fit, times = tune(runs, lambda f: experiments.time_to(f, 1000.0, best, 1.0))
    assert name == "passes=4.0" and times["passes=4.0"] < times["passes=0.2"]
    total = primal_objective(six_tasks(spark), fit.weights_frame(), relation, Hinge(), problem.tasks)
    assert total == pytest.approx(fit.history[-1]["primal"])


def test_state_merges_by_group(spark):
    packed = frames.pack(six_tasks(spark), 8)
    fit = update_weights(prepare(packed, 2), ClusterRelation(clusters=(0,) * 6), Hinge(), 1)
    merged = {(r.task_id, r.block_id): r.alpha for r in joins.merge_state(packed, fit.state.duals.where("task_id <> 2")).collect()}
    assert all(merged[r.task_id, r.block_id] == r.alpha for r in fit.state.duals.collect() if r.task_id != 2)
    assert all(not any(a) for (t, _), a in merged.items() if t == 2)


def test_registered_sql(spark):
    register(spark)
    row = spark.sql("SELECT vector_dot(array(1D, 2D), array(3D, 4D)) AS d, vector_axpy(2D, array(1D), array(1D)) AS a, hinge_loss(0.5D, 1D) AS h, one_against_rest('a', NULL) AS o, portable_uniform('x:1') AS u").first()
    assert (row.d, row.a, row.h, row.o) == (11.0, [3.0], 0.5, -1.0) and 0 <= row.u < 1
    assert spark.sql("SELECT vector_sum_udaf(x) FROM VALUES (array(1D, 2D)), (array(3D, 4D)) AS t(x)").first()[0] == [4.0, 6.0]


def test_select_tasks_and_one_hot(spark):
    df = spark.createDataFrame([(1, "a"), (12, "b"), (None, None)], "task_id long, c string")
    ids = lambda **k: [r.task_id for r in frames.select_tasks(df, **k).collect()]
    assert ids(pattern="^1") == [1, 12] and ids(equal=12) == [12] and ids(missing=True) == [None] and ids(between=(2, 20)) == [12]
    assert [list(r) for r in df.select(*frames.one_hot("c", ["a", "b"])).collect()] == [[1.0, 0.0], [0.0, 1.0], [0.0, 0.0]]


def test_stream_drives_the_solver_and_goes_on_after_a_restart(spark, tmp_path):
    problem = prepare(frames.pack(six_tasks(spark)), 2)
    relation = ClusterRelation(lam1=1.0, lam2=0.2, clusters=(0, 1, 0, 1, 0, 1))
    step, states = windows.solver_rounds(problem, relation, Hinge(), policies.WorkBudget(passes=1), relation.sigma(6) * problem.blocks)
    spark.dataSource.register(NodeSimulator)
    answers = spark.readStream.format("node_simulator").schema("round long, task_id long, dropped boolean").option("nodes", 6).option("drop", 0.4).load()
    for wanted in (2, 4):  # stopped, and started again from its checkpoint
        query = windows.clocked_rounds(answers, step, f"file://{tmp_path}/cp", "100 milliseconds")
        for _ in range(120):
            if len(states) > wanted or query.exception():
                break
            query.awaitTermination(1)
        query.stop()
    assert len(states) > 4
    first = experiments.update_weights(problem, relation, Hinge(), 1, policies.compose(policies.WorkBudget(passes=1), policies.DropPolicy(0.4)))
    assert np.allclose(states[1].v, first.state.v)  # the simulator's nodes drop by the same draws


def test_late_rows_are_counted(spark, tmp_path):
    import datetime as dt

    day = dt.datetime(2024, 1, 1)
    for k, days in enumerate((0, 40, 1)):  # the third file is behind the watermark
        rows = [(10 * k + i, day + dt.timedelta(days=days, hours=i), 1, "view", 1.0, "{}") for i in range(3)]
        spark.createDataFrame(rows, formats.EVENT_SCHEMA).coalesce(1).write.mode("append").parquet(f"file://{tmp_path}/events")
        query = windows.to_table(windows.window_features(formats.stream_events(spark, f"file://{tmp_path}/events"), "1 day", late="2 days"), f"file://{tmp_path}/out", f"file://{tmp_path}/cp")
        query.awaitTermination()
    assert windows.dropped_late(query) >= 1
    assert spark.read.parquet(f"file://{tmp_path}/out").agg(F.sum("n")).first()[0] == 3  # the first day; the last one is still open
    weights = spark.createDataFrame([(1, [2.0])], "task_id long, w array<double>")
    scored = windows.scored(formats.stream_events(spark, f"file://{tmp_path}/events"), weights, lambda e: e.select(F.col("user_id").alias("task_id"), F.array("value").alias("features")))
    windows.to_memory(scored, "scored_now", "append").awaitTermination()
    assert {r.z for r in spark.table("scored_now").collect()} == {2.0}

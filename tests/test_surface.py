"""Losses in both forms, relations, joins, reports, sources, streams and registered functions, on small inputs."""

import datetime as dt

import numpy as np
import pytest
from pyspark.sql import functions as F

from taskmesh.functions import portable_uniform, uniform_for
from taskmesh.functions.registered import register
from taskmesh.operators import frames, joins, reports
from taskmesh.operators import relations as rel
from taskmesh.operators.local import arrow_pass, expression_pass
from taskmesh.operators.losses import LOSSES
from taskmesh.sources import formats
from taskmesh.sources.simulator import NodeSimulator
from taskmesh.streaming import windows
from tests.fixtures import six_tasks


@pytest.mark.parametrize("name", list(LOSSES))
def test_loss_forms_agree_and_steps_minimise(spark, name):
    loss = LOSSES[name]
    rows = [(y, z, a) for y in (1.0, -1.0) for z in (-1.7, -0.3, 0.0, 0.6, 1.2) for a in (0.0, 0.4, 0.9)]
    df = spark.createDataFrame([(y, z, y * a) for y, z, a in rows], "y double, z double, alpha double")
    got = df.select("y", "z", "alpha", loss.value_column(F.col("z"), F.col("y")).alias("v"), loss.conjugate_column(F.col("alpha"), F.col("y")).alias("c")).collect()
    for r in got:
        assert r.v == pytest.approx(float(loss.value(r.z, r.y)), abs=1e-9) and r.c == pytest.approx(float(loss.conjugate(r.alpha, r.y)), abs=1e-9)
    for y, z, a in rows:
        q, start = 0.7, y * a
        new = loss.step(start, y, z, q)
        cost = lambda n: float(loss.conjugate(n, y)) + z * (n - start) + q / 2 * (n - start) ** 2  # noqa: B023, E731
        inside = [n for n in np.linspace(new - 0.2, new + 0.2, 41) if name == "squared" or (abs(n) <= 1 and (name == "absolute" or 0 <= y * n <= 1))]
        assert all(cost(new) <= cost(n) + 1e-9 for n in inside)


def test_expression_and_arrow_pass_agree(spark):
    rows = frames.pack(six_tasks(spark)).withColumn("alpha", F.array_repeat(F.lit(0.0), F.size("ys"))).withColumn("w", F.array_repeat(F.lit(0.1), 5))
    for c, v in (("kappa", 0.5), ("sigma", 2.0), ("budget", 3), ("theta", 0.0), ("dropped", False)):
        rows = rows.withColumn(c, F.lit(v))
    for name in ("hinge", "smooth_hinge", "squared", "absolute"):
        one = {r.task_id: r.s for r in rows.select("task_id", expression_pass(LOSSES[name]).alias("s")).collect()}
        for r in arrow_pass(rows, LOSSES[name]).collect():
            assert np.allclose(one[r.task_id].a, r.alpha) and np.allclose(one[r.task_id].u, 0.1 + np.array(r.dv)) and one[r.task_id].k == r.steps


def test_relations_closed_forms_and_updates(spark):
    rng = np.random.default_rng(0)
    v = rng.normal(size=(6, 3))
    c = rel.ClusterRelation(lam1=2.0, lam2=0.3, clusters=(0, 0, 1, 1, 1, 2))
    k = np.linalg.inv(2 * c.gram(6))
    assert np.allclose(c.mix(v), k @ v) and np.allclose(c.kappa(6), np.diag(k)) and np.isclose(c.sigma(6), rel.largest_ratio(k))
    assert c.sigma(6) <= c.sigma(6, "gershgorin") + 1e-9 <= c.sigma(6, "trace") + 1e-6
    w = c.mix(v)
    assert np.isclose(c.penalty(w) + c.conjugate(v), np.sum(w * v))
    shared = spark.createDataFrame([(t, row.tolist()) for t, row in enumerate(v)], "task_id long, v array<double>")
    clusters = spark.createDataFrame(list(enumerate(c.clusters)), "task_id long, cluster_id long")
    mixed = {r.task_id: r.w for r in rel.mix_frame(shared, clusters, 2.0, 0.3).collect()}
    assert all(np.allclose(mixed[t], w[t]) for t in range(6))
    assert rel.ClusterRelation(k=2).update(np.vstack([v[:3] * 0 + 5, v[3:] * 0 - 5])).clusters == (0, 0, 0, 1, 1, 1)
    cov = rel.CovarianceRelation(lam1=1.0, lam2=0.1).update(v)
    cost = lambda o: np.trace(v.T @ np.linalg.inv(o) @ v)
    for _ in range(50):
        a = rng.normal(size=(6, 6))
        o = a @ a.T + 1e-3 * np.eye(6)
        assert cost(cov.omega) <= cost(o / np.trace(o)) * 1.02
    s = rel.ConvexClusterRelation(k=2, eta=0.1).update(v).s
    assert np.isclose(np.trace(s), 2, atol=1e-3) and np.linalg.eigvalsh(s)[-1] <= 1 + 1e-9
    p = rel.SpectralClusterRelation(k=2).update(v).projector
    assert np.allclose(p @ p, p) and np.isclose(np.trace(p), 2)
    sp = rel.SparsePrecisionRelation(lam_s=0.05)
    assert sp._cost(v @ v.T, sp.update(v).omega) <= sp._cost(v @ v.T, np.eye(6))
    g = rel.GraphRelation([(0, 1, 1.0), (1, 2, 2.0)], 4)
    assert np.allclose(g.omega.sum(axis=1), 0) and g.sigma(4) >= 1


def test_frames(spark):
    df = six_tasks(spark)
    assert frames.validate(df) == 5
    with pytest.raises(ValueError):
        frames.validate(df.unionAll(df.limit(1)))
    assert frames.valid_points(df.withColumn("label", F.lit(0.5)), 5).count() == 0
    assert frames.filter_tasks(df, 10).select("task_id").distinct().count() == 3
    parts = {(r.task_id, r.split): r["count"] for r in frames.split(df).groupBy("task_id", "split").count().collect()}
    assert parts[0, "train"] == 3 and parts[4, "train"] == 23
    back = frames.explode_blocks(frames.pack(df, 4)).select("task_id", "row_id", "features", "label")
    assert sorted(map(str, back.collect())) == sorted(map(str, df.collect()))
    both = frames.composite(df, spark.createDataFrame([(0,), (1,)], "config_id int"))
    assert both.select("task_id").distinct().count() == 12
    assert uniform_for("a", 3) == pytest.approx(spark.range(1).select(portable_uniform("a", 3)).first()[0])


def test_joins(spark):
    day = dt.datetime(2024, 1, 1)
    events = spark.createDataFrame([(1, day, 5), (1, day + dt.timedelta(days=2), 6), (2, day, 7)], "k long, t timestamp, v long")
    versions = spark.createDataFrame([(1, day - dt.timedelta(days=1), 10), (1, day + dt.timedelta(days=1), 11)], "k long, s timestamp, w long")
    assert [(r.v, r.w) for r in joins.asof(events, versions, "k", "t", "s", ["w"]).orderBy("v").collect()] == [(5, 10), (6, 11), (7, None)]
    spans = spark.createDataFrame([(1, day - dt.timedelta(hours=1), day + dt.timedelta(hours=30))], "k long, a timestamp, b timestamp")
    assert [r.v for r in joins.within_intervals(events, spans, "k", "t", "a", "b").collect()] == [5]
    tasks, answers = spark.range(4).withColumnRenamed("id", "task_id"), spark.range(2).withColumnRenamed("id", "task_id")
    assert joins.reporting_tasks(tasks, answers).count() == 2 and joins.silent_tasks(tasks, answers).count() == 2
    old, new = spark.createDataFrame([(1, 1.0), (2, 2.0)], "task_id long, x double"), spark.createDataFrame([(2, 3.0), (3, 4.0)], "task_id long, x double")
    assert sorted(r.found for r in joins.reconcile(old, new, ["task_id"], "x").collect()) == ["both", "new", "old"]
    assert joins.config_grid(spark, lam=[0.1, 1.0], fold=[0, 1, 2]).count() == 6
    docs = spark.createDataFrame([(1, "a b c d e f g h i"), (2, "x b c d e f g h i j"), (3, None)], "doc_id long, text string")
    bench = spark.createDataFrame([(1, "zz b c d e f g h i")], "item_id long, text string")
    assert [r.doc_id for r in joins.decontaminate(docs, bench).orderBy("doc_id").collect()] == [3]


def test_reports(spark):
    errors = spark.createDataFrame([(1, "a", "x", 0.1), (2, "a", "y", 0.3), (3, "b", "x", 0.3)], "task_id long, g string, model string, error double")
    assert reports.error_rollup(errors, "g").count() == 3 and reports.error_cube(errors, "g", "model").count() == 8
    assert reports.error_sets(errors, [["g"], []], ["g"]).count() == 3
    assert [r.place for r in reports.rank_tasks(errors).orderBy("place").collect()] == [1, 2, 3]
    assert reports.hardest_tasks(errors, 1).first().task_id == 2
    assert reports.pivot_errors(errors, ["x", "y"]).columns == ["task_id", "x", "y"]
    points = spark.createDataFrame([(1, [1.0, 2.0]), (9, [1.0, 1.0])], "task_id long, features array<double>")
    weights = spark.createDataFrame([(1, [1.0, 1.0]), (2, [3.0, 1.0])], "task_id long, w array<double>")
    assert {r.task_id: r.z for r in reports.predict(points, weights).collect()} == {1: 3.0, 9: 3.0}
    clusters = spark.createDataFrame([(1, 0), (2, 1), (9, 1)], "task_id long, cluster_id long")
    assert {r.task_id: r.z for r in reports.predict(points, weights, clusters).collect()} == {1: 3.0, 9: 4.0}
    wave = spark.createDataFrame([([1.0, 0.0, -1.0, 0.0],)], "x array<double>").select(reports.dft(F.col("x"), 4, 3).alias("m")).first().m
    assert np.allclose(wave, [0, 2, 0], atol=1e-9)


def test_sources_and_functions(spark, tmp_path):
    weights = spark.createDataFrame([(1, [1.0, 2.0])], "task_id long, w array<double>")
    formats.save_model(weights, {"lam1": 1.0}, f"file://{tmp_path}/m")
    back, meta = formats.load_model(spark, f"file://{tmp_path}/m")
    assert back.first().w == [1.0, 2.0] and meta == {"lam1": 1.0}
    weights.select("task_id").write.csv(f"file://{tmp_path}/c")
    assert formats.load_any(spark, f"file://{tmp_path}/c", "csv", "task_id long").first().task_id == 1
    spark.dataSource.register(NodeSimulator)
    nodes = spark.read.format("node_simulator").option("nodes", 7).load()
    assert nodes.count() == 7 and nodes.where("speed BETWEEN 0.25 AND 1").count() == 7
    register(spark)
    assert spark.sql("SELECT predict_udf(array(1D, 2D), array(3D, 4D))").first()[0] == 11.0
    assert spark.sql("SELECT * FROM expand_grid(array(0.1D, 1.0D), 3)").count() == 6


def test_streams_equal_their_batch_twins(spark, tmp_path):
    day = dt.datetime(2024, 1, 1)
    rows = [(i, day + dt.timedelta(hours=5 * i), i % 3, "purchase" if i % 4 == 0 else "view", float(i), "{}") for i in range(40)]
    events = spark.createDataFrame(rows, formats.EVENT_SCHEMA)
    path = f"file://{tmp_path}/events"
    events.repartition(2).write.parquet(path)
    stream = windows.window_features(formats.stream_events(spark, path), "2 days", late="30 days")
    windows.to_memory(stream, "features_now").awaitTermination()
    batch = windows.window_features(events.withColumn("ts", F.col("ts").cast("timestamp")), "2 days")
    assert sorted(map(str, spark.table("features_now").collect())) == sorted(map(str, batch.collect()))
    twice = windows.deduplicated(formats.stream_events(spark, path).unionByName(formats.stream_events(spark, path)), "30 days")
    windows.to_table(twice, f"file://{tmp_path}/out", f"file://{tmp_path}/cp").awaitTermination()
    assert spark.read.parquet(f"file://{tmp_path}/out").count() == 40
    seen = []
    spark.dataSource.register(NodeSimulator)
    answers = spark.readStream.format("node_simulator").schema("round long, task_id long, dropped boolean").option("nodes", 6).option("drop", 0.4).load()
    query = windows.clocked_rounds(answers, lambda batch, tasks: seen.append(tasks), f"file://{tmp_path}/cp2", "100 milliseconds")
    for _ in range(100):
        if len(seen) >= 3:
            break
        query.awaitTermination(1)
    query.stop()
    assert seen[0] == [t for t in range(6) if uniform_for("drop", 0, 0, 0, t) >= 0.4]

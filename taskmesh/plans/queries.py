"""Registered queries of the engine's own methods, each a small plan over the given tables."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from taskmesh.functions.draws import portable_uniform, uniform_for
from taskmesh.functions.vectors import norm2
from taskmesh.operators import frames, joins, measures, policies
from taskmesh.operators.local import arrow_pass, expression_pass
from taskmesh.operators.losses import Absolute, Hinge, Logistic, Loss, SmoothHinge, Squared
from taskmesh.operators.relations import (
    ClusterRelation, ConvexClusterRelation, CovarianceRelation, DenseRelation, GraphRelation, IndependentRelation, MeanRelation, Relation, SparsePrecisionRelation, SpectralClusterRelation, mix_frame,
)
from taskmesh.operators.solver import FitResult, State, attach, fit_multitask, prepare, run_round, update_weights, vectors_frame
from taskmesh.operators.vector_aggregates import gram, vector_mean, vector_sum
from taskmesh.plans import experiments, workloads
from taskmesh.sources import load

Query = Callable[[SparkSession, str], DataFrame]
M, D = 20, 64
LAM1, LAM2 = 1.0, 0.5


def r6(c) -> F.Column:
    return F.round(c, 6)


def small_sensor(spark: SparkSession, d: str) -> DataFrame:
    """20 sensors, all coordinates, the natural label; without a bias, as SQL reads them."""
    return workloads.sensor_tasks(spark, d, M, D, planted=False)


def small_clusters(spark: SparkSession) -> DataFrame:
    return spark.range(M).select(F.col("id").alias("task_id"), (F.col("id") % 3).cast("int").alias("cluster_id"))


def small_relation() -> ClusterRelation:
    return ClusterRelation(lam1=LAM1, lam2=LAM2, clusters=tuple(t % 3 for t in range(M)))


# Data -------------------------------------------------------------------------------------------------------------------


def _summary(build: Callable) -> Query:
    """Per task of a workload: points, positives, and a checksum of features."""

    def query(spark: SparkSession, d: str) -> DataFrame:
        df = build(spark, d)
        total = F.aggregate("features", F.lit(0.0), lambda s, x: s + x)
        return df.groupBy("task_id").agg(F.count("*").alias("n"), F.count_if(F.col("label") > 0).alias("positives"), F.round(F.avg(total), 4).alias("mean_feature_sum"), F.max(F.size("features")).alias("d"))

    return query


def task_sizes(spark, d):
    return frames.task_sizes(workloads.nation_tasks(spark, d, planted=False))


def task_imbalance(spark, d):
    return frames.imbalance(workloads.customer_tasks(spark, d)).select("tasks", "points", "least", "median", "most", r6(F.col("most_over_median")).alias("most_over_median"), r6(F.col("gini")).alias("gini"))


def split_75_25(spark, d):
    out = frames.split(workloads.nation_tasks(spark, d, planted=False))
    return out.groupBy("task_id", "split").agg(F.count("*").alias("n"), F.sum("row_id").alias("rows"))


def folds_ntile5(spark, d):
    out = frames.folds(workloads.nation_tasks(spark, d, planted=False))
    return out.groupBy("task_id", "fold").agg(F.count("*").alias("n"), F.sum("row_id").alias("rows"))


def skew_subsample(spark, d):
    return frames.skew_subsample(workloads.nation_tasks(spark, d, planted=False)).groupBy("task_id").agg(F.count("*").alias("n"), F.sum("row_id").alias("rows"))


def stratified_sample(spark, d):
    return frames.stratified(workloads.nation_tasks(spark, d, planted=False), 30).groupBy("task_id").agg(F.count("*").alias("n"), F.sum("row_id").alias("rows"))


def bootstrap_counts(spark, d):
    return frames.bootstrap_weights(workloads.nation_tasks(spark, d, planted=False)).groupBy("weight").agg(F.count("*").alias("n"))


def portable_draws(spark, d):
    u = portable_uniform("demo", 7, F.col("o_orderkey"))
    return load(spark, d, "orders", ["o_orderkey"]).select("o_orderkey", r6(u).alias("u"))


def standardize_train_only(spark, d):
    out = frames.standardize(frames.split(small_sensor(spark, d)))
    long = out.select("split", F.posexplode("features").alias("coordinate", "x"))
    return long.groupBy("split", "coordinate").agg(F.round(F.avg("x"), 5).alias("mean"), F.round(F.stddev_samp("x"), 5).alias("sd"))


def pack_blocks(spark, d):
    packed = frames.pack(small_sensor(spark, d), block_rows=8)
    return packed.select("task_id", "block_id", F.size("ys").alias("n"), F.col("row_ids")[0].alias("first_row"), r6(F.aggregate("norms", F.lit(0.0), lambda s, x: s + x)).alias("norms"))


def planted_sensor_labels(spark, d):
    return workloads.sensor_tasks(spark, d).groupBy("task_id").agg(F.count("*").alias("n"), F.sum("label").cast("long").alias("balance"))


def hash_text_features(spark, d):
    grams = workloads.hash_text(load(spark, d, "documents", ["doc_id", "text"]), buckets=256)
    return grams.select("doc_id", F.posexplode("grams").alias("bucket", "share")).where("share > 0").select("doc_id", "bucket", r6(F.col("share")).alias("share"))


# Relations -----------------------------------------------------------------------------------------------------------------


def _shared(spark, d):
    """A stand-in for shared vectors: the sum of a task's points times their labels."""
    tasks = small_sensor(spark, d).select("task_id", F.transform("features", lambda x: x * F.col("label")).alias("v"))
    return vector_sum(tasks, ["task_id"], "v")


def _long(df, column):
    return df.select("task_id", F.posexplode(column).alias("coordinate", "x")).select("task_id", "coordinate", r6(F.col("x")).alias("x"))


def mix_independent(spark, d):
    return _long(mix_frame(_shared(spark, d), None, 0.0, LAM2), "w")


def mix_cluster(spark, d):
    return _long(mix_frame(_shared(spark, d), small_clusters(spark), LAM1, LAM2), "w")


def mix_mean(spark, d):
    return _long(mix_frame(_shared(spark, d), small_clusters(spark).withColumn("cluster_id", F.lit(0)), LAM1, LAM2), "w")


def mix_known_region(spark, d):
    tasks = workloads.nation_tasks(spark, d, planted=False).select("task_id", F.transform("features", lambda x: x * F.col("label")).alias("v"))
    return _long(mix_frame(vector_sum(tasks, ["task_id"], "v"), workloads.nation_clusters(spark, d), LAM1, LAM2), "w")


def cluster_centroids(spark, d):
    means = vector_mean(_shared(spark, d).join(small_clusters(spark), "task_id"), ["cluster_id"], "v", "mean")
    return means.select("cluster_id", F.posexplode("mean").alias("coordinate", "x")).select("cluster_id", "coordinate", r6(F.col("x")).alias("x"))


def customer_clusters(spark, d):
    """Customers as tasks, clustered by their nation."""
    return load(spark, d, "customer", ["c_custkey", "c_nationkey"]).select(F.col("c_custkey").cast("long").alias("task_id"), F.col("c_nationkey").alias("cluster_id"))


def kappa_by_task(spark, d):
    tasks = customer_clusters(spark, d)
    sizes = tasks.groupBy("cluster_id").agg(F.count("*").alias("size")).withColumnRenamed("cluster_id", "own")  # a row a nation
    size = F.col("size")
    both = tasks.join(F.broadcast(sizes), F.col("cluster_id").eqNullSafe(F.col("own")))
    return both.select("task_id", r6(0.5 * ((1 - 1 / size) / (LAM1 + LAM2) + 1 / (size * LAM2))).alias("kappa"))


def sigma_rules(spark, d):
    sizes = customer_clusters(spark, d).groupBy("cluster_id").agg(F.count("*").alias("c"))
    found = sizes.agg(F.max("c").alias("most"), F.sum("c").alias("tasks")).where("tasks > 0").first()
    r = ClusterRelation(lam1=LAM1, lam2=LAM2)
    rules = [("spectral", r.largest_sigma(found.most)), ("gershgorin", r.largest_sigma(found.most)), ("trace", r.sigma(found.tasks, "trace"))] if found else []
    return spark.createDataFrame([(rule, round(float(s), 6)) for rule, s in rules], "rule string, sigma double")


def gram_matrix(spark, d):
    return gram(small_sensor(spark, d), "features").select("i", "j", F.round("value", 5).alias("value"))


def task_similarity_topk(spark, d):
    return joins.related_tasks(_shared(spark, d), "v", 3).select("task_id", "other", "rank", r6(F.col("cosine")).alias("cosine"))


def graph_laplacian(spark, d):
    pairs = workloads.nation_clusters(spark, d)
    edges = pairs.alias("a").join(pairs.alias("b"), (F.col("a.cluster_id") == F.col("b.cluster_id")) & (F.col("a.task_id") < F.col("b.task_id"))).select(F.col("a.task_id").alias("i"), F.col("b.task_id").alias("j"), F.lit(1.0).alias("weight"))
    return joins.laplacian(edges)


# Solver ------------------------------------------------------------------------------------------------------------------


def start_rows(spark, d, sigma: float = 3.0, budget: int = 1 << 30) -> DataFrame:
    packed = frames.pack(small_sensor(spark, d))
    small = packed.withColumn("alpha", F.array_repeat(F.lit(0.0), F.size("ys"))).withColumn("w", F.array_repeat(F.lit(0.0), D))
    return small.withColumn("kappa", F.lit(0.5)).withColumn("sigma", F.lit(sigma)).withColumn("budget", F.lit(budget)).withColumn("theta", F.lit(0.0)).withColumn("dropped", F.lit(False))


def _local(loss: Loss, budget: int = 1 << 30) -> Query:
    """One pass inside the JVM; SQL does the same by recursion."""

    def query(spark: SparkSession, d: str) -> DataFrame:
        rows = start_rows(spark, d, budget=budget).withColumn("s", expression_pass(loss))
        return rows.select("task_id", F.col("s.k").alias("steps"), F.posexplode("s.u").alias("coordinate", "u")).select("task_id", "steps", "coordinate", r6(F.col("u")).alias("u"))

    return query


def _local_arrow(loss: Loss) -> Query:
    def query(spark: SparkSession, d: str) -> DataFrame:
        done = arrow_pass(start_rows(spark, d), loss)
        return done.select("task_id", "steps", F.posexplode("dv").alias("coordinate", "dv")).select("task_id", "steps", "coordinate", r6(F.col("dv")).alias("dv"))

    return query


def _rounds(rounds: int, relation: Callable[[], Relation], loss: Loss, **options) -> Query:
    def query(spark: SparkSession, d: str) -> DataFrame:
        fit = update_weights(prepare(frames.pack(small_sensor(spark, d))), relation(), loss, rounds, **options)
        return _long(fit.weights_frame(), "w")

    return query


def plain_rounds(spark, d):
    """Two rounds of tasks without a relation, squared loss."""
    return _rounds(2, lambda: IndependentRelation(lam2=LAM2), Squared(), sigma=1.0)(spark, d)


def dropping_weights(spark, d):
    """Weights after three rounds in which each node drops out with probability one half."""
    return _rounds(3, small_relation, Hinge(), sigma=3.0, policy=policies.compose(policies.WorkBudget(passes=1), policies.DropPolicy(0.5)))(spark, d)


def clock_round(spark, d):
    """What each node can do before a deadline: steps by its own speed and network, none if its answer would be late."""
    problem = prepare(frames.pack(small_sensor(spark, d)))
    profile = problem.spark.createDataFrame([(t, 0.25 + 0.75 * uniform_for("speed", 0, t), 0.5 + uniform_for("net", 0, t)) for t in problem.tasks], "task_id long, speed double, comm_scale double")
    fit = update_weights(problem, small_relation(), Hinge(), 2, policies.ClockPolicy(cycle=30.0, step_cost=1.0, comm_cost=20.0), profile=profile)
    return fit.log_frame().select("round", "task_id", "dropped", "steps")


def averaged_iterate(spark, d):
    """The mean of the iterates of the last rounds, as weights."""
    fit = update_weights(prepare(frames.pack(small_sensor(spark, d))), small_relation(), Hinge(), 3, sigma=3.0, average_from=1)
    return _long(vectors_frame(fit.problem, fit.average, "w"), "w")


def per_step_settings(spark, d):
    """Rounds and sigma that depend on the outer step and its relation."""
    problem = prepare(frames.pack(workloads.doc_quality_tasks(spark, d)))
    fit = fit_multitask(problem, ClusterRelation(lam1=0.1, lam2=0.1, k=2), Squared(), outer=2, rounds=lambda i: 2 + i, sigma=lambda r: r.sigma(4, "gershgorin"))
    return _history(fit)


def _half_state(spark, d):
    """A feasible state that SQL can tell: every dual is half its label."""
    problem = prepare(frames.pack(small_sensor(spark, d)))
    duals = problem.packed.select("task_id", "block_id", F.transform("ys", lambda y: 0.5 * y).alias("alpha"))
    shared = {r.task_id: r.v for r in _shared(spark, d).collect()}  # d numbers per task
    return problem, State(np.array([[0.5 * x for x in shared[t]] for t in problem.tasks]), duals)


def _objective(loss: Loss) -> Query:
    def query(spark: SparkSession, d: str) -> DataFrame:
        problem, state = _half_state(spark, d)
        found = measures.optimality(problem, state, small_relation(), loss)
        return found.select(*[F.round(c, 5).alias(c) for c in ("primal", "dual", "gap")])

    return query


def subproblem_value(spark, d):
    """Each task's local subproblem at a quarter step from the half state, by its conjugates, linear and curvature terms."""
    problem, state = _half_state(spark, d)
    relation = small_relation()
    rows = attach(problem, state, relation.mix(state.v), relation.kappa(M), np.full(M, 3.0))
    rows = rows.withColumn("delta", F.transform("ys", lambda y: 0.25 * y))
    return measures.subproblem_values(rows, Hinge()).select("task_id", F.round("value", 5).alias("value"))


def subproblem_theta(spark, d):
    """The accuracy of one pass from zero, against a nearly exact solution of every subproblem."""
    problem, relation = prepare(frames.pack(small_sensor(spark, d))), small_relation()
    start, sigma = State(np.zeros((M, D))), np.full(M, 3.0)
    after, _, _ = run_round(problem, start, relation, Hinge(), policies.WorkBudget(passes=1), sigma, 0, 0)
    return measures.theta_frame(problem, start, after, relation, Hinge(), sigma).select("task_id", r6(F.col("theta")).alias("theta"))


def measured_bounds(spark, d):
    """The bounds on rounds, from a measured log and the constants of a real problem."""
    problem, relation, loss = prepare(frames.pack(small_sensor(spark, d))), small_relation(), SmoothHinge(0.5)
    fit = update_weights(problem, relation, loss, 4, policies.compose(policies.WorkBudget(passes=1), policies.DropPolicy(0.25)))
    theta = measures.assumption_report(fit.log_frame()).first().p_max
    s = measures.smooth_constant(problem, relation, loss.mu, relation.sigma(M))
    n = int(problem.points.sum())
    first, total = measures.rounds_bound_lipschitz(n, 1e-3, theta, 1.0, float((relation.kappa(M) * problem.largest * problem.points**2).sum()), relation.sigma(M), fit.history[0]["dual"] - fit.history[-1]["dual"])
    return spark.createDataFrame([(round(float(theta), 6), round(float(s), 6), measures.rounds_bound_smooth(n, 1e-3, theta, s), first, total)], "p_max double, s double, smooth long, lipschitz_first long, lipschitz_total long")


def _relation_fit(build: Callable[[int], Relation], tasks: Callable = workloads.doc_quality_tasks) -> Query:
    """Two outer steps with this relation from the first one on; primal, dual and gap of every round."""

    def query(spark: SparkSession, d: str) -> DataFrame:
        problem = prepare(frames.pack(tasks(spark, d)))
        relation = build(len(problem.tasks))
        return _history(fit_multitask(problem, relation, Squared(), outer=2, rounds=3, first=relation))

    return query


def fit_graph_relation(spark, d):
    """Nations of one region are neighbours: a graph that is known beforehand."""
    problem = prepare(frames.pack(workloads.nation_tasks(spark, d)))
    region = {r.task_id: r.cluster_id for r in workloads.nation_clusters(spark, d).collect()}  # a row a task
    edges = [(i, j, 1.0) for i, a in enumerate(problem.tasks) for j, b in enumerate(problem.tasks) if i < j and region[a] == region[b]]
    return _history(update_weights(problem, GraphRelation(edges, len(problem.tasks), 1.0, 1.0), Hinge(), 4))


def _history(fit: FitResult) -> DataFrame:
    return fit.history_frame().select("run", "outer", "round", *[F.round(c, 5).alias(c) for c in ("primal", "dual", "gap")])


def fit_alternating_cluster(spark, d):
    problem = prepare(frames.pack(workloads.sensor_tasks(spark, d)))
    return fit_multitask(problem, ClusterRelation(lam1=0.5, lam2=0.05, k=3), Hinge(), outer=2, rounds=4).weights_frame()


def fit_covariance_relation(spark, d):
    problem = prepare(frames.pack(workloads.doc_quality_tasks(spark, d)))
    return _history(fit_multitask(problem, CovarianceRelation(lam1=0.1, lam2=0.1), Squared(), outer=2, rounds=4))


def drop_round(spark, d):
    problem = prepare(frames.pack(small_sensor(spark, d)))
    fit = update_weights(problem, small_relation(), Hinge(), 3, policies.compose(policies.WorkBudget(passes=1), policies.DropPolicy(0.5)))
    return fit.log_frame().select("round", "task_id", "dropped", "steps")


def sgd_rounds(spark, d):
    from taskmesh.operators.baselines import minibatch_sgd

    fit = minibatch_sgd(prepare(frames.pack(small_sensor(spark, d))), small_relation(), Hinge(), batch=8, eta=0.05, rounds=3)
    return fit.history_frame().select("round", F.round("primal", 5).alias("primal"))


def sdca_minibatch_rounds(spark, d):
    from taskmesh.operators.baselines import minibatch_sdca

    return _history(minibatch_sdca(prepare(frames.pack(small_sensor(spark, d))), small_relation(), Hinge(), batch=8, scale=2.0, rounds=3))


def local_model_fit(spark, d):
    from taskmesh.operators.baselines import fit_local

    return fit_local(small_sensor(spark, d), Hinge(), LAM2, passes=20)


def global_model_fit(spark, d):
    from taskmesh.operators.baselines import fit_global

    return fit_global(small_sensor(spark, d), Hinge(), LAM2, rounds=4).weights_frame()


# Measures ----------------------------------------------------------------------------------------------------------------


def _stored_weights(spark, d) -> DataFrame:
    """A fixed stand-in for weights, so that SQL can judge the measures alone."""
    return mix_frame(_shared(spark, d), small_clusters(spark), LAM1, LAM2)


def task_error(spark, d):
    return measures.task_error(small_sensor(spark, d), _stored_weights(spark, d)).select("task_id", "n_test", r6(F.col("error")).alias("error"))


def mean_task_error(spark, d):
    return measures.mean_task_error(measures.task_error(small_sensor(spark, d), _stored_weights(spark, d))).select(r6(F.col("error")).alias("error"), "tasks")


def _loss_sums(loss: Loss) -> Query:
    def query(spark: SparkSession, d: str) -> DataFrame:
        scored = measures.score(small_sensor(spark, d), _stored_weights(spark, d))
        return scored.groupBy("task_id").agg(F.round(F.sum(loss.value_column(F.col("z"), F.col("label"))), 5).alias("loss"))

    return query


def penalty_cluster(spark, d):
    """lam1 times the spread around clusters' means, plus lam2 times the squared length."""
    w = _stored_weights(spark, d).join(small_clusters(spark), "task_id")
    means = vector_mean(w, ["cluster_id"], "w", "mean")
    spread = norm2(F.zip_with("w", "mean", lambda a, b: a - b))
    return w.join(means, "cluster_id").agg(F.round(F.sum(LAM1 * spread + LAM2 * norm2("w")), 5).alias("penalty"))


def _synthetic_log(spark, d) -> DataFrame:
    """A round log by hash, over suppliers: steps, drops and answers of eight rounds."""
    nodes = load(spark, d, "supplier", ["s_suppkey"]).crossJoin(spark.range(8).select(F.col("id").cast("int").alias("round")))
    steps = F.floor(10 + 90 * portable_uniform("steps", F.col("s_suppkey"), F.col("round"))).cast("int")
    dropped = portable_uniform("gone", F.col("s_suppkey"), F.col("round")) < 0.1
    log = nodes.select(F.lit("x").alias("run"), F.lit(0).alias("outer"), "round", F.col("s_suppkey").alias("task_id"), F.when(dropped, 0).otherwise(steps).alias("steps"), dropped.alias("dropped"))
    return log.withColumn("theta", F.when(F.col("dropped"), 1.0).otherwise(1.0 / F.col("steps"))).withColumn("flops", F.col("steps") * 40.0).withColumn("comm_elems", F.when(F.col("dropped"), 0).otherwise(20).cast("long"))


def _simulated(network: str) -> Query:
    def query(spark: SparkSession, d: str) -> DataFrame:
        out = measures.simulated_time(_synthetic_log(spark, d), measures.NETWORKS[network])
        return out.select("round", "seconds", "comm_elems", "flops", "sim_time")

    return query


def straggler_report(spark, d):
    return measures.straggler_report(_synthetic_log(spark, d)).select("round", "most", "median", r6(F.col("ratio")).alias("ratio"))


def assumption_report(spark, d):
    return measures.assumption_report(_synthetic_log(spark, d)).select(*[r6(F.col(c)).alias(c) for c in ("p_max", "theta_max", "theta_bar")])


def communication_volume(spark, d):
    return measures.communication(_synthetic_log(spark, d))


def time_to_target(spark, d):
    times = measures.simulated_time(_synthetic_log(spark, d), 10.0).withColumn("suboptimality", 1.0 / (F.col("round") + 1))
    return measures.time_to_target(times, 0.26)


def rounds_bounds(spark, d):
    """Customers as tasks without a relation, their orders as points of length one: curvature and the first gap (hinge, zero weights)
    follow from the tasks' sizes."""
    sizes = load(spark, d, "orders", ["o_custkey"]).groupBy("o_custkey").agg(F.count("*").alias("n"))
    found = sizes.agg(F.sum("n").alias("n"), F.sum(F.col("n") * F.col("n")).alias("square")).where("n > 0").first()
    schema = "smooth long, lipschitz_first long, lipschitz_total long"
    if found is None:
        return spark.createDataFrame([], schema)
    n, kappa = found.n, float(IndependentRelation(lam2=LAM2).kappa(1)[0])
    first, total = measures.rounds_bound_lipschitz(n, 1e-3, 0.5, 1.0, kappa * found.square, 3.0, float(n))
    return spark.createDataFrame([(measures.rounds_bound_smooth(n, 1e-3, 0.5, 0.01), first, total)], schema)


def trial_summary(spark, d):
    trials = load(spark, d, "events").select(F.col("event_type").alias("model"), (F.col("user_id") % 10).alias("trial"), "value").groupBy("model", "trial").agg(F.avg("value").alias("error"))
    return measures.summarize_trials(trials).select("model", r6(F.col("mean")).alias("mean"), r6(F.col("se")).alias("se"), "trials")


# Experiments --------------------------------------------------------------------------------------------------------------


def _comparison(build: Callable, clusters: int = 3) -> Query:
    """The whole protocol: seven penalties, five folds, ten shuffles; mean error and standard error by model."""

    def query(spark: SparkSession, d: str) -> DataFrame:
        out = experiments.compare_models(build(spark, d), clusters=clusters)
        return measures.summarize_trials(out).select("model", "mean", "se", "trials")

    return query


def _experiment_problem(spark, d, tasks: Callable = workloads.sensor_tasks):
    return prepare(frames.pack(tasks(spark, d))), ClusterRelation(lam1=1.0, lam2=0.5, clusters=tuple(t % 3 for t in range(23)))


def skewed_sensors(spark, d):
    return frames.skew_subsample(workloads.sensor_tasks(spark, d))


def skewed_language(spark, d):
    return frames.skew_subsample(workloads.doc_language_tasks(spark, d))


def skewed_events(spark, d):
    return frames.skew_subsample(workloads.event_window_tasks(spark, d, planted=True))


def figure_straggler(spark, d):
    """Statistical heterogeneity is what this is about, so the sensors are of unequal size."""
    problem, relation = _experiment_problem(spark, d, skewed_sensors)
    return experiments.straggler_curves(problem, relation, Hinge(), rounds=8)


def figure_heterogeneity(spark, d):
    problem, relation = _experiment_problem(spark, d)
    return experiments.heterogeneity_curves(problem, relation, Hinge(), rounds=8)


def figure_drops(spark, d):
    problem, relation = _experiment_problem(spark, d)
    return experiments.drop_curves(problem, relation, Hinge(), silent=(0,), rounds=8)


def figure_drops_whole(spark, d):
    """Dropped nodes in the whole alternation, with the relation learned on the way."""
    problem, _ = _experiment_problem(spark, d)
    return experiments.drop_curves(problem, ClusterRelation(lam1=1.0, lam2=0.5, k=3), Hinge(), ps=(0.0, 0.25, 0.5, 0.75, 0.9), silent=(0,), rounds=4, outer=3)


QUERIES: dict[str, Query] = {
    **{f"tasks_{name}": _summary(build) for name, build in workloads.WORKLOADS.items()},
    "task_sizes": task_sizes, "task_imbalance": task_imbalance, "split_75_25": split_75_25, "folds_ntile5": folds_ntile5, "skew_subsample": skew_subsample,
    "stratified_sample": stratified_sample, "bootstrap_counts": bootstrap_counts, "portable_uniform": portable_draws, "standardize_train_only": standardize_train_only,
    "pack_blocks": pack_blocks, "planted_sensor_labels": planted_sensor_labels, "hash_text_features": hash_text_features,
    "mix_independent": mix_independent, "mix_cluster": mix_cluster, "mix_mean": mix_mean, "mix_known_region": mix_known_region, "cluster_centroids": cluster_centroids,
    "kappa_by_task": kappa_by_task, "sigma_cluster_rules": sigma_rules, "gram_matrix": gram_matrix, "task_similarity_topk": task_similarity_topk, "graph_laplacian_edges": graph_laplacian,
    "local_pass_hinge": _local(Hinge()), "local_pass_squared": _local(Squared()), "local_pass_smooth_hinge": _local(SmoothHinge(0.5)), "local_pass_absolute": _local(Absolute()),
    "budgeted_pass": _local(Hinge(), 7), "local_pass_arrow": _local_arrow(Hinge()), "local_pass_logistic": _local_arrow(Logistic()),
    "first_round_cluster": _rounds(1, small_relation, Hinge(), sigma=3.0), "three_rounds_cluster": _rounds(3, small_relation, Hinge(), sigma=3.0),
    "gamma_half_round": _rounds(1, small_relation, Hinge(), sigma=3.0, gamma=0.5), "independent_rounds": plain_rounds, "dropping_weights": dropping_weights, "clock_round": clock_round,
    "averaged_iterate": averaged_iterate, "per_step_settings": per_step_settings, "duality_gap_hinge": _objective(Hinge()), "duality_gap_squared": _objective(Squared()), "duality_gap_smooth_hinge": _objective(SmoothHinge(0.5)),
    "subproblem_value": subproblem_value, "subproblem_theta": subproblem_theta, "measured_bounds": measured_bounds,
    "fit_mean_relation": _relation_fit(lambda m: MeanRelation(m, 0.1, 0.1)), "fit_dense_relation": _relation_fit(lambda m: DenseRelation(lam1=0.1, lam2=0.1, omega=np.eye(m) - np.full((m, m), 1.0 / m))),
    "fit_spectral_relation": _relation_fit(lambda m: SpectralClusterRelation(lam1=0.1, lam2=0.1, k=2)), "fit_convex_relation": _relation_fit(lambda m: ConvexClusterRelation(lam1=0.1, lam2=0.1, k=2)),
    "fit_sparse_precision": _relation_fit(lambda m: SparsePrecisionRelation(lam1=0.1, lam2=0.1)), "fit_graph_relation": fit_graph_relation,
    "drop_round": drop_round, "sgd_rounds": sgd_rounds, "sdca_minibatch_rounds": sdca_minibatch_rounds, "local_model_fit": local_model_fit, "global_model_fit": global_model_fit,
    "fit_alternating_cluster": fit_alternating_cluster, "fit_covariance_relation": fit_covariance_relation,
    "task_error": task_error, "mean_task_error": mean_task_error, "primal_loss_hinge": _loss_sums(Hinge()), "primal_loss_smooth_hinge": _loss_sums(SmoothHinge(0.5)),
    "primal_loss_squared": _loss_sums(Squared()), "primal_loss_logistic": _loss_sums(Logistic()), "primal_loss_absolute": _loss_sums(Absolute()), "penalty_cluster": penalty_cluster,
    "simulated_time_wifi": _simulated("wifi"), "simulated_time_lte": _simulated("lte"), "simulated_time_3g": _simulated("3g"), "straggler_report": straggler_report,
    "assumption_report": assumption_report, "communication_volume": communication_volume, "time_to_target": time_to_target, "rounds_bounds": rounds_bounds, "trial_summary": trial_summary,
    "compare_models": _comparison(workloads.sensor_tasks), "compare_models_language": _comparison(workloads.doc_language_tasks, 4),
    "compare_models_events": _comparison(lambda spark, d: workloads.event_window_tasks(spark, d, planted=True)), "compare_models_skewed": _comparison(skewed_language, 4), "compare_models_skewed_events": _comparison(skewed_events),
    "figure_straggler": figure_straggler, "figure_heterogeneity": figure_heterogeneity, "figure_drops": figure_drops, "figure_drops_whole": figure_drops_whole,
}

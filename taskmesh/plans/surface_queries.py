"""Registered queries for the operators around the methods, with their DuckDB SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from taskmesh.functions.vectors import dot
from taskmesh.operators import frames, joins, reports
from taskmesh.plans import workloads
from taskmesh.sources import load
from taskmesh.streaming import windows


def r6(c):
    return F.round(c, 6)


def _events(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))


def class_balance_rollup(spark, d):
    docs = load(spark, d, "documents", ["doc_id", "lang", "source"]).join(load(spark, d, "labels"), "doc_id")
    return docs.rollup("lang", "source").agg(F.count("*").alias("n"), F.count_if(F.col("quality") == 1).alias("good"), F.grouping_id().alias("level"))


def cube_lang_source(spark, d):
    errors = load(spark, d, "documents", ["doc_id", "lang", "source"]).join(load(spark, d, "labels"), "doc_id").withColumn("error", F.col("toxic").cast("double"))
    return reports.error_cube(errors, "lang", "source").select("lang", "source", r6(F.col("error")).alias("error"), "tasks", F.col("level").cast("long").alias("level"))


def grouping_sets_error(spark, d):
    errors = load(spark, d, "documents", ["doc_id", "lang", "source"]).join(load(spark, d, "labels"), "doc_id").withColumn("error", F.col("quality").cast("double"))
    return reports.error_sets(errors, [["lang"], ["source"], []], ["lang", "source"]).select("lang", "source", r6(F.col("error")).alias("error"), "tasks")


def label_coverage(spark, d):
    docs = load(spark, d, "documents", ["doc_id", "source"]).join(load(spark, d, "labels"), "doc_id", "left")
    return docs.groupBy("source").agg(F.count("*").alias("docs"), F.count("quality").alias("labelled"), F.count_if(F.col("toxic") == 1).alias("toxic"))


def decontaminated(spark, d):
    docs = load(spark, d, "documents", ["doc_id", "text", "lang"])
    return joins.decontaminate(docs, load(spark, d, "benchmark")).select("doc_id", "lang")


def asof_latest_weights(spark, d):
    events = _events(spark, d).select("event_id", "user_id", "ts")
    versions = _events(spark, d).where("event_type = 'signup'").select("user_id", F.col("ts").alias("at"), F.col("event_id").alias("version"))
    versions = versions.groupBy("user_id", "at").agg(F.max("version").alias("version"))
    return joins.asof(events, versions, "user_id", "ts", "at", ["version"]).select("event_id", "version")


def interval_join_sessions(spark, d):
    spans = _events(spark, d).where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase"), (F.col("ts") - F.expr("INTERVAL 6 HOURS")).alias("a"), F.col("ts").alias("b"))
    return joins.within_intervals(_events(spark, d), spans, "user_id", "ts", "a", "b").groupBy("purchase").agg(F.count("*").alias("n"), F.max("event_id").alias("last"))


def tumbling_counts(spark, d):
    return windows.window_features(_events(spark, d), "1 day").select("user_id", F.unix_seconds("start").alias("start"), "n", F.round("total", 4).alias("total"), "least", "most", "purchases")


def sliding_windows_features(spark, d):
    return windows.window_features(_events(spark, d), "2 days", "1 day").select("user_id", F.unix_seconds("start").alias("start"), "n", F.round("total", 4).alias("total"), "purchases")


def session_windows(spark, d):
    return windows.session_features(_events(spark, d), "6 hours").select("user_id", F.unix_seconds("start").alias("start"), "n", F.round("total", 4).alias("total"))


def temporal(spark, d):
    out = reports.temporal_features(_events(spark, d))
    return out.select("event_id", "user_id", "before", "after", r6(F.col("moving")).alias("moving"), "last_hour")


def json_props(spark, d):
    k = F.from_json("props", "k int")["k"]
    return load(spark, d, "events").groupBy("event_type").agg(F.sum(k).alias("k"), F.max(F.get_json_object("props", "$.k").cast("int")).alias("most"))


def map_params(spark, d):
    """Sparse features as a map by event type, then scaled."""
    counts = load(spark, d, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    maps = counts.groupBy("user_id").agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("event_type", "n")))).alias("m"))
    total = F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda s, x: s + x)
    return maps.select("user_id", r6(F.element_at(F.transform_values("m", lambda k, v: v / total), "view")).alias("view_share"), F.size("m").alias("types"))


def setops_split_check(spark, d):
    """Training and test rows share nothing and leave out nothing."""
    parts = frames.split(workloads.nation_tasks(spark, d, planted=False)).select("task_id", "row_id", "split")
    train, test = (parts.where(F.col("split") == s).select("task_id", "row_id") for s in ("train", "test"))
    everything = parts.select("task_id", "row_id")
    counts = [train.intersect(test), everything.exceptAll(train.unionByName(test)), train.unionByName(test).distinct()]
    names = ("shared", "missing", "kept")
    out = None
    for name, df in zip(names, counts, strict=True):
        one = df.agg(F.count("*").alias("n")).select(F.lit(name).alias("what"), "n")
        out = one if out is None else out.unionByName(one)
    return out


def semi_reporting_tasks(spark, d):
    tasks, answers = load(spark, d, "customer", ["c_custkey"]).withColumnRenamed("c_custkey", "task_id"), load(spark, d, "orders", ["o_custkey", "o_totalprice"]).where("o_totalprice > 400000").withColumnRenamed("o_custkey", "task_id")
    return joins.reporting_tasks(tasks, answers).select("task_id", F.lit("reports").alias("state")).unionByName(joins.silent_tasks(tasks, answers).select("task_id", F.lit("silent").alias("state")))


def reconcile_state(spark, d):
    old = load(spark, d, "orders").where("o_orderpriority < '3'").groupBy(F.col("o_custkey").alias("task_id")).agg(F.count("*").alias("n"))
    new = load(spark, d, "orders").where("o_orderpriority > '3'").groupBy(F.col("o_custkey").alias("task_id")).agg(F.count("*").alias("n"))
    return joins.reconcile(old, new, ["task_id"], "n")


def topk_hard_tasks(spark, d):
    errors = load(spark, d, "orders").groupBy(F.col("o_custkey").alias("task_id")).agg(r6(F.avg((F.col("o_orderstatus") == "F").cast("double"))).alias("error"))
    return reports.hardest_tasks(errors, 10)


def rank_tasks(spark, d):
    errors = load(spark, d, "orders").join(load(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).groupBy(F.col("c_nationkey").alias("task_id")).agg(F.round(F.avg((F.col("o_orderstatus") == "F").cast("double")), 2).alias("error"))
    return reports.rank_tasks(errors).select("task_id", "error", "place", "rank", "dense", r6(F.col("percent")).alias("percent"), r6(F.col("cumulative")).alias("cumulative"))


def pivot_errors(spark, d):
    errors = load(spark, d, "events").groupBy(F.col("user_id").alias("task_id"), F.col("event_type").alias("model")).agg((F.sum(F.round(F.col("value") * 10_000).cast("long")) / F.count("value")).alias("error"))
    return reports.pivot_errors(errors, ["click", "view", "purchase"])


def distinct_tasks(spark, d):
    return reports.distinct_tasks(load(spark, d, "orders").withColumnRenamed("o_custkey", "task_id")).select("exact")


def argmin_lambda(spark, d):
    scored = load(spark, d, "events").groupBy(F.col("user_id").alias("trial"), (F.col("event_id") % 3).cast("double").alias("lam")).agg(F.round(F.avg("value"), 3).alias("error"))
    return reports.best_config(scored, ["trial"])


def score_broadcast_join(spark, d):
    points = workloads.sensor_tasks(spark, d, 20, 64, planted=False)
    weights = points.where("row_id < 20").select("task_id", F.col("features").alias("w"))
    return points.join(F.broadcast(weights), "task_id").select("row_id", r6(dot("features", "w")).alias("z"))  # 20 rows


def one_vs_rest_predict(spark, d):
    points = load(spark, d, "embeddings").select(F.col("vec_id").alias("row_id"), F.transform("embedding", lambda x: x.cast("double")).alias("features"))
    scores = points.select("row_id", F.explode(F.array(*[F.struct(F.lit(c).alias("class"), F.element_at("features", k + 1).alias("z")) for k, c in enumerate("abc")])).alias("s")).select("row_id", "s.class", "s.z")
    return reports.one_vs_rest(scores)


def time_quantiles(spark, d):
    orders = load(spark, d, "orders").withColumn("round", F.substring("o_orderpriority", 1, 1))
    out = reports.time_quantiles(orders, "o_totalprice")
    return out.select("round", F.round(F.col("exact")[0], 4).alias("p50"), F.round(F.col("exact")[1], 4).alias("p90"), F.round(F.col("exact")[2], 4).alias("p99"))


def first_last_values(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    e = _events(spark, d)
    return e.select("user_id", F.first("value").over(w).alias("first"), F.last("value").over(w).alias("last"), F.nth_value("value", 2).over(w).alias("second")).distinct()


QUERIES = {
    "class_balance_rollup": class_balance_rollup, "cube_lang_source": cube_lang_source, "grouping_sets_error": grouping_sets_error, "label_coverage_left_join": label_coverage,
    "decontaminate_anti_join": decontaminated, "asof_latest_weights": asof_latest_weights, "interval_join_sessions": interval_join_sessions, "tumbling_counts": tumbling_counts,
    "sliding_windows_features": sliding_windows_features, "session_windows": session_windows, "temporal_features": temporal, "json_props": json_props, "map_params": map_params,
    "setops_split_check": setops_split_check, "semi_reporting_tasks": semi_reporting_tasks, "reconcile_state": reconcile_state, "topk_hard_tasks": topk_hard_tasks, "rank_tasks": rank_tasks,
    "pivot_errors": pivot_errors, "distinct_tasks": distinct_tasks, "argmin_lambda": argmin_lambda, "score_broadcast_join": score_broadcast_join, "one_vs_rest_predict": one_vs_rest_predict,
    "time_quantiles": time_quantiles, "first_last_values": first_last_values,
}

LABELLED = "documents JOIN labels USING (doc_id)"
SPLIT_PARTS = """SELECT task_id, row_id FROM (SELECT c_nationkey::BIGINT AS task_id, o_orderkey AS row_id FROM orders JOIN customer ON o_custkey = c_custkey)"""
DAY = "epoch(date_trunc('day', ts))::BIGINT"
TOKENS = "list_filter(string_split(lower(regexp_replace(text, '[^\\p{L}\\p{N}]+', ' ', 'g')), ' '), lambda w: w <> '')"
SHINGLES = f"SELECT id, unnest(list_transform(range(1, greatest(len(t) - 7, 0) + 1), lambda i: array_to_string(t[i:i + 7], ' '))) AS s FROM (SELECT id, {TOKENS} AS t FROM ROWS)"

ORACLES = {
    "class_balance_rollup": f"SELECT lang, source, count(*) AS n, count(*) FILTER (quality = 1) AS good, grouping_id(lang, source)::BIGINT AS level FROM {LABELLED} GROUP BY ROLLUP (lang, source)",
    "cube_lang_source": f"SELECT lang, source, round(avg(toxic), 6) AS error, count(*) AS tasks, grouping_id(lang, source)::BIGINT AS level FROM {LABELLED} GROUP BY CUBE (lang, source)",
    "grouping_sets_error": f"SELECT lang, source, round(avg(quality), 6) AS error, count(*) AS tasks FROM {LABELLED} GROUP BY GROUPING SETS ((lang), (source), ())",
    "label_coverage_left_join": "SELECT source, count(*) AS docs, count(quality) AS labelled, count(*) FILTER (toxic = 1) AS toxic FROM documents LEFT JOIN labels USING (doc_id) GROUP BY source",
    "decontaminate_anti_join": f"""WITH b AS ({SHINGLES.replace('ROWS', '(SELECT item_id AS id, text FROM benchmark)')}), d AS ({SHINGLES.replace('ROWS', '(SELECT doc_id AS id, text FROM documents)')})
      SELECT doc_id, lang FROM documents WHERE doc_id NOT IN (SELECT id FROM d WHERE s IN (SELECT s FROM b))""",
    "asof_latest_weights": """SELECT e.event_id, v.version FROM events e ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS version FROM events WHERE event_type = 'signup' GROUP BY 1, 2) v
      ON e.user_id = v.user_id AND e.ts >= v.ts""",
    "interval_join_sessions": """SELECT p.event_id AS purchase, count(*) AS n, max(e.event_id) AS last FROM events p JOIN events e ON p.user_id = e.user_id AND e.ts BETWEEN p.ts - INTERVAL 6 HOURS AND p.ts
      WHERE p.event_type = 'purchase' GROUP BY 1""",
    "tumbling_counts": f"SELECT user_id, {DAY} AS start, count(*) AS n, round(sum(value), 4) AS total, min(value) AS least, max(value) AS most, count(*) FILTER (event_type = 'purchase') AS purchases FROM events GROUP BY 1, 2",
    "sliding_windows_features": f"""SELECT user_id, {DAY} - 86400 * k.range AS start, count(*) AS n, round(sum(value), 4) AS total, count(*) FILTER (event_type = 'purchase') AS purchases FROM events, range(2) k GROUP BY 1, 2""",
    "session_windows": """SELECT user_id, min(floor(epoch(ts))::BIGINT) AS start, count(*) AS n, round(sum(value), 4) AS total FROM
      (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 6 HOURS THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s""",
    "temporal_features": """SELECT event_id, user_id, lag(value) OVER w AS before, lead(value) OVER w AS after, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS moving,
      count(*) OVER (PARTITION BY user_id ORDER BY floor(epoch(ts)) RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS last_hour FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)""",
    "json_props": "SELECT event_type, sum((props::JSON->>'k')::INTEGER)::BIGINT AS k, max((props::JSON->>'k')::INTEGER) AS most FROM events GROUP BY 1",
    "map_params": "SELECT user_id, round((count(*) FILTER (event_type = 'view')) / count(*), 6) AS view_share, count(DISTINCT event_type)::INTEGER AS types FROM events GROUP BY 1",
    "setops_split_check": f"SELECT 'shared' AS what, 0::BIGINT AS n UNION ALL SELECT 'missing', 0 UNION ALL SELECT 'kept', count(*) FROM ({SPLIT_PARTS})",
    "semi_reporting_tasks": "SELECT c_custkey AS task_id, CASE WHEN c_custkey IN (SELECT o_custkey FROM orders WHERE o_totalprice > 400000) THEN 'reports' ELSE 'silent' END AS state FROM customer",
    "reconcile_state": """SELECT task_id, o.n AS old, n.n AS new, CASE WHEN o.n IS NULL THEN 'new' WHEN n.n IS NULL THEN 'old' ELSE 'both' END AS found FROM
      (SELECT o_custkey AS task_id, count(*) AS n FROM orders WHERE o_orderpriority < '3' GROUP BY 1) o FULL JOIN (SELECT o_custkey AS task_id, count(*) AS n FROM orders WHERE o_orderpriority > '3' GROUP BY 1) n USING (task_id)""",
    "topk_hard_tasks": "SELECT o_custkey AS task_id, round(avg((o_orderstatus = 'F')::INT), 6) AS error FROM orders GROUP BY 1 ORDER BY error DESC, task_id LIMIT 10",
    "rank_tasks": """SELECT task_id, error, row_number() OVER (ORDER BY error DESC, task_id)::INTEGER AS place, rank() OVER w::INTEGER AS rank, dense_rank() OVER w::INTEGER AS dense, round(percent_rank() OVER w, 6) AS percent, round(cume_dist() OVER w, 6) AS cumulative
      FROM (SELECT c_nationkey AS task_id, round(avg((o_orderstatus = 'F')::INT), 2) AS error FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1) WINDOW w AS (ORDER BY error DESC)""",
    "pivot_errors": "SELECT user_id AS task_id, " + ", ".join(f"sum(round(value * 10000)::BIGINT) FILTER (event_type = '{m}') / count(value) FILTER (event_type = '{m}') AS \"{m}\"" for m in ("click", "view", "purchase")) + " FROM events GROUP BY 1",
    "distinct_tasks": "SELECT count(DISTINCT o_custkey) AS exact FROM orders",
    "argmin_lambda": """SELECT trial, lam, error FROM (SELECT *, row_number() OVER (PARTITION BY trial ORDER BY error, lam DESC) AS r FROM
      (SELECT user_id AS trial, (event_id % 3)::DOUBLE AS lam, round(avg(value), 3) AS error FROM events GROUP BY 1, 2)) WHERE r = 1""",
    "score_broadcast_join": "SELECT p.vec_id AS row_id, round(list_dot_product(p.embedding::DOUBLE[], w.embedding::DOUBLE[]), 6) AS z FROM embeddings p JOIN embeddings w ON w.vec_id = p.vec_id % 20",
    "one_vs_rest_predict": "SELECT vec_id AS row_id, CASE WHEN embedding[1] >= embedding[2] AND embedding[1] >= embedding[3] THEN 'a' WHEN embedding[2] >= embedding[3] THEN 'b' ELSE 'c' END AS class FROM embeddings",
    "time_quantiles": "SELECT o_orderpriority[1] AS round, round(quantile_cont(o_totalprice, 0.5), 4) AS p50, round(quantile_cont(o_totalprice, 0.9), 4) AS p90, round(quantile_cont(o_totalprice, 0.99), 4) AS p99 FROM orders GROUP BY 1",
    "first_last_values": """SELECT DISTINCT user_id, first_value(value) OVER w AS first, last_value(value) OVER w AS last, nth_value(value, 2) OVER w AS second FROM events
      WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)""",
}

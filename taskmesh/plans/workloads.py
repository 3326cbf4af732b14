"""Task frames from the given tables: task_id, row_id, features, label. Labels called planted are synthetic by construction."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from taskmesh.functions.draws import portable_uniform, uniform_for
from taskmesh.functions.vectors import dot
from taskmesh.operators.frames import binarize, filter_tasks, one_hot, standardize
from taskmesh.sources import load

LETTERS = "abcdefghijklmnopqrstuvwxyz"
LANGUAGES = ("de", "en", "es", "fr")
SEGMENTS = ("AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY")


def planted_vectors(spark: SparkSession, tasks: list[int], groups: list[int], d: int, own: float = 0.3, seed: int = 0) -> DataFrame:
    """task_id, u: a vector of the task's group plus some of its own, from portable draws."""
    rows = []
    for t, g in zip(tasks, groups, strict=True):
        rows.append((t, [2 * uniform_for("base", seed, g, j) - 1 + own * (2 * uniform_for("own", seed, t, j) - 1) for j in range(d)]))
    return spark.createDataFrame(rows, "task_id long, u array<double>")


def plant(df: DataFrame, vectors: DataFrame, flips: float = 0.03, seed: int = 0) -> DataFrame:
    """Labels by the sign of the product with the task's vector, a few of them turned by hash. vectors: a row per task."""
    sign = F.when(dot("features", "u") >= 0, 1.0).otherwise(-1.0)
    turned = F.when(portable_uniform("flip", seed, F.col("task_id"), F.col("row_id")) < flips, -sign).otherwise(sign)
    return df.join(F.broadcast(vectors), "task_id").withColumn("label", turned).drop("u")


def sensor_tasks(spark: SparkSession, sf_dir: str, m: int = 23, d: int | None = None, planted: bool = True) -> DataFrame:
    """Embeddings dealt to m sensors; planted: three groups of hyperplanes. d: only the first coordinates, without a bias."""
    df = load(spark, sf_dir, "embeddings")
    x = F.transform("embedding", lambda a: a.cast("double"))
    x = F.slice(x, 1, d) if d else F.concat(x, F.array(F.lit(1.0)))
    df = df.select((F.col("vec_id") % m).alias("task_id"), F.col("vec_id").alias("row_id"), x.alias("features"), F.when(F.col("label") < 5, 1.0).otherwise(-1.0).alias("label"))
    return plant(df, planted_vectors(spark, list(range(m)), [t % 3 for t in range(m)], d or 65)) if planted else df


def source_number(source: Column) -> Column:
    return F.coalesce(F.regexp_extract(source, r"(\d+)$", 1).try_cast("long"), F.lit(-1))


def letter_shares(text: Column) -> list[Column]:
    low = F.lower(text)
    letters = F.greatest(F.length(F.regexp_replace(low, "[^a-z]", "")), F.lit(1))
    return [(F.length(low) - F.length(F.replace(low, F.lit(c), F.lit("")))) / letters for c in LETTERS]


def hash_text(df: DataFrame, text: str = "text", buckets: int = 256, n: int = 2, out: str = "grams") -> DataFrame:
    """df and shares of hashed character n-grams of the lower-cased text, as an array of ``buckets``. A gram's bucket is the
    polynomial of its code points in 31, modulo ``buckets``. Whole texts, one pass over the characters, no shuffle."""
    from pyspark.sql import types as T

    plain = df.withColumn("_low", F.lower(F.coalesce(F.col(text), F.lit(""))))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            shares = []
            for low in b.column("_low").to_pylist():
                code = np.frombuffer(low.encode("utf-32-le", "replace"), np.uint32).astype(np.int64)
                grams = max(0, len(code) - n + 1)
                key = np.zeros(grams, np.int64)
                for k in range(n):
                    key = (key * 31 + code[k : k + grams]) % buckets
                shares.append(np.bincount(key, minlength=buckets) / max(1, grams))
            kept = [c for c in b.schema.names if c != "_low"]
            yield pa.RecordBatch.from_arrays([*[b.column(c) for c in kept], pa.array(shares, pa.list_(pa.float64()))], [*kept, out])

    schema = T.StructType([*[f for f in plain.schema.fields if f.name != "_low"], T.StructField(out, T.ArrayType(T.DoubleType()))])
    return plain.mapInArrow(run, schema)


def doc_language_tasks(spark: SparkSession, sf_dir: str, buckets: int = 256) -> DataFrame:
    """Sources predict a language of their own against the rest, from letters and hashed pairs of letters: a real signal, another
    target in each of four groups."""
    docs = load(spark, sf_dir, "documents", ["doc_id", "text", "lang", "source", "n_chars"]).where("text IS NOT NULL")
    task = source_number(F.col("source"))
    positive = F.element_at(F.array(*[F.lit(c) for c in LANGUAGES]), (F.pmod(task, F.lit(4)) + 1).cast("int"))
    docs = hash_text(docs, buckets=buckets)
    features = F.concat(F.array(*letter_shares(F.col("text"))), F.col("grams"), F.array(F.log1p("n_chars") / 10.0, F.lit(1.0)))
    return docs.select(task.alias("task_id"), F.col("doc_id").alias("row_id"), features.alias("features"), F.when(F.col("lang") == positive, 1.0).otherwise(-1.0).alias("label"))


def text_statistics(text: Column) -> list[Column]:
    """Shares of non-letters and digits, of repeated lines, mean word length, and the log of the length."""
    n = F.greatest(F.length(text), F.lit(1))
    lines = F.split(text, "\n")
    words = F.split(text, "\\s+")
    return [
        F.length(F.regexp_replace(text, "[\\p{L}\\s]", "")) / n, F.length(F.regexp_replace(text, "[^0-9]", "")) / n, 1.0 - F.size(F.array_distinct(lines)) / F.size(lines),
        F.length(F.regexp_replace(text, "\\s", "")) / F.size(words) / 10.0, F.log1p(F.length(text)) / 10.0,
    ]


def doc_quality_tasks(spark: SparkSession, sf_dir: str, by: str = "lang", target: str = "quality") -> DataFrame:
    """Labelled documents by language (262 to 39 of them) or source: quality or toxic from simple statistics."""
    docs = load(spark, sf_dir, "documents", ["doc_id", "text", "lang", "source"]).where("text IS NOT NULL")
    task = F.when(F.col("lang") == "de", 0).when(F.col("lang") == "en", 1).when(F.col("lang") == "es", 2).otherwise(3).cast("long") if by == "lang" else source_number(F.col("source"))
    joined = docs.join(load(spark, sf_dir, "labels"), "doc_id")
    return joined.select(task.alias("task_id"), F.col("doc_id").alias("row_id"), F.array(*text_statistics(F.col("text")), F.lit(1.0)).alias("features"), binarize(target, 1).alias("label"))


EVENT_TYPES = ("click", "view", "signup", "error", "purchase")


def event_window_tasks(spark: SparkSession, sf_dir: str, size: str = "2 days", slide: str = "1 day", planted: bool = False) -> DataFrame:
    """Users' sliding windows: statistics of values, shares of types, gaps, hours and a small spectrum, 40 numbers; label: a purchase
    in the window, or planted in three groups of users on standardized features."""
    events = load(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    k = F.from_json("props", "k int")["k"]
    angle = F.hour("ts") * (2 * math.pi / 24)
    gap = F.unix_micros("ts") / 1e6 - F.lag(F.unix_micros("ts") / 1e6).over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
    base = events.withColumn("k", k).withColumn("gap", gap).withColumn("eighth", F.floor(F.hour("ts") / 3)).withColumn("before", F.lag("value").over(Window.partitionBy("user_id").orderBy("ts", "event_id")))
    types = EVENT_TYPES
    stats = base.groupBy("user_id", F.window("ts", size, slide).alias("w")).agg(
        F.count("*").alias("n"), F.avg("value").alias("mean"), F.coalesce(F.stddev_pop("value"), F.lit(0.0)).alias("sd"), F.min("value").alias("least"), F.max("value").alias("most"),
        F.expr("percentile(value, array(0.25, 0.5, 0.75))").alias("q"), F.avg(F.col("value") * F.col("value")).alias("energy"), F.coalesce(F.try_divide(F.covar_pop("value", "before"), F.stddev_pop("value") * F.stddev_pop("before")), F.lit(0.0)).alias("lag1"),
        F.coalesce(F.avg("gap"), F.lit(0.0)).alias("gap"), F.coalesce(F.max("gap"), F.lit(0.0)).alias("most_gap"), F.coalesce(F.min("gap"), F.lit(0.0)).alias("least_gap"),
        F.coalesce(F.avg("k"), F.lit(0.0)).alias("k"), F.coalesce(F.max("k"), F.lit(0)).alias("most_k"), F.coalesce(F.min("k"), F.lit(0)).alias("least_k"),
        F.avg(F.pow("value", F.lit(3.0))).alias("third"), F.coalesce(F.avg(F.abs(F.col("value") - F.col("before"))), F.lit(0.0)).alias("change"), F.countDistinct("eighth").alias("eighths"), F.avg(F.sin(angle)).alias("s"), F.avg(F.cos(angle)).alias("c"),
        *[F.avg((F.col("event_type") == t).cast("double")).alias(f"is_{t}") for t in types], *[F.sum(F.when(F.col("eighth") == e, F.col("value")).otherwise(0.0)).alias(f"e{e}") for e in range(8)],
    )
    spectrum = [
        F.sqrt(F.pow(sum((F.col(f"e{e}") * math.cos(2 * math.pi * f * e / 8) for e in range(8)), F.lit(0.0)), 2) + F.pow(sum((F.col(f"e{e}") * math.sin(2 * math.pi * f * e / 8) for e in range(8)), F.lit(0.0)), 2)) / 1000.0
        for f in range(5)
    ]
    columns = [F.col("n") / 10.0, *[F.col(c) / 100.0 for c in ("mean", "sd", "least", "most")], *[F.col("q")[i] / 100.0 for i in range(3)], F.col("energy") / 1e4, F.col("lag1"), F.col("gap") / 86400.0, F.col("k") / 100.0, F.col("s"), F.col("c"), *[F.col(f"is_{t}") for t in types[:-1]], *spectrum,
               F.col("most_gap") / 86400.0, F.col("least_gap") / 86400.0, F.col("most_k") / 100.0, F.col("least_k") / 100.0, F.col("third") / 1e6, F.col("change") / 100.0, F.col("eighths") / 8.0,
               (F.col("most") - F.col("least")) / 100.0, *[F.col(f"e{e}") / 1000.0 for e in range(8)], F.lit(1.0)]
    out = stats.select(F.col("user_id").alias("task_id"), F.unix_seconds("w.start").alias("row_id"), F.array(*columns).alias("features"), F.when(F.col("is_purchase") > 0, 1.0).otherwise(-1.0).alias("label"))
    if not planted:
        return out
    users = sorted(r.user_id for r in events.select("user_id").distinct().collect())  # a row a task
    return plant(standardize(out, None), planted_vectors(spark, users, [u % 3 for u in users], len(columns)))


def _orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = load(spark, sf_dir, "orders").join(load(spark, sf_dir, "customer"), F.col("o_custkey") == F.col("c_custkey"))
    month = F.month("o_orderdate") * (2 * math.pi / 12)
    priorities = one_hot(F.substring("o_orderpriority", 1, 1), list("12345"))
    segments = one_hot("c_mktsegment", list(SEGMENTS))
    x = F.array(F.log1p("o_totalprice") / 10.0, *priorities, F.sin(month), F.cos(month), F.dayofweek("o_orderdate") / 7.0, F.col("c_acctbal") / 10000.0, *segments, F.lit(1.0))
    return orders.withColumn("features", x).withColumn("label", F.when(F.col("o_orderstatus") == "F", 1.0).otherwise(-1.0))


def customer_tasks(spark: SparkSession, sf_dir: str, min_rows: int = 1, planted: bool = False) -> DataFrame:
    """Orders by customer: many tasks of one to a few dozen points. planted: one hyperplane for each market segment."""
    df = _orders(spark, sf_dir).select(F.col("o_custkey").alias("task_id"), F.col("o_orderkey").alias("row_id"), "features", "label")
    df = filter_tasks(df, min_rows) if min_rows > 1 else df
    if not planted:
        return df
    known = {r.c_custkey: SEGMENTS.index(r.c_mktsegment) for r in load(spark, sf_dir, "customer", ["c_custkey", "c_mktsegment"]).collect()}  # a row a task
    return plant(standardize(df, None), planted_vectors(spark, list(known), list(known.values()), 16))


def nation_tasks(spark: SparkSession, sf_dir: str, planted: bool = True) -> DataFrame:
    """Orders by the customer's nation; planted: one hyperplane per region, shifted by nation."""
    df = _orders(spark, sf_dir).select(F.col("c_nationkey").cast("long").alias("task_id"), F.col("o_orderkey").alias("row_id"), "features", "label")
    if not planted:
        return df
    regions = {r.n_nationkey: r.n_regionkey for r in load(spark, sf_dir, "nation").collect()}  # 25 rows
    return plant(df, planted_vectors(spark, list(regions), list(regions.values()), 16))


def nation_clusters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The relation known beforehand: task_id (nation), cluster_id (region)."""
    nation, region = load(spark, sf_dir, "nation"), load(spark, sf_dir, "region")
    return nation.join(F.broadcast(region), F.col("n_regionkey") == F.col("r_regionkey")).select(F.col("n_nationkey").cast("long").alias("task_id"), F.col("r_regionkey").alias("cluster_id"))


def supplier_tasks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Line items by supplier: the throughput workload; label: returned."""
    items = load(spark, sf_dir, "lineitem").join(load(spark, sf_dir, "part", ["p_partkey", "p_size", "p_retailprice"]), F.col("l_partkey") == F.col("p_partkey"))
    month = F.month("l_shipdate") * (2 * math.pi / 12)
    x = [F.col("l_quantity") / 50.0, F.log1p("l_extendedprice") / 10.0, F.col("l_discount") * 10.0, F.col("l_tax") * 10.0, F.col("p_size") / 50.0, F.col("p_retailprice") / 2000.0, F.sin(month), F.cos(month), (F.col("l_linestatus") == "O").cast("double"), F.lit(1.0)]
    return items.select(F.col("l_suppkey").alias("task_id"), (F.col("l_orderkey") * 8 + F.col("l_linenumber")).alias("row_id"), F.array(*x).alias("features"), binarize("l_returnflag", "R").alias("label"))


def host_tasks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages by host: a long tail; label: the page says that it is English."""
    pages = load(spark, sf_dir, "pages").where("html IS NOT NULL")
    host = F.regexp_extract("url", "^[a-z]+://([^/:]+)", 1)
    body = F.regexp_replace("html", "<[^>]*>", " ")
    x = F.array(*letter_shares(body), F.log1p(F.length("html")) / 10.0, F.length(F.regexp_replace("html", "[^<]", "")) / F.greatest(F.length("html"), F.lit(1)), F.lit(1.0))
    lang = F.regexp_extract("html", 'lang="([a-z]+)', 1)
    return pages.select(F.conv(F.substring(F.md5(host.cast("binary")), 1, 8), 16, 10).cast("long").alias("task_id"), F.col("page_id").alias("row_id"), x.alias("features"), F.when(lang == "en", 1.0).otherwise(-1.0).alias("label"))


def conversation_tasks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Turns by conversation; label: the assistant speaks."""
    turns = load(spark, sf_dir, "conversations")
    text = F.coalesce("text", F.lit(""))
    n = F.greatest(F.length(text), F.lit(1))
    x = F.array(F.log1p(F.length(text)) / 10.0, F.length(F.regexp_replace(text, "[^?]", "")) / n, F.length(F.regexp_replace(text, "[^0-9]", "")) / n, F.length(F.regexp_replace(text, "[^ ]", "")) / n, F.lit(1.0))
    return turns.select(F.col("conv_id").alias("task_id"), F.col("turn").alias("row_id"), x.alias("features"), binarize("role", "assistant").alias("label"))


WORKLOADS = {
    "sensor": sensor_tasks, "doc_language": doc_language_tasks, "doc_quality": doc_quality_tasks, "event_windows": event_window_tasks, "customer": customer_tasks,
    "nation": nation_tasks, "supplier": supplier_tasks, "host": host_tasks, "conversation": conversation_tasks,
}


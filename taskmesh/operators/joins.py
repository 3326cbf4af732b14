"""Joins a user of the methods needs: as-of, interval, semi and anti, full outer, similarity of tasks, decontamination."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from taskmesh.functions.vectors import dot, norm2
from taskmesh.operators.relations import MAX_DENSE_TASKS


def asof(events: DataFrame, versions: DataFrame, key: str, event_time: str, version_time: str, columns: list[str]) -> DataFrame:
    """Each event with the latest version not later than it: one union and one window, no join. columns: of the version."""
    left = events.select(F.struct(*[F.col(c) for c in events.columns]).alias("_e"), F.col(key).alias("_k"), F.col(event_time).alias("_t"), F.lit(1).alias("_side"), F.lit(None).cast(versions.select(F.struct(*columns)).schema[0].dataType).alias("_v"))
    right = versions.select(F.lit(None).cast(left.schema["_e"].dataType).alias("_e"), F.col(key).alias("_k"), F.col(version_time).alias("_t"), F.lit(0).alias("_side"), F.struct(*columns).alias("_v"))
    last = F.last("_v", ignorenulls=True).over(Window.partitionBy("_k").orderBy("_t", "_side").rowsBetween(Window.unboundedPreceding, 0))
    return left.unionAll(right).withColumn("_v", last).where("_side = 1").select("_e.*", *[F.col("_v")[c].alias(c) for c in columns])


def within_intervals(events: DataFrame, intervals: DataFrame, key: str, time: str, start: str, end: str, bucket_seconds: int = 86400) -> DataFrame:
    """Events inside intervals of the same key: both are cut into time buckets, so a busy key spreads over tasks."""
    at = F.floor(F.unix_seconds(F.col(time)) / bucket_seconds).alias("_b")
    cut = intervals.withColumn("_b", F.explode(F.sequence(F.floor(F.unix_seconds(start) / bucket_seconds), F.floor(F.unix_seconds(end) / bucket_seconds))))
    return events.withColumn("_b", at).join(cut, [key, "_b"]).where(F.col(time).between(F.col(start), F.col(end))).drop("_b")


def reporting_tasks(tasks: DataFrame, answers: DataFrame) -> DataFrame:
    return tasks.join(answers, "task_id", "left_semi")


def silent_tasks(tasks: DataFrame, answers: DataFrame) -> DataFrame:
    return tasks.join(answers, "task_id", "left_anti")


def reconcile(old: DataFrame, new: DataFrame, keys: list[str], value: str) -> DataFrame:
    """Old and new state side by side, with where each row was found."""
    joined = old.withColumnRenamed(value, "old").join(new.withColumnRenamed(value, "new"), keys, "full")
    return joined.withColumn("found", F.when(F.col("old").isNull(), "new").when(F.col("new").isNull(), "old").otherwise("both"))


def merge_state(blocks: DataFrame, duals: DataFrame) -> DataFrame:
    """Every block with its duals, as a grouped pass over both sides at once: task_id, block_id, rows, alpha. A block without
    duals starts at zero; duals of a block that is gone are left out. blocks: task_id, block_id, ys."""

    def merge(left: pa.Table, right: pa.Table) -> pa.Table:
        known = dict(zip(right.column("block_id").to_pylist(), right.column("alpha").to_pylist(), strict=True))
        ids, sizes = left.column("block_id").to_pylist(), [len(y) for y in left.column("ys").to_pylist()]
        alphas = [known.get(b) or [0.0] * n for b, n in zip(ids, sizes, strict=True)]
        return pa.table({"task_id": left.column("task_id"), "block_id": left.column("block_id"), "rows": pa.array(sizes, pa.int32()), "alpha": pa.array(alphas, pa.list_(pa.float64()))})

    both = blocks.select("task_id", "block_id", "ys").groupBy("task_id").cogroup(duals.select("task_id", "block_id", "alpha").groupBy("task_id"))
    return both.applyInArrow(merge, "task_id long, block_id int, rows int, alpha array<double>")


def config_grid(spark, **lists) -> DataFrame:
    """Every combination of the given values, numbered."""
    out = spark.range(1).select()
    for name, values in lists.items():
        out = out.crossJoin(spark.createDataFrame([(v,) for v in values], [name]))
    return out.withColumn("config_id", F.row_number().over(Window.orderBy(*lists)) - 1)


def related_tasks(vectors: DataFrame, column: str, k: int) -> DataFrame:
    """Each task's k most similar others by cosine (ties: the smaller id). It compares all pairs of tasks, as dense relations do,
    and so refuses more of them than those."""
    tasks = vectors.count()
    if tasks > MAX_DENSE_TASKS:
        raise ValueError(f"{tasks} tasks; all pairs of at most {MAX_DENSE_TASKS}")
    a, b = vectors.select("task_id", F.col(column).alias("a")), vectors.select(F.col("task_id").alias("other"), F.col(column).alias("b"))
    cosine = dot("a", "b") / F.sqrt(norm2("a") * norm2("b"))
    pairs = a.join(b, F.col("task_id") != F.col("other")).select("task_id", "other", cosine.alias("cosine"))
    rank = F.row_number().over(Window.partitionBy("task_id").orderBy(F.desc(F.round("cosine", 9)), "other"))
    return pairs.withColumn("rank", rank).where(F.col("rank") <= k)


def laplacian(edges: DataFrame) -> DataFrame:
    """edges: i, j, weight, each once. The Laplacian's entries as i, j, value."""
    both = edges.select("i", "j", "weight").unionAll(edges.select(F.col("j").alias("i"), F.col("i").alias("j"), "weight"))
    degree = both.groupBy("i").agg(F.sum("weight").alias("value")).select("i", F.col("i").alias("j"), "value")
    return degree.unionAll(both.select("i", "j", (-F.col("weight")).alias("value")))


def shingles(text, words: int = 8):
    """Distinct word n-grams of a text, as an array of hashes."""
    tokens = F.filter(F.split(F.lower(F.regexp_replace(text, "[^\\p{L}\\p{N}]+", " ")), " "), lambda w: w != "")

    def runs(t):
        at = F.sequence(F.lit(1), F.size(t) - words + 1)
        return F.when(F.size(t) >= words, F.transform(at, lambda i: F.xxhash64(F.array_join(F.slice(t, i, words), " ")))).otherwise(F.array().cast("array<bigint>"))

    # An array of one list stands for a variable, so a text is split once and not again for each of its runs.
    return F.array_distinct(F.transform(F.array(tokens), runs)[0])


def decontaminate(docs: DataFrame, benchmark: DataFrame, words: int = 8) -> DataFrame:
    """Documents that share no run of so many words with the benchmark."""
    known = benchmark.select(F.explode(shingles(F.col("text"), words)).alias("s")).distinct()
    hit = docs.select("doc_id", F.explode(shingles(F.col("text"), words)).alias("s")).join(known, "s", "left_semi").select("doc_id").distinct()
    return docs.join(hit, "doc_id", "left_anti")

"""Task frames: one row per point (task_id, row_id, features, label), their checks, splits, folds, samples and packing.

Packing is the only shuffle of features: afterwards a row is a block of a task, and every round reads blocks in place.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from taskmesh.functions.draws import portable_uniform
from taskmesh.functions.vectors import norm2
from taskmesh.operators.vector_aggregates import feature_moments
from taskmesh.sources import materialise

BLOCK_ROWS = 4096


def binarize(column: Column | str, positive: object) -> Column:
    """One against the rest, as +1 and -1."""
    column = F.col(column) if isinstance(column, str) else column
    return F.when(column.eqNullSafe(F.lit(positive)), F.lit(1.0)).otherwise(F.lit(-1.0))


def assemble(df: DataFrame, columns: list[str], out: str = "features", bias: bool = False) -> DataFrame:
    return df.withColumn(out, F.array(*[F.col(c).cast("double") for c in columns], *[F.lit(1.0)] * bias))


def add_bias(df: DataFrame) -> DataFrame:
    return df.withColumn("features", F.concat("features", F.array(F.lit(1.0))))


def valid_points(df: DataFrame, d: int, classification: bool = True) -> DataFrame:
    """Rows with all of d finite features, and a label that is +1 or -1 where classes are learned."""
    bad = F.exists("features", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    label = F.col("label").isin(1.0, -1.0) if classification else ~F.isnan("label")
    return df.where(F.col("task_id").isNotNull() & F.col("features").isNotNull() & (F.size("features") == d) & ~bad & F.col("label").isNotNull() & label)


def validate(df: DataFrame, classification: bool = True) -> int:
    """Raises on null, ragged or non-finite features, wrong labels or repeated rows; returns the number of features."""
    size = F.size("features")
    bad = F.exists("features", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    wrong = ~F.col("label").isin(1.0, -1.0) if classification else F.isnan("label")
    low, high, odd = df.agg(F.min(size), F.max(size), F.count_if(F.coalesce(bad | wrong | F.col("task_id").isNull(), F.lit(True)))).first()
    if odd or low != high:
        raise ValueError(f"{odd} unusable rows; between {low} and {high} features")
    if not df.groupBy("task_id", "row_id").count().where("count > 1").isEmpty():
        raise ValueError("repeated task_id, row_id")
    return int(high or 0)


def filter_tasks(df: DataFrame, min_rows: int = 1, max_rows: int | None = None) -> DataFrame:
    n = df.groupBy("task_id").agg(F.count("*").alias("_n"))
    kept = n.where(F.col("_n") >= min_rows) if max_rows is None else n.where(F.col("_n").between(min_rows, max_rows))
    return df.join(kept, "task_id", "left_semi")


def select_tasks(
    df: DataFrame, ids: list[int] | None = None, between: tuple[int, int] | None = None, pattern: str | None = None, equal: int | None = None, missing: bool | None = None, column: str = "task_id"
) -> DataFrame:
    """Rows by their task: one of ``ids``, within a range, by a pattern of the id as text, equal to one value (null-safe), or with
    a null id (missing) or not; all that are given must hold. column: the task's, or another that names it."""
    c = F.col(column)
    for wanted in (
        None if ids is None else c.isin(ids), None if between is None else c.between(*between), None if pattern is None else c.cast("string").rlike(pattern),
        None if equal is None else c.eqNullSafe(F.lit(equal)), None if missing is None else c.isNull() == F.lit(missing),
    ):
        df = df if wanted is None else df.where(wanted)
    return df


def one_hot(column: Column | str, categories: list) -> list[Column]:
    """A 0/1 column for each category; a value that is none of them, or null, has none set."""
    column = F.col(column) if isinstance(column, str) else column
    return [F.coalesce((column == F.lit(c)).cast("double"), F.lit(0.0)) for c in categories]


def task_sizes(df: DataFrame) -> DataFrame:
    return df.groupBy("task_id").agg(F.count("*").alias("n"), F.count_if(F.col("label") > 0).alias("positives"))


def imbalance(df: DataFrame) -> DataFrame:
    """Tasks, points, the smallest, median and largest task, largest over median, and the Gini coefficient of sizes.

    Ranks come from how many tasks have each size, so what is put in order is the distinct sizes, not the tasks."""
    n = df.groupBy("task_id").agg(F.count("*").alias("n")).groupBy("n").agg(F.count("*").alias("k"))
    below = F.coalesce(F.sum("k").over(Window.orderBy("n").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    ranked = n.withColumn("r", F.col("k") * below + F.col("k") * (F.col("k") + 1) / 2)  # the sum of the ranks of one size
    stats = ranked.agg(
        F.sum("k").alias("tasks"), F.sum(F.col("n") * F.col("k")).alias("points"), F.min("n").alias("least"), F.expr("percentile(n, 0.5, k)").alias("median"), F.max("n").alias("most"),
        F.sum(F.col("n") * F.col("r")).alias("_rn"),
    )
    gini = 2.0 * F.col("_rn") / (F.col("tasks") * F.col("points")) - (F.col("tasks") + 1) / F.col("tasks")
    return stats.select("tasks", "points", "least", "median", "most", (F.col("most") / F.col("median")).alias("most_over_median"), gini.alias("gini"))


def _shuffled(trial: int | Column, seed: int) -> Column:
    return portable_uniform("split", seed, trial if isinstance(trial, Column) else F.lit(trial), F.col("task_id"), F.col("row_id"))


def ranked(df: DataFrame, draw: Column, keys: tuple[str, ...] = ("task_id",), lot: int = BLOCK_ROWS) -> DataFrame:
    """Adds _n, the rows of a row's key, and _rank, its place from 1 on in the order of ``draw`` (uniform in [0, 1)), then row_id.

    A key of any size is spread: its rows are cut into lots by ranges of the draw, about ``lot`` rows each, ranked within a lot,
    and lots add the rows of those before them. So no key's rows meet in one task."""
    own = df.withColumn("_u", draw)
    sizes = own.groupBy(*keys).agg(F.count("*").alias("_n"))
    own = _with(own, sizes, keys).withColumn("_lot", F.floor(F.col("_u") * F.ceil(F.col("_n") / lot)).cast("long"))
    lots = own.groupBy(*keys, "_lot").agg(F.count("*").alias("_c"))
    ahead = F.sum("_c").over(Window.partitionBy(*keys).orderBy("_lot")) - F.col("_c")
    within = F.row_number().over(Window.partitionBy(*keys, "_lot").orderBy("_u", "row_id"))
    out = _with(own.withColumn("_place", within), lots.select(*keys, "_lot", ahead.alias("_ahead")), (*keys, "_lot"))
    return out.withColumn("_rank", F.col("_place") + F.col("_ahead")).drop("_u", "_lot", "_place", "_ahead")


def _with(df: DataFrame, sums: DataFrame, keys: tuple[str, ...]) -> DataFrame:
    """Rows with the sums of their key; the sums are rebalanced, so that adaptive execution may split a hot key of ``df``."""
    named = sums.withColumnsRenamed({k: f"_k_{k}" for k in keys}).hint("rebalance")
    same = None
    for k in keys:
        one = F.col(k).eqNullSafe(F.col(f"_k_{k}"))
        same = one if same is None else same & one
    return df.join(named, same).drop(*[f"_k_{k}" for k in keys])


def split(df: DataFrame, trial: int = 0, share: float = 0.75, seed: int = 0) -> DataFrame:
    """Within each task the first ceil(share * n) rows by hash are for training."""
    out = ranked(df, _shuffled(trial, seed))
    return out.withColumn("split", F.when(F.col("_rank") <= F.ceil(F.col("_n") * F.lit(share)), "train").otherwise("test")).drop("_rank", "_n")


def tile(rank: Column, n: Column, k: int) -> Column:
    """Which of k nearly equal parts, the larger ones first, a rank from 1 to n is in; from 0 on."""
    size, more = F.floor(n / k), F.pmod(n, F.lit(k))
    head = more * (size + 1)
    tail = more + F.floor((rank - 1 - head) / F.greatest(size, F.lit(1)))
    return F.when(rank <= head, F.floor((rank - 1) / (size + 1))).otherwise(tail).cast("int")


def folds(df: DataFrame, k: int = 5, trial: int = 0, seed: int = 0) -> DataFrame:
    """Within each task, k folds of nearly equal size by hash."""
    return ranked(df, _shuffled(trial, seed + 1)).withColumn("fold", tile(F.col("_rank"), F.col("_n"), k)).drop("_rank", "_n")


def bernoulli(df: DataFrame, p: float | Column, seed: int = 0) -> DataFrame:
    """Each row by a hash of its own: no dependence on partitions, unlike sample()."""
    return df.where(portable_uniform("keep", seed, F.col("task_id"), F.col("row_id")) < p)


def stratified(df: DataFrame, per_task: int, seed: int = 0) -> DataFrame:
    """Exactly so many rows of each task (all, if it has fewer)."""
    return ranked(df, portable_uniform("pick", seed, F.col("task_id"), F.col("row_id"))).where(F.col("_rank") <= per_task).drop("_rank", "_n")


def bootstrap_weights(df: DataFrame, seed: int = 0) -> DataFrame:
    """A Poisson(1) weight for each row, by hash: how many steps of the distribution the draw has reached. The draw has 32 bits,
    so steps end where the rest has less than one of its values."""
    u = portable_uniform("boot", seed, F.col("task_id"), F.col("row_id"))
    return df.withColumn("weight", sum(((u >= s).cast("int") for s in poisson_steps()), F.lit(0)))


def poisson_steps(least: float = 2.0**-32) -> list[float]:
    """Cumulative probabilities of a Poisson(1) number, until the rest is below ``least``."""
    out, total, term, k = [], 0.0, math.exp(-1.0), 0
    while 1.0 - total >= least:
        total += term
        out.append(total)
        k += 1
        term /= k
    return out


def skew_subsample(df: DataFrame, levels: int = 4, seed: int = 0) -> DataFrame:
    """Keeps 1, 1/2, 1/4, ... of tasks in turn."""
    return bernoulli(df, F.pow(F.lit(0.5), F.pmod(F.col("task_id"), F.lit(levels))), seed)


def standardize(df: DataFrame, fit_on: str | None = "train") -> DataFrame:
    """Each coordinate by the mean and deviation of the training rows (all rows, if fit_on is None); constants stay."""
    base = df.where(F.col("split") == fit_on) if fit_on else df
    moments = feature_moments(base).agg(F.transform(F.sort_array(F.collect_list(F.struct("coordinate", "mean", "sd"))), lambda s: F.struct(s["mean"], s["sd"])).alias("_m"))
    scaled = F.zip_with("features", "_m", lambda x, m: F.when(m["sd"] > 0, (x - m["mean"]) / m["sd"]).otherwise(x))
    return df.crossJoin(F.broadcast(moments)).withColumn("features", scaled).drop("_m")  # one row of d numbers


def blocked(df: DataFrame, block_rows: int = BLOCK_ROWS, seed: int = 0) -> DataFrame:
    """Adds block_id. A task's rows go to ceil(n / block_rows) blocks by a draw of their own, so a block has block_rows points or
    fewer on average, and all of a task that has no more than that. No order over a task is needed, only its size."""
    sizes = df.groupBy("task_id").agg(F.count("*").alias("_n"))
    u = portable_uniform("block", seed, F.col("task_id"), F.col("row_id"))
    return _with(df, sizes, ("task_id",)).withColumn("block_id", F.floor(u * F.ceil(F.col("_n") / block_rows)).cast("int")).drop("_n")


def pack(df: DataFrame, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """Blocks of about block_rows points: task_id, block_id, row_ids, xs, ys, norms, rows in order of row_id.

    A task of any size is cut before its rows are gathered, so no task's rows ever meet in one array or one task."""
    cut = blocked(df.select("task_id", "row_id", "features", "label"), block_rows)
    rows = F.sort_array(F.collect_list(F.struct("row_id", "label", "features")))
    packed = cut.groupBy("task_id", "block_id").agg(rows.alias("r"))
    get = lambda field: F.transform("r", lambda s: s[field])
    packed = packed.select("task_id", "block_id", get("row_id").alias("row_ids"), get("features").alias("xs"), get("label").alias("ys"))
    return packed.withColumn("norms", F.transform("xs", norm2))


def block_places(packed: DataFrame) -> DataFrame:
    """task_id, block_id, places: of each row of a block its place in the whole task, from 0 on in order of row_id. Rows are cut by
    ranges of task and row, and ranges add the rows of those before them, so no task's rows meet in one place."""
    spark = packed.sparkSession
    rows = packed.select("task_id", "block_id", F.posexplode("row_ids").alias("at", "row_id"))
    width = int(spark.conf.get("spark.sql.shuffle.partitions"))
    cut = materialise(rows.repartitionByRange(width, "task_id", "row_id").withColumn("_lot", F.spark_partition_id()), "ranges")
    lots = cut.groupBy("task_id", "_lot").agg(F.count("*").alias("_c"))
    ahead = F.sum("_c").over(Window.partitionBy("task_id").orderBy("_lot")) - F.col("_c")
    within = F.row_number().over(Window.partitionBy("task_id", "_lot").orderBy("row_id", "block_id", "at")) - 1
    placed = _with(cut.withColumn("_place", within), lots.select("task_id", "_lot", ahead.alias("_ahead")), ("task_id", "_lot"))
    rows = F.sort_array(F.collect_list(F.struct("at", (F.col("_place") + F.col("_ahead")).alias("place"))))
    return placed.groupBy("task_id", "block_id").agg(F.transform(rows, lambda s: s["place"]).alias("places"))


def explode_blocks(packed: DataFrame, *extra: str) -> DataFrame:
    """Back to points; ``extra`` names arrays as long as the block."""
    zipped = F.explode(F.arrays_zip("row_ids", "xs", "ys", *extra)).alias("z")
    return packed.select("task_id", "block_id", zipped).select(
        "task_id", "block_id", F.col("z.row_ids").alias("row_id"), F.col("z.xs").alias("features"), F.col("z.ys").alias("label"), *[F.col(f"z.{e}").alias(e) for e in extra]
    )


def composite(df: DataFrame, configs: DataFrame) -> DataFrame:
    """Every task under every configuration, as a task of its own: config_id * 2**32 + task_id. configs: config_id, few rows.
    Configurations are independent diagonal blocks, so one frame trains them all."""
    return df.crossJoin(F.broadcast(configs)).withColumn("base_task", F.col("task_id")).withColumn("task_id", F.shiftleft(F.col("config_id").cast("long"), 32) + F.col("task_id"))

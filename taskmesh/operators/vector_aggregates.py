"""Sums and means of array columns by group: by coordinate, so partial sums are combined before the shuffle."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def _by_coordinate(df: DataFrame, keys: list[str], column: str, aggregate, out: str) -> DataFrame:
    long = df.select(*keys, F.posexplode(column).alias("_i", "_x"))
    summed = long.groupBy(*keys, "_i").agg(aggregate(F.col("_x").cast("double")).alias("_x"))
    gathered = F.sort_array(F.collect_list(F.struct("_i", "_x")))
    return summed.groupBy(*keys).agg(F.transform(gathered, lambda s: s["_x"]).alias(out))


def vector_sum(df: DataFrame, keys: list[str], column: str, out: str | None = None) -> DataFrame:
    return _by_coordinate(df, keys, column, F.sum, out or column)


def vector_mean(df: DataFrame, keys: list[str], column: str, out: str | None = None) -> DataFrame:
    return _by_coordinate(df, keys, column, F.avg, out or column)


def gram(df: DataFrame, column: str) -> DataFrame:
    """X'X over all rows as i, j, value with i <= j; d * d rows, summed before the shuffle."""
    pairs = df.select(F.posexplode(column).alias("i", "a"), F.col(column).alias("_v")).select("i", "a", F.posexplode("_v").alias("j", "b")).where("i <= j")
    return pairs.groupBy("i", "j").agg(F.sum(F.col("a") * F.col("b")).alias("value"))


def feature_moments(df: DataFrame, column: str = "features", keys: tuple[str, ...] = ()) -> DataFrame:
    """Mean and sample deviation of each coordinate."""
    long = df.select(*keys, F.posexplode(column).alias("coordinate", "x"))
    return long.groupBy(*keys, "coordinate").agg(F.avg("x").alias("mean"), F.stddev_samp("x").alias("sd"), F.count("x").alias("n"))

"""Other formats in and out: files with a declared schema, event streams, packed blocks, models and logs."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

EVENT_SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def load_any(spark: SparkSession, path: str, format: str, schema: str | T.StructType, **options: str) -> DataFrame:  # noqa: A002
    """csv, json, orc, text or parquet, with the schema given, never inferred."""
    return spark.read.format(format).schema(schema).options(**options).load(path)


def stream_events(spark: SparkSession, path: str, files_per_trigger: int = 1, schema: str = EVENT_SCHEMA) -> DataFrame:
    """A folder of event files as a stream, with ts as an instant."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def save_blocks(packed: DataFrame, table: str, buckets: int) -> None:
    """Packed blocks as a table bucketed and sorted by task: later joins by task need no exchange on this side."""
    packed.write.mode("overwrite").bucketBy(buckets, "task_id").sortBy("task_id", "block_id").saveAsTable(table)


def save_model(weights: DataFrame, meta: dict, path: str) -> None:
    """Weights as Parquet, the relation and settings as one JSON line beside them."""
    weights.write.mode("overwrite").parquet(f"{path}/weights")
    weights.sparkSession.createDataFrame([(json.dumps(meta, sort_keys=True),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/meta")


def load_model(spark: SparkSession, path: str) -> tuple[DataFrame, dict]:
    return spark.read.schema("task_id long, w array<double>").parquet(f"{path}/weights"), json.loads(spark.read.text(f"{path}/meta").first().value)


def append_round_log(log: DataFrame, path: str) -> None:
    log.write.mode("append").partitionBy("run").parquet(path)


def checkpoint_state(df: DataFrame) -> DataFrame:
    """Cuts the lineage with a reliable checkpoint; the session must name a checkpoint folder."""
    return df.checkpoint(eager=True)

"""Mixing sources to target weights, with DataFrame functions only.

Every source has a weight; the mix has as many words as the corpus. A source's target is its share by weight, but never
more than ``max_repeat`` times its own size: what is above that is shared again among the others, which is the level
``t = min(max_repeat * size, level * weight)`` with one common level. The repetition rate of a source is target / size:
each of its documents is emitted ``floor(rate)`` times, and once more if a uniform number, hashed from a seed and its
doc_id, is below the fraction of the rate. Bernoulli draws of a few long documents can miss a small source's target, so
``seeds`` seeds are weighed in one pass (sums only) and each source keeps the one whose words come nearest.

Defined cases: null text has size 0; a null source is a source of its own, last in order; a source of size 0 has target
0 and its documents are emitted once at most (rate 0: not at all); rows that repeat a doc_id get the same draw; an empty
table gives an empty result; columns of any other name pass through ``mix``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from taskmesh.sources import load, materialise

WORDS = r"[^\x20\x09-\x0D]+"


def word_count(text: Column) -> Column:
    """Number of words; null counts as empty."""
    return F.coalesce(F.regexp_count(text, F.lit(WORDS)), F.lit(0)).cast("long")


def draw(doc_id: Column, seed: Column | int) -> Column:
    """A uniform number in [0, 1) that depends on the seed and the document only: the document's md5 gives a start and a step of
    32 bits, and each seed is a step further, so one digest serves all seeds and any engine can draw the same."""
    seed = F.lit(seed) if isinstance(seed, int) else seed
    digest = F.md5(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary"))
    start, step = (F.conv(F.substring(digest, at, 8), 16, 10).cast("long") for at in (1, 9))
    return F.pmod(start + seed.cast("long") * step, F.lit(1 << 32)) / F.lit(float(1 << 32))


def targets(sizes: DataFrame, max_repeat: int = 3, weights: tuple[int, ...] = (1, 2, 3)) -> DataFrame:
    """sizes: source, source_size, one row for each source. Adds weight (``weights`` in turn by code point, null last) and target."""
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    weighed = sizes.withColumn(
        "weight", F.element_at(F.array(*[F.lit(float(w)) for w in weights]), F.pmod(F.row_number().over(by_name) - 1, F.lit(len(weights))) + 1)
    )
    # Sources reach their ceiling in the order of ceiling / weight. The level that leaves out those before a source falls
    # from there on once it is below that source's reach, so the greatest such level is the right one.
    by_ceiling = Window.orderBy("_reach", F.col("source").asc_nulls_last())
    everything = Window.partitionBy()
    ceiling = F.lit(float(max_repeat)) * F.col("source_size")
    ranked = (
        weighed.withColumn("_reach", ceiling / F.col("weight"))
        .withColumn("_total", F.sum("source_size").over(everything).cast("double"))
        .withColumn("_weights", F.sum("weight").over(everything))
        .withColumn("_full", F.coalesce(F.sum(ceiling).over(by_ceiling.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0)))
        .withColumn("_gone", F.coalesce(F.sum("weight").over(by_ceiling.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0)))
        .withColumn("_level", (F.col("_total") - F.col("_full")) / (F.col("_weights") - F.col("_gone")))
        .withColumn("_common", F.max(F.when(F.col("_level") <= F.col("_reach"), F.col("_level"))).over(everything))
    )
    return ranked.select("source", "source_size", "weight", F.least(ceiling, F.col("_common") * F.col("weight")).alias("target"))


def _key(source: Column) -> Column:
    """A join key that holds null sources too."""
    return F.coalesce(F.concat(F.lit("="), source), F.lit(""))


def rates(sized: DataFrame, max_repeat: int = 3, weights: tuple[int, ...] = (1, 2, 3), seeds: int = 32) -> DataFrame:
    """sized: doc_id, source, size (read twice: give a stored table). One stored row for each source: key, sizes, target, rate in two parts, seed."""
    sources = targets(sized.groupBy("source").agg(F.sum("size").alias("source_size")), max_repeat, weights)
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0)) + F.lit(1e-12)
    sources = materialise(
        sources.select(_key(F.col("source")).alias("_key"), "source_size", "target", F.floor(rate).alias("_whole"), (rate - F.floor(rate)).alias("_part")),
        "mix-sources",
    )
    part = F.col("_part")
    tried = (
        sized.select(_key(F.col("source")).alias("_key"), "doc_id", "size")
        .join(sources.select("_key", "_part"), "_key")
        .groupBy("_key")
        .agg(*[F.sum(F.when(draw(F.col("doc_id"), s) < part, F.col("size")).otherwise(F.lit(0))).alias(f"_s{s}") for s in range(seeds)])
    )
    missing = F.col("target") - F.col("_whole") * F.col("source_size")
    best = F.array_min(F.array(*[F.struct(F.abs(F.col(f"_s{s}") - missing).alias("miss"), F.lit(s).alias("seed")) for s in range(seeds)]))["seed"]
    return materialise(sources.join(tried, "_key").select("_key", "source_size", "target", "_whole", "_part", best.alias("_seed")), "mix-rates")


def with_copies(rows: DataFrame, by_source: DataFrame, max_repeat: int = 3) -> DataFrame:
    """rows: any with doc_id and source. Adds source_size, target and copies (how often the mix has the row)."""
    copies = F.col("_whole") + (draw(F.col("doc_id"), F.col("_seed")) < F.col("_part")).cast("long")
    joined = rows.withColumn("_key", _key(F.col("source"))).join(by_source, "_key")
    return joined.withColumn("copies", F.least(copies, F.lit(max_repeat)).cast("long")).drop("_key", "_whole", "_part", "_seed")


def sizes(docs: DataFrame) -> DataFrame:
    """A stored table of doc_id, source and size."""
    return materialise(docs.select("doc_id", "source", word_count(F.col("text")).alias("size")), "mix-sizes")


def mix(docs: DataFrame, max_repeat: int = 3, weights: tuple[int, ...] = (1, 2, 3), seeds: int = 32) -> DataFrame:
    """The mixed corpus: the rows of ``docs``, each as often as its plan says. Texts are not shuffled: rates join by source."""
    own = docs.columns
    body = docs.select("doc_id", "source", F.struct(*[F.col(f"`{c}`") for c in own]).alias("_row"))
    out = with_copies(body, rates(sizes(docs), max_repeat, weights, seeds), max_repeat).where("copies > 0")
    out = out.select("_row", F.explode(F.sequence(F.lit(1), F.col("copies").cast("int"))).alias("_copy"))
    return out.select(*[F.col("_row").getField(c).alias(c) for c in own])


def op9_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    sized = sizes(load(spark, sf_dir, "documents", ["doc_id", "text", "source"]))
    plan = with_copies(sized, rates(sized))
    return plan.select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("copies")).alias("taken"), "copies", "source")

"""Near duplicates by one-permutation MinHash.

A document is the set of its distinct word shingles, as 64-bit hashes. One hash of each shingle serves all ``bins``: its
high part names the bin and the least value in a bin is the bin's signature. Empty bins borrow from a non-empty bin that a
hash sequence of the bin number finds (optimal densification: each empty bin follows its own sequence). ``rows``
neighbouring bins make a band, and documents whose bands agree share a bucket.

Steps, all of them bounded in pairs:

1. Documents with equal sets are one class; its least doc_id stands for it.
2. In each bucket the class with the least doc_id is the centre of a star: one candidate edge for every other class, so a
   bucket of n classes proposes n - 1 pairs, not n * n / 2. Only a class's least centre is tried first.
3. Candidates are confirmed on full sets; confirmed links give components.
4. What stars may have missed: pairs of one bucket whose classes are still in different components, and that were not
   tried. Sizes and one-bit sketches rule nearly all of them out (the bound on the sketches' difference is five standard
   deviations from what a pair at the threshold has); of what is left, pairs that share none of their rarest shingles
   cannot reach the threshold (exact prefix and position bounds), and the others are confirmed on full sets too. A bucket
   that lies within one component, such as a large group of near copies, proposes nothing here. So every pair of classes that shares a bucket
   is linked, tried, or already connected: components lose nothing to the stars.
5. Components come from distributed label exchange; the least doc_id of a component is kept.

Defined cases: null text and text without words have an empty set and link with nothing; texts with fewer words than a
shingle have one shingle, their whole sequence; rows that repeat a doc_id are each judged by their own text, and links of
any of them count for the id; a row with null doc_id that has a text never links, and is kept; an empty table gives an
empty result; columns of any other name pass through ``drop_near_duplicates``.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from taskmesh.llm.graph import connected_components
from taskmesh.llm.words import CACHE_ENTRIES, lean, text_bytes, words
from taskmesh.sources import load, materialise

U64 = np.uint64
_M1, _M2, _M3 = U64(0x9E3779B97F4A7C15), U64(0xBF58476D1CE4E5B9), U64(0x94D049BB133111EB)


@dataclass(frozen=True)
class MinHashConfig:
    shingle: int = 5
    percent: int = 80
    bins: int = 256
    rows: int = 7

    @property
    def bands(self) -> int:
        return self.bins // self.rows


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijection on 64-bit numbers that spreads every bit."""
    x = (x ^ (x >> U64(30))) * _M2
    x = (x ^ (x >> U64(27))) * _M3
    return x ^ (x >> U64(31))


class WordHashes(dict):
    """Cache of words' 64-bit hashes, bounded."""

    def __missing__(self, word: bytes) -> int:
        if len(self) >= CACHE_ENTRIES:
            self.clear()
        self[word] = found = xxhash.xxh64_intdigest(word)
        return found


def shingle_set(tokens: list[bytes], n: int, hashes: WordHashes) -> np.ndarray:
    """Sorted distinct hashes of the shingles; of the whole sequence, if it is shorter than one."""
    if not tokens:
        return np.zeros(0, U64)
    w = np.fromiter(map(hashes.__getitem__, tokens), U64, len(tokens))
    span = min(n, len(w))
    out = np.full(len(w) - span + 1, U64(span))
    for k in range(span):
        out = mix64(out * _M1 + w[k : len(w) - span + 1 + k])
    return np.unique(out)


def set_key(shingles: np.ndarray) -> int:
    """Of a set that is not empty; equal sets have equal keys."""
    return xxhash.xxh64_intdigest(shingles.tobytes()) - (1 << 63)


def donors(bins: int, tries: int = 64) -> np.ndarray:
    """For each bin, the sequence of bins it borrows from while it is empty."""
    grid = np.arange(bins, dtype=U64)[:, None] * U64(1_000_003) + np.arange(1, tries + 1, dtype=U64)[None, :]
    return (mix64(grid * _M1) % U64(bins)).astype(np.int64)


def signature(shingles: np.ndarray, bins: int, sequence: np.ndarray) -> np.ndarray:
    """The densified signature of a sorted set that is not empty; bins is a power of two."""
    shift = U64(64 - (bins.bit_length() - 1))
    bounds = np.arange(bins, dtype=U64) << shift
    first = np.searchsorted(shingles, bounds)
    last = np.append(first[1:], len(shingles))
    full = first < last
    sig = shingles[np.minimum(first, len(shingles) - 1)]
    empty = np.flatnonzero(~full)
    if len(empty):
        hit = full[sequence[empty]]
        at = hit.argmax(axis=1)
        found = hit[np.arange(len(empty)), at]
        donor = sequence[empty, at]
        left = np.flatnonzero(~found)
        if len(left):  # no luck in all tries: walk on to the next full bin
            where = np.flatnonzero(full)
            donor[left] = where[np.searchsorted(where, empty[left]) % len(where)]
        sig[empty] = mix64(sig[donor] + U64(1) + empty.astype(U64) * _M1)
    return sig


def _describe(config: MinHashConfig):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes, sequence = WordHashes(), donors(config.bins)
        used = config.bands * config.rows
        numbers = np.arange(config.bands, dtype=U64)
        for b in batches:
            n, key, bands, sketch = [], [], [], []
            for text in text_bytes(b):
                own = shingle_set(words(text), config.shingle, hashes)
                n.append(len(own))
                if not len(own):
                    key.append(0), bands.append(None), sketch.append(None)
                    continue
                key.append(set_key(own))
                sig = signature(own, config.bins, sequence)
                grouped = sig[:used].reshape(config.bands, config.rows)
                h = numbers * _M1
                for k in range(config.rows):
                    h = mix64(h * _M1 + grouped[:, k])
                bands.append(h.view(np.int64))
                sketch.append(np.packbits((mix64(sig) & U64(1)).astype(np.uint8)).view(np.int64))
            yield pa.RecordBatch.from_arrays(
                [b.column("doc_id"), pa.array(n, pa.int64()), pa.array(key, pa.int64()), pa.array(bands, pa.list_(pa.int64())), pa.array(sketch, pa.list_(pa.int64()))],
                ["doc_id", "n", "key", "bands", "sketch"],
            )

    return run


def _sets(config: MinHashConfig):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = WordHashes()
        for b in batches:
            own = ((key, shingle_set(words(text), config.shingle, hashes)) for key, text in zip(b.column("key").to_pylist(), text_bytes(b), strict=True))
            own = [(key, s) for key, s in own if set_key(s) == key]  # an id that repeats has other texts too
            yield pa.RecordBatch.from_arrays([pa.array([k for k, _ in own], pa.int64()), pa.array([s.view(np.int64) for _, s in own], pa.list_(pa.int64()))], ["key", "shingles"])

    return run


def _size_fits(percent: int, a: str, b: str) -> Column:
    """A pair can only reach the threshold if its smaller set is large enough."""
    return F.least(a, b) * 100 >= F.greatest(a, b) * percent


def _sketch_fits(config: MinHashConfig, a: str, b: str, na: str, nb: str) -> Column:
    """Differing bits of a pair at the threshold: mean plus five standard deviations; few shingles mean fewer free bits."""
    p = (1 - config.percent / 100) / 2
    differ = sum((F.bit_count(F.col(a)[i].bitwiseXOR(F.col(b)[i])) for i in range(config.bins // 64)), F.lit(0))
    free = F.least(F.least(na, nb), F.lit(config.bins)).cast("double")
    return differ <= config.bins * (p + 5 * F.sqrt(F.lit(p * (1 - p)) / free))


def full_sets(keys: DataFrame, texts: DataFrame, config: MinHashConfig, repeated: bool = True) -> DataFrame:
    """keys: key. Their sets, stored: key, shingles, one row for each. texts: key and the texts of its first id, which may be
    other sets' too; repeated: whether a class may have several rows of its own among them."""
    needed = texts.join(keys.hint("rebalance"), "key", "left_semi")
    sets = needed.mapInArrow(lean(_sets(config)), "key long, shingles array<long>")
    return materialise(sets.dropDuplicates(["key"]) if repeated else sets, "minhash-sets")


def confirm(pairs: DataFrame, sets: DataFrame, config: MinHashConfig) -> DataFrame:
    """pairs: ka, kb and more. Those that reach the threshold on full sets."""
    both = pairs.join(sets.selectExpr("key AS ka", "shingles AS sa"), "ka").join(sets.selectExpr("key AS kb", "shingles AS sb"), "kb")
    common = F.size(F.array_intersect("sa", "sb")).cast("long")
    return both.where(common * 100 >= (F.size("sa") + F.size("sb") - common) * config.percent).drop("sa", "sb")


def rare_shingles(sets: DataFrame, config: MinHashConfig) -> DataFrame:
    """key, s, at, n: each set's rarest shingles with their places, as many as a pair at the threshold must share one of.

    Order every set by how few of the sets hold a shingle. Two sets that reach the threshold share a shingle among the first
    ``n - ceil(n * percent / 100) + 1`` of both; shingles that no other set holds keep their places but need no row."""
    tokens = sets.select("key", F.size("shingles").cast("long").alias("n"), F.explode("shingles").alias("s"))
    held = tokens.groupBy("s").agg(F.count("*").alias("held"))
    joined = tokens.join(held.withColumnRenamed("s", "_s").hint("rebalance"), F.col("s") == F.col("_s"))
    at = F.row_number().over(Window.partitionBy("key").orderBy("held", "s")).cast("long") - 1
    return joined.withColumn("at", at).where((F.col("at") * 100 <= F.col("n") * (100 - config.percent)) & (F.col("held") > 1)).select("key", "s", "at", "n")


def _two_sides(rows: DataFrame) -> tuple[DataFrame, DataFrame]:
    return tuple(rows.toDF(*[f"{c}_{side}" for c in rows.columns]) for side in "ab")


def components(docs: DataFrame, config: MinHashConfig) -> DataFrame:
    """docs: doc_id, text. Returns doc_id, n_shingles, component_id, kept and class_id (the least doc_id with the same set), by row."""
    docs = docs.select("doc_id", "text")
    described = materialise(docs.mapInArrow(lean(_describe(config)), "doc_id long, n long, key long, bands array<long>, sketch array<long>"), "minhash-docs")
    with_set = described.where("n > 0 AND doc_id IS NOT NULL")
    least = materialise(with_set.groupBy("key").agg(F.min("doc_id").alias("rep")), "minhash-least")
    # One row of each class stands for it; where rows repeat an id and a text, any of them: they are equal.
    stand = with_set.join(least.withColumnRenamed("key", "_key"), (F.col("key") == F.col("_key")) & (F.col("doc_id") == F.col("rep")))
    each = stand.groupBy("key").agg(*[F.first(c).alias(c) for c in ("rep", "n", "sketch", "bands")], F.count("*").alias("rows"))
    classes = materialise(each, "minhash-classes")
    repeated = not classes.where("rows > 1").isEmpty()

    buckets = classes.select("key", "rep", F.posexplode("bands").alias("band", "hash"))
    centres = buckets.groupBy("band", "hash").agg(F.min(F.struct("rep", "key")).alias("c"), F.count("*").alias("members")).where("members > 1")
    shared = materialise(
        buckets.join(centres.selectExpr("band AS _b", "hash AS _h", "c").hint("rebalance"), (F.col("band") == F.col("_b")) & (F.col("hash") == F.col("_h"))).select("band", "hash", "key", "rep", "c"),
        "minhash-buckets",
    )
    small = classes.select("key", "n", "sketch")
    first = shared.where("key <> c.key").groupBy("key", "rep").agg(F.min("c").alias("c")).selectExpr("key AS kb", "rep AS b", "c.key AS ka", "c.rep AS a")
    first = first.join(small.selectExpr("key AS ka", "n AS na", "sketch AS za"), "ka").join(small.selectExpr("key AS kb", "n AS nb", "sketch AS zb"), "kb")
    tried = materialise(first.where(_size_fits(config.percent, "na", "nb") & _sketch_fits(config, "za", "zb", "na", "nb")).select("ka", "kb", "a", "b"), "minhash-stars")

    # The texts of each class's first id, for full sets, which drop those that are not the class's.
    keyed = classes.selectExpr("rep AS _rep", "key").hint("rebalance")
    texts = docs.where("doc_id IS NOT NULL").join(keyed, F.col("doc_id") == F.col("_rep")).select("key", "text")
    ends = tried.selectExpr("ka AS key").unionAll(tried.selectExpr("kb AS key")).distinct()
    links = materialise(confirm(tried, full_sets(ends, texts, config, repeated), config).select("a", "b"), "minhash-links")
    found = connected_components(links)

    member = shared.join(found.hint("rebalance"), F.col("rep") == F.col("node"), "left").select("band", "hash", "key", "rep", F.coalesce("component", "rep").alias("comp"))
    member = materialise(member, "minhash-members")
    mixed = member.groupBy("band", "hash").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi")).where("lo < hi").selectExpr("band AS _b", "hash AS _h")
    open_ = member.join(mixed.hint("rebalance"), (F.col("band") == F.col("_b")) & (F.col("hash") == F.col("_h")), "left_semi")
    open_ = materialise(open_.join(small.withColumnRenamed("key", "_key"), F.col("key") == F.col("_key")).select("band", "hash", "key", "rep", "comp", "n", "sketch"), "minhash-open")
    # Only pairs of one bucket across components, and only those that sizes and sketches leave open: the classes with any
    # such partner, and then pairs of these that share a rare shingle early enough.
    across = (F.col("comp_a") != F.col("comp_b")) & _size_fits(config.percent, "n_a", "n_b") & _sketch_fits(config, "sketch_a", "sketch_b", "n_a", "n_b")
    left, right = _two_sides(open_)
    hopeful = left.join(right, (F.col("band_a") == F.col("band_b")) & (F.col("hash_a") == F.col("hash_b")) & across, "left_semi")
    hopeful = materialise(hopeful.selectExpr("key_a AS key", "rep_a AS rep", "comp_a AS comp").distinct(), "minhash-hopeful")
    sets = full_sets(hopeful.select("key"), texts, config, repeated)
    rare = materialise(rare_shingles(sets, config).join(hopeful, "key"), "minhash-rare")
    left, right = _two_sides(rare)
    # At the first shingle that two sets share in this order, what follows bounds their intersection.
    most = F.least(F.col("n_a") - F.col("at_a"), F.col("n_b") - F.col("at_b"))
    enough = most * (100 + config.percent) >= (F.col("n_a") + F.col("n_b")) * config.percent
    pairs = left.join(right, (F.col("s_a") == F.col("s_b")) & (F.col("comp_a") < F.col("comp_b")) & _size_fits(config.percent, "n_a", "n_b") & enough)
    pairs = pairs.selectExpr("key_a AS ka", "key_b AS kb", "rep_a AS a", "rep_b AS b").distinct()
    seen = tried.selectExpr("ka", "kb").unionAll(tried.selectExpr("kb AS ka", "ka AS kb"))
    rest = materialise(pairs.join(seen, ["ka", "kb"], "left_anti"), "minhash-rest")
    if not rest.isEmpty():
        more = materialise(confirm(rest, sets, config).select("a", "b"), "minhash-links")
        if not more.isEmpty():
            found = connected_components(links.unionAll(more))

    by_class = materialise(
        classes.select("key", "rep").join(found, F.col("rep") == F.col("node"), "left").select("key", "rep", F.coalesce("component", "rep").alias("component")), "minhash-result"
    )
    lone = F.col("doc_id").isNull() | (F.col("n") == 0)
    out = described.select("doc_id", "n", F.when(~lone, F.col("key")).alias("key")).join(by_class, "key", "left")
    component = F.when(lone, F.col("doc_id")).otherwise(F.col("component"))
    return out.select(
        "doc_id", F.col("n").alias("n_shingles"), component.alias("component_id"), (lone | (F.col("doc_id") == component)).alias("kept"), F.coalesce("rep", "doc_id").alias("class_id")
    )


def drop_near_duplicates(docs: DataFrame, config: MinHashConfig = MinHashConfig()) -> DataFrame:
    """The rows of ``docs`` that are kept: one document of each component (its least doc_id; one row of it, if it repeats), and rows
    without an id."""
    own = docs.columns
    plain = docs.toDF(*[f"c{i}" for i in range(len(own))])
    at = own.index("doc_id")
    kept = materialise(components(docs, config).where("kept AND doc_id IS NOT NULL").select("doc_id").distinct(), "minhash-kept")
    known = plain.join(kept, F.col(f"c{at}") == F.col("doc_id"), "left_semi")
    repeated = plain.where(F.col(f"c{at}").isNotNull()).groupBy(f"c{at}").agg(F.count("*").alias("rows")).where("rows > 1")
    if not repeated.isEmpty():
        known = known.dropDuplicates([f"c{at}"])
    return known.unionAll(plain.where(F.col(f"c{at}").isNull())).toDF(*own)


def op1_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents", ["doc_id", "text"])
    return components(docs, MinHashConfig(shingle=3, percent=85))

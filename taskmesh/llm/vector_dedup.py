"""Near duplicates of embeddings by random-hyperplane signs.

Each table draws hyperplanes from a seed; the signs of a vector's products with them are its key in that table. A pair at
the threshold agrees in one sign with probability 1 - angle / pi, in a table's key with that to the number of bits, and is
missed by all tables with probability ``miss`` at most: the number of tables follows from the number of bits, which follows
from the number of vectors, so that buckets of unrelated vectors stay of one size at every scale.

Ids travel to buckets with a sketch, the first ``SKETCH`` of their signs; vectors follow only into buckets where a sketch is
near enough to another (within seven standard deviations of what a pair at the threshold has).

Vectors that are equal form one class first. Within a bucket every pair of classes is compared in double precision, in
blocks: a bucket of more than ``block`` classes is split, and each pair of its parts is a task's run of its own. No pair
leaves the task. A linked pair is counted in the first table where its keys agree, which both rows' keys tell, so counts
need no list of pairs; connectivity needs one spanning forest of each block only. Components come from distributed label
exchange.

Defined cases: vectors that are null, zero, or hold null or non-finite components link with nothing and are kept; vectors
of another length than a partner's link with nothing of it; rows that repeat a vec_id with equal vectors count as vectors of
their own; a null vec_id links with nothing; an empty table gives an empty result.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from taskmesh.llm.graph import connected_components
from taskmesh.llm.vectors import bounds, by_length, key_runs, matrix, usable
from taskmesh.sources import load, materialise

BUCKET = 16
BLOCK = 512
MISS = 1e-6
#: Signs of a vector that travel ahead of it.
SKETCH = 256


def table_plan(vectors: int, cosine: float, miss: float = MISS, bucket: int = BUCKET) -> tuple[int, int]:
    """Bits of a key, and tables, for so many vectors."""
    bits = min(62, max(6, math.ceil(math.log2(max(2, vectors) / bucket))))
    agree = (1 - math.acos(cosine) / math.pi) ** bits
    return bits, max(1, math.ceil(math.log(miss) / math.log1p(-agree)))


def planes(dims: int, bits: int, table: int, seed: int) -> np.ndarray:
    return np.random.default_rng([seed, table, dims]).standard_normal((dims, bits))


def sign_keys(x: np.ndarray, bits: int, tables: int, seed: int) -> np.ndarray:
    """One key for each row and table."""
    weights = (1 << np.arange(bits, dtype=np.int64))[:, None]
    out = np.empty((len(x), tables), np.int64)
    for t in range(tables):
        out[:, t] = ((x @ planes(x.shape[1], bits, t, seed) > 0).astype(np.int64) @ weights)[:, 0]
    return out


def sketch(keys: np.ndarray, bits: int) -> np.ndarray:
    """The first SKETCH signs of all tables' keys, eight to a byte, in whole words of 64."""
    signs = (keys[:, :, None] >> np.arange(bits) & 1).astype(np.uint8).reshape(len(keys), -1)[:, :SKETCH]
    return np.packbits(np.pad(signs, ((0, 0), (0, -signs.shape[1] % 64))), axis=1)


def sketch_bound(cosine: float, signs: int) -> int:
    """Differing signs of a pair at the threshold: the mean and seven standard deviations, which it exceeds less often than 1e-8."""
    n, p = min(SKETCH, signs), math.acos(cosine) / math.pi
    return math.floor(n * p + 7 * math.sqrt(n * p * (1 - p)))


def _forest(a: np.ndarray, b: np.ndarray, size: int) -> list[tuple[int, int]]:
    """Edges of a spanning forest of the pairs, over 0 .. size - 1."""
    parent = list(range(size))

    def root(x: int) -> int:
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    kept = []
    for x, y in zip(a.tolist(), b.tolist(), strict=True):
        rx, ry = root(x), root(y)
        if rx != ry:
            parent[max(rx, ry)] = min(rx, ry)
            kept.append((x, y))
    return kept


def near_duplicates(vectors: DataFrame, cosine: float = 0.95, seed: int = 11, block: int = BLOCK, miss: float = MISS) -> DataFrame:
    """vectors: vec_id, embedding. Returns vec_id, n_links, component_id, kept by row."""
    good = materialise(usable(vectors).withColumn("key", F.xxhash64("embedding")), "vec-usable")
    # Equal vectors: the hash brings them together, equality of the vectors decides.
    classes = materialise(good.groupBy("key", "embedding").agg(F.min("vec_id").alias("rep"), F.count("*").alias("copies")), "vec-classes")
    bits, tables = table_plan(classes.count(), cosine, miss)

    def signs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for part in by_length(b):
                x = matrix(part)
                keys = sign_keys(x, bits, tables, seed) ^ (x.shape[1] << 40 if bits < 40 else 0)
                sketches = pa.array([s.tobytes() for s in sketch(keys, bits)], pa.binary())
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(list(keys), pa.list_(pa.int64())), sketches], [*part.schema.names, "keys", "sketch"])

    keyed = classes.mapInArrow(signs, "key long, embedding array<double>, rep long, copies long, keys array<long>, sketch binary")
    keyed = materialise(keyed.withColumn("cls", F.xxhash64("key", "rep")), "vec-keys")
    buckets = keyed.select("cls", F.posexplode("keys").alias("t", "k"))
    sizes = materialise(buckets.groupBy("t", "k").agg(F.count("*").alias("members")).where("members > 1"), "vec-buckets")
    width = max(1, int(vectors.sparkSession.conf.get("spark.sql.shuffle.partitions")))

    def dealt_out(members: DataFrame, *carried: str) -> DataFrame:
        """members: of buckets, with t, k and cls. Each goes to the pairs of parts of its bucket that its own part is in."""
        parts = F.ceil(F.col("members") / block).cast("int")
        rows = members.join(sizes.withColumnsRenamed({"t": "_t", "k": "_k"}), (F.col("t") == F.col("_t")) & (F.col("k") == F.col("_k")))
        rows = rows.withColumn("part", F.pmod(F.xxhash64("cls", F.lit(seed)), parts).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), parts - 1)))
        rows = rows.select("t", "k", F.least("part", "other").alias("p"), F.greatest("part", "other").alias("q"), "part", *carried)
        return rows.repartition(width, "t", "k", "p", "q").sortWithinPartitions("t", "k", "p", "q", "part", carried[0])

    # Ids and sketches travel first; vectors follow only to buckets where a sketch found them a partner.
    away = sketch_bound(cosine, bits * tables)

    def partners(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["t", "k", "p", "q"]
        for b in key_runs(batches, names):
            cls, part, p_of, q_of, t_of = (b.column(c).to_numpy(zero_copy_only=False) for c in ("cls", "part", "p", "q", "t"))
            words = np.frombuffer(b"".join(b.column("sketch").to_pylist()), np.uint64).reshape(b.num_rows, -1)
            some = np.zeros(b.num_rows, bool)
            for low, high in bounds(b, names):
                own = part[low:high] == p_of[low]
                rows_a = np.flatnonzero(own) + low
                same = p_of[low] == q_of[low]
                rows_b = rows_a if same else np.flatnonzero(~own) + low
                differ = sum(np.bitwise_count(words[rows_a, j][:, None] ^ words[rows_b, j][None, :]).astype(np.int16) for j in range(words.shape[1]))
                close = differ <= away
                if same:
                    np.fill_diagonal(close, False)
                some[rows_a] |= close.any(axis=1)
                some[rows_b] |= close.any(axis=0)
            yield pa.RecordBatch.from_arrays([pa.array(cls[some], pa.int64()), pa.array(t_of[some], pa.int32())], ["cls", "t"])

    sketched = dealt_out(keyed.select("cls", "sketch", F.posexplode("keys").alias("t", "k")), "cls", "sketch")
    paired = sketched.mapInArrow(partners, "cls long, t int").groupBy("cls").agg(F.collect_set("t").alias("in_tables"))
    paired = materialise(paired.withColumnRenamed("cls", "_cls"), "vec-partners")  # a set of tables for each vector
    rows = keyed.join(paired, F.col("cls") == F.col("_cls")).select("cls", "rep", "copies", "embedding", "keys", F.explode("in_tables").alias("t"))
    rows = rows.withColumn("k", F.element_at("keys", F.col("t") + 1))
    dealt = dealt_out(rows, "rep", "copies", "embedding", "keys")

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["t", "k", "p", "q"]
        for b in (part for whole in key_runs(batches, names) for part in by_length(whole)):
            rep, copies, part = (b.column(c).to_numpy(zero_copy_only=False) for c in ("rep", "copies", "part"))
            p_of, q_of, t_of = (b.column(c).to_numpy(zero_copy_only=False) for c in ("p", "q", "t"))
            x = matrix(b)
            x = x / np.sqrt((x * x).sum(axis=1))[:, None]
            keys = matrix_of_keys(b)
            counts, edges = np.zeros(len(rep), np.int64), []
            for low, high in bounds(b, names):
                if high - low < 2:
                    continue
                own = part[low:high] == p_of[low]
                rows_a = np.flatnonzero(own) + low
                rows_b = rows_a if p_of[low] == q_of[low] else np.flatnonzero(~own) + low
                close = x[rows_a] @ x[rows_b].T >= cosine - 1e-9
                if rows_b is rows_a:
                    close = np.triu(close, 1)
                i, j = np.nonzero(close)
                if not len(i):
                    continue
                i, j = rows_a[i], rows_b[j]
                sure = np.fromiter((float(np.dot(x[m], x[n])) >= cosine for m, n in zip(i.tolist(), j.tolist(), strict=True)), bool, len(i)) if len(i) < 64 else np.einsum("ij,ij->i", x[i], x[j]) >= cosine
                first = (keys[i] == keys[j]).argmax(axis=1) == t_of[low]
                i, j = i[sure & first], j[sure & first]
                np.add.at(counts, i, copies[j])
                np.add.at(counts, j, copies[i])
                edges += [(m + low, n + low) for m, n in _forest(i - low, j - low, high - low)]
            some = np.flatnonzero(counts)
            a = [rep[m] for m, _ in edges]
            c = [rep[n] for _, n in edges]
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array(np.concatenate([rep[some], np.array(a, np.int64)]), pa.int64()),
                    pa.array([*counts[some].tolist(), *[None] * len(a)], pa.int64()),
                    pa.array([*[None] * len(some), *c], pa.int64()),
                ],
                ["rep", "links", "to"],
            )

    found = materialise(dealt.mapInArrow(compare, "rep long, links long, to long"), "vec-links")
    joined = connected_components(found.where("to IS NOT NULL").selectExpr("rep AS a", "to AS b"))
    links = found.where("links IS NOT NULL").groupBy("rep").agg(F.sum("links").alias("links"))
    by_class = classes.join(links.withColumnRenamed("rep", "_r"), F.col("rep") == F.col("_r"), "left").join(joined, F.col("rep") == F.col("node"), "left")
    by_class = materialise(
        by_class.select("key", "embedding", (F.col("copies") - 1 + F.coalesce("links", F.lit(0))).alias("n_links"), F.coalesce("component", "rep").alias("component_id")), "vec-result"
    )
    linked = good.join(by_class, ["key", "embedding"]).select("vec_id", "n_links", "component_id")
    good_ids = good.select("vec_id").distinct().withColumnRenamed("vec_id", "_v")
    rest = vectors.select("vec_id").join(good_ids, F.col("vec_id") == F.col("_v"), "left_anti")
    rest = rest.select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    return linked.unionAll(rest).withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))


def matrix_of_keys(batch: pa.RecordBatch) -> np.ndarray:
    column = batch.column("keys")
    return column.flatten().to_numpy(zero_copy_only=False).reshape(len(column), -1)


def op7_vector_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(load(spark, sf_dir, "embeddings", ["vec_id", "embedding"]))

"""Nearest neighbours by inner product, with an inverted multi-index.

Each vector is cut into two halves, and each half is quantised with centroids of its own, trained on a bounded sample
(``sample`` vectors by hash order). A pair of centroids is a cell. For a query, the product with a cell's pair is the sum of
two numbers, one of each half; a heap walks the pairs from the greatest sum down, as if both lists were sorted, until the
cells passed hold the wanted number of vectors. The vectors in these cells are ranked again by exact inner products.

The last sum passed is all that has to travel: a cell was passed if its sum is not below it. A walk over a large share of
the cells is dear, so there the same sum is selected instead (``last_sum``). Vectors are dealt in blocks of neighbouring
cells, and blocks in groups; a query goes once to each group where it passed a cell, is compared there with tiles of bounded
size, and its best ``k`` of each group meet in two rounds of merging, so no task holds all queries of a group or all
candidates of a query. Scores of what is returned are summed in one order, so copies of a vector have the same.

How many vectors to pass: ``visit`` of all, and ``least`` at least. Nearest neighbours of vectors without structure are hard
to find (64 independent dimensions: the 20 nearest among 51,282 have a cosine of 0.35 or so), and recall, measured against
brute force, needs half of all there; vectors with structure need far less. The share is a parameter.

Defined cases: vectors that are null, zero, or hold null or non-finite components take no part, nor do those of another
length than most; ties go to the smaller vec_id; a row is no candidate of queries with its vec_id; rows that repeat a vec_id
are candidates one by one, and ask once, with the least of their vectors; fewer candidates than ``k`` give fewer rows; an empty table gives an empty result.
"""

from __future__ import annotations

import heapq
import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from taskmesh.llm.vectors import matrix, usable
from taskmesh.sources import load, materialise

BLOCK = 512
#: Blocks that a query visits together: it travels, and brings its best, once for all of them.
GROUP = 8
#: Queries compared at a time, and pairs of vectors held at a time while their products are summed.
TILE, PAIRS = 128, 1 << 15
#: A walk takes about so many times as long for a cell as a selection.
DEAR = 64
MOST_CENTROIDS = 1024


@dataclass(frozen=True)
class MultiIndex:
    """first, second: centroids of the halves; counts: vectors in each cell; first_block, parts: where the vectors of a
    first centroid are: in ``parts`` blocks from ``first_block`` on."""

    first: np.ndarray
    second: np.ndarray
    counts: np.ndarray
    first_block: np.ndarray
    parts: np.ndarray

    @property
    def half(self) -> int:
        return self.first.shape[1]


def kmeans(x: np.ndarray, k: int, seed: int, rounds: int = 12) -> np.ndarray:
    """Plain k-means; a centroid that loses all its points takes the one that is worst off."""
    rng = np.random.default_rng(seed)
    centres = x[rng.choice(len(x), min(k, len(x)), replace=False)].copy()
    for _ in range(rounds):
        d = (centres * centres).sum(axis=1) - 2 * (x @ centres.T)
        own = d.argmin(axis=1)
        total = np.zeros_like(centres)
        np.add.at(total, own, x)
        n = np.bincount(own, minlength=len(centres))
        worst = np.argsort(-(d[np.arange(len(x)), own] + (x * x).sum(axis=1)))
        for lost, w in zip(np.flatnonzero(n == 0), worst, strict=False):
            total[lost], n[lost] = x[w], 1
        centres = total / n[:, None]
    return centres


def nearest(x: np.ndarray, centres: np.ndarray) -> np.ndarray:
    return ((centres * centres).sum(axis=1) - 2 * (x @ centres.T)).argmin(axis=1)


def walk(u: np.ndarray, v: np.ndarray, counts: np.ndarray, wanted: int) -> float:
    """Passes cells by falling u[i] + v[j] until they hold ``wanted`` vectors; returns the last sum passed."""
    by_u, by_v = np.argsort(-u), np.argsort(-v)
    us, vs = u[by_u].tolist(), v[by_v].tolist()
    held: list[list[int]] = []  # counts of the rows reached, in the order of columns
    reached = [0] * len(us)  # how far each row has been pushed
    heap = [(-(us[0] + vs[0]), 0, 0)]
    reached[0] = 1
    held.append(counts[by_u[0]][by_v].tolist())
    found, last = 0, math.inf
    while heap:
        s, i, j = heapq.heappop(heap)
        if held[i][j]:
            last = -s
            found += held[i][j]
            if found >= wanted:
                return last
        if j + 1 < len(vs) and reached[i] == j + 1:
            heapq.heappush(heap, (-(us[i] + vs[j + 1]), i, j + 1))
            reached[i] = j + 2
        if j == 0 and i + 1 < len(us):
            heapq.heappush(heap, (-(us[i + 1] + vs[0]), i + 1, 0))
            held.append(counts[by_u[i + 1]][by_v].tolist())
            reached[i + 1] = 1
    return -math.inf


def select(sums: np.ndarray, counts: np.ndarray, wanted: int, bins: int = 1024) -> float:
    """The last sum that ``walk`` passes, from the sums of all filled cells and their counts: by a histogram, then exactly in one bin of it."""
    top, low = float(sums.max()), float(sums.min())
    if int(counts.sum()) < wanted:
        return -math.inf
    scale = bins / (top - low) if top > low else 0.0
    own = ((top - sums) * (scale if math.isfinite(scale) else 0.0)).astype(np.int64)  # falling sums, rising bins
    held = np.cumsum(np.bincount(own, counts))
    at = int(np.searchsorted(held, wanted))
    inside = np.flatnonzero(own == at)
    inside = inside[np.argsort(-sums[inside])]
    before = held[at - 1] if at else 0
    return float(sums[inside[np.searchsorted(before + np.cumsum(counts[inside]), wanted)]])


def last_sum(u: np.ndarray, v: np.ndarray, counts: np.ndarray, cells: tuple[np.ndarray, np.ndarray, np.ndarray], wanted: int) -> float:
    """What ``walk`` returns, by the cheaper way. cells: i, j and count of each filled cell."""
    i, j, n = cells
    if wanted * DEAR < int(n.sum()):
        return walk(u, v, counts, wanted)
    return select(u[i] + v[j], n, wanted)


def deal_blocks(per_first: np.ndarray, block: int) -> tuple[np.ndarray, np.ndarray, int]:
    """First centroids in turn share a block while they fit; one with more vectors than a block gets several of its own."""
    first_block, parts = np.zeros(len(per_first), np.int64), np.ones(len(per_first), np.int64)
    at, held = 0, 0
    for i, n in enumerate(per_first.tolist()):
        if held and held + n > block:
            at, held = at + 1, 0
        first_block[i], parts[i] = at, max(1, -(-n // block))
        if parts[i] > 1:
            at, held = at + int(parts[i]), 0
        else:
            held += n
    return first_block, parts, at + 1


def build(vectors: DataFrame, sample: int = 20_000, seed: int = 5, block: int = BLOCK) -> tuple[MultiIndex, DataFrame]:
    """vectors: a stored table of vec_id, embedding, all of one length. Returns the index and the stored table with i, j and block."""
    n = vectors.count()
    rows = vectors.orderBy(F.xxhash64(F.lit(seed), "vec_id"), "vec_id").limit(sample).select("embedding").toArrow()
    x = matrix(rows.combine_chunks().to_batches(max_chunksize=max(1, rows.num_rows))[0])
    k = max(1, min(MOST_CENTROIDS, round(math.sqrt(n / 3)), len(x)))
    half = (x.shape[1] + 1) // 2
    first, second = kmeans(x[:, :half], k, seed), kmeans(x[:, half:], k, seed + 1)
    shared = vectors.sparkSession.sparkContext.broadcast((first, second))

    def assign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        a, b = shared.value
        for part in batches:
            own = matrix(part)
            i, j = nearest(own[:, : a.shape[1]], a), nearest(own[:, a.shape[1] :], b)
            yield pa.RecordBatch.from_arrays([*part.columns, pa.array(i, pa.int32()), pa.array(j, pa.int32())], [*part.schema.names, "i", "j"])

    assigned = materialise(vectors.select("vec_id", "embedding").mapInArrow(assign, "vec_id long, embedding array<double>, i int, j int"), "ann-assigned")
    counts = np.zeros((len(first), len(second)), np.int64)
    for r in assigned.groupBy("i", "j").count().collect():  # one row for each cell at most, MOST_CENTROIDS squared
        counts[r.i, r.j] = r["count"]
    first_block, parts, _ = deal_blocks(counts.sum(axis=1), block)
    return MultiIndex(first, second, counts, first_block, parts), assigned


def search(vectors: DataFrame, is_query: Column, k: int = 20, visit: float = 0.5, least: int = 2000, sample: int = 20_000, seed: int = 5, block: int = BLOCK) -> DataFrame:
    """vectors: vec_id, embedding. is_query: which rows are queries too. Returns query_id, rank, vec_id, score."""
    good = usable(vectors)
    lengths = good.groupBy(F.size("embedding").alias("n")).count().orderBy(F.desc("count"), "n").first()
    out_schema = "query_id long, rank int, vec_id long, score double"
    if lengths is None:
        return vectors.sparkSession.createDataFrame([], out_schema)
    good = materialise(good.where(F.size("embedding") == lengths.n), "ann-usable")
    spark = vectors.sparkSession
    index, assigned = build(good, sample, seed, block)
    shared = spark.sparkContext.broadcast(index)
    wanted = max(least, math.ceil(visit * int(index.counts.sum())))

    def route(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = shared.value
        filled = own.counts > 0
        i_of, j_of = np.nonzero(filled)
        cells = i_of, j_of, own.counts[i_of, j_of]
        rows_of, starts = np.unique(i_of, return_index=True)  # first centroids with vectors, and where their cells begin
        first_group = (own.first_block[rows_of] // GROUP).tolist()
        last_group = ((own.first_block[rows_of] + own.parts[rows_of] - 1) // GROUP).tolist()
        for b in batches:
            q = matrix(b)
            u, v = q[:, : own.half] @ own.first.T, q[:, own.half :] @ own.second.T
            at, groups, cuts = [], [], []
            for row in range(len(q)):
                cut = last_sum(u[row], v[row], own.counts, cells, wanted)
                best = np.maximum.reduceat(v[row][j_of], starts) + u[row][rows_of]
                found: set[int] = set()
                for i in np.flatnonzero(best >= cut - 1e-9).tolist():
                    found.update(range(first_group[i], last_group[i] + 1))
                at += [row] * len(found)
                groups += sorted(found)
                cuts += [cut] * len(found)
            for low in range(0, len(at), 4096):
                rows = pa.array(at[low : low + 4096])
                yield pa.RecordBatch.from_arrays(
                    [pa.array(groups[low : low + 4096], pa.int64()), pa.array(cuts[low : low + 4096], pa.float64()), b.column("vec_id").take(rows), b.column("embedding").take(rows)],
                    ["group", "cut", "vec_id", "embedding"],
                )

    width = int(spark.conf.get("spark.sql.shuffle.partitions"))
    # An id asks once. Walks are dear, so few queries are spread too.
    asking = assigned.where(is_query).groupBy("vec_id").agg(F.min("embedding").alias("embedding")).repartition(width, F.xxhash64("vec_id"))
    routed = asking.select("vec_id", "embedding").mapInArrow(route, "group long, cut double, vec_id long, embedding array<double>")
    home = spark.createDataFrame([(i, int(f), int(p)) for i, (f, p) in enumerate(zip(index.first_block, index.parts, strict=True))], "_i int, first_block long, parts long")
    entries = assigned.join(F.broadcast(home), F.col("i") == F.col("_i"))  # MOST_CENTROIDS rows at most
    own_block = F.col("first_block") + F.pmod(F.xxhash64("vec_id", F.lit(seed)), F.col("parts"))
    entries = entries.select(F.floor(own_block / GROUP).alias("group"), F.lit(0).alias("side"), "i", "j", F.lit(0.0).alias("cut"), "vec_id", "embedding")
    asked = routed.select("group", F.lit(1).alias("side"), F.lit(0).alias("i"), F.lit(0).alias("j"), "cut", "vec_id", "embedding")
    met = entries.unionAll(asked).repartition(width, "group").sortWithinPartitions("group", "side", "vec_id")

    def rank(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = shared.value
        now, parts, ready = None, [], None
        for b in batches:
            group_of, side = (b.column(c).to_numpy(zero_copy_only=False) for c in ("group", "side"))
            edges = [0, *(np.flatnonzero((group_of[1:] != group_of[:-1]) | (side[1:] != side[:-1])) + 1).tolist(), b.num_rows]
            for low, high in zip(edges[:-1], edges[1:], strict=True):
                if low == high:
                    continue
                if group_of[low] != now:
                    now, parts, ready = group_of[low], [], None
                piece = b.slice(low, high - low)
                if side[low] == 0:
                    parts.append(piece)
                    continue
                if ready is None and parts:
                    ready = tuple(np.concatenate([f(p) for p in parts]) for f in (matrix, *[lambda p, c=c: p.column(c).to_numpy(zero_copy_only=False) for c in ("vec_id", "i", "j")]))
                if ready is not None:
                    yield _best(piece, ready, own, k, int(now))

    pieces = met.mapInArrow(rank, "query_id long, lot int, best array<struct<away:double,vec_id:long>>")
    merged = F.slice(F.array_sort(F.flatten(F.collect_list("best"))), 1, k).alias("best")
    best = pieces.groupBy("query_id", "lot").agg(merged).groupBy("query_id").agg(merged)
    placed = best.select("query_id", F.posexplode("best").alias("at", "b"))
    return placed.select("query_id", (F.col("at") + 1).cast("int").alias("rank"), F.col("b.vec_id").alias("vec_id"), (-F.col("b.away")).alias("score"))


def _best(asked: pa.RecordBatch, ready: tuple, index: MultiIndex, k: int, group: int) -> pa.RecordBatch:
    """The best ``k`` of one group for each query: only vectors in cells that the query passed."""
    x, ids, i, j = ready
    asked_for = matrix(asked)
    query_ids = asked.column("vec_id").to_numpy(zero_copy_only=False)
    cut = asked.column("cut").to_numpy(zero_copy_only=False)
    longest = np.sqrt((x * x).sum(axis=1).max())
    row_of, scores, found = [], [], []
    for low in range(0, len(asked_for), TILE):
        q = asked_for[low : low + TILE]
        sums = (q[:, : index.half] @ index.first.T).take(i, axis=1)
        sums += (q[:, index.half :] @ index.second.T).take(j, axis=1)
        score = q @ x.T
        score[(sums < cut[low : low + TILE, None] - 1e-9) | (ids[None, :] == query_ids[low : low + TILE, None])] = -np.inf
        edge = np.partition(score, len(ids) - k, axis=1)[:, len(ids) - k] if k < len(ids) else np.full(len(q), -np.inf)
        edge -= 1e-12 * longest * np.sqrt((q * q).sum(axis=1))  # a product may round otherwise than the sum below
        row, at = np.nonzero((score >= edge[:, None]) & np.isfinite(score))
        exact = np.empty(len(row))
        for p in range(0, len(row), PAIRS):
            exact[p : p + PAIRS] = (q[row[p : p + PAIRS]] * x[at[p : p + PAIRS]]).sum(axis=1)
        order = np.lexsort((ids[at], -exact, row))
        row, at, exact = row[order], at[order], exact[order]
        kept = np.arange(len(row)) - np.searchsorted(row, row, "left") < k
        row_of.append(low + row[kept]), scores.append(exact[kept]), found.append(ids[at[kept]])
    ends = np.searchsorted(np.concatenate(row_of), np.arange(len(asked_for) + 1), "left")
    best = pa.StructArray.from_arrays([pa.array(-np.concatenate(scores), pa.float64()), pa.array(np.concatenate(found), pa.int64())], ["away", "vec_id"])
    return pa.RecordBatch.from_arrays(
        [pa.array(query_ids, pa.int64()), pa.array([group % 16] * len(query_ids), pa.int32()), pa.ListArray.from_arrays(pa.array(ends, pa.int32()), best)], ["query_id", "lot", "best"]
    )


def op3_multi_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    return search(load(spark, sf_dir, "embeddings", ["vec_id", "embedding"]), F.col("vec_id") % 20 == 0)

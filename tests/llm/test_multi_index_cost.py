"""What a query of the multi-index costs: large shares of cells are selected, not walked, and its best travel once a group."""

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from taskmesh.llm import multi_index


def cells_of(counts):
    i, j = np.nonzero(counts)
    return i, j, counts[i, j]


def test_selection_stops_where_the_walk_stops():
    rng = np.random.default_rng(8)
    for case in range(300):
        u, v, counts = rng.normal(size=9), rng.normal(size=6), rng.integers(0, 4, (9, 6))
        if case % 3 == 0:
            u, v = np.round(u, 1), np.round(v, 1)  # equal sums
        if case % 50 == 1:
            u, v = np.zeros(9), np.zeros(6)
        counts[0, 0] = 1
        wanted = int(rng.integers(1, counts.sum() + 3))
        i, j, n = cells_of(counts)
        assert multi_index.select(u[i] + v[j], n, wanted) == multi_index.walk(u, v, counts, wanted)


def test_large_shares_take_no_steps_of_the_heap(monkeypatch):
    rng = np.random.default_rng(9)
    u, v, counts = rng.normal(size=40), rng.normal(size=40), rng.integers(0, 4, (40, 40))
    want = {w: multi_index.walk(u, v, counts, w) for w in (5, int(counts.sum()) // 2)}
    steps = []
    monkeypatch.setattr(multi_index, "walk", lambda *a, own=multi_index.walk: steps.append(1) or own(*a))
    assert {w: multi_index.last_sum(u, v, counts, cells_of(counts), w) for w in want} == want and len(steps) == 1


def test_best_of_a_group_is_exact_with_ties_and_tiles():
    rng = np.random.default_rng(10)
    x = np.repeat(rng.normal(size=(30, 8)), 10, axis=0)  # ten copies of each
    ids = rng.permutation(300)
    q, query_ids = np.vstack([x[:200], rng.normal(size=(100, 8))]), np.concatenate([ids[:200], np.arange(1000, 1100)])
    index = multi_index.MultiIndex(np.zeros((1, 4)), np.zeros((1, 4)), np.array([[300]]), np.zeros(1, int), np.ones(1, int))
    asked = pa.RecordBatch.from_arrays([pa.array(query_ids), pa.array(np.full(300, -np.inf)), pa.array(q.tolist())], ["vec_id", "cut", "embedding"])
    zero = np.zeros(300, int)
    got = multi_index._best(asked, (x, ids, zero, zero), index, 25, 3).to_pylist()
    for row, r in enumerate(got):
        want = sorted((-float((q[row : row + 1] * x[m : m + 1]).sum(axis=1)[0]), int(ids[m])) for m in range(300) if ids[m] != query_ids[row])[:25]
        assert r["query_id"] == query_ids[row] and [(b["away"], b["vec_id"]) for b in r["best"]] == want


def test_a_query_brings_its_best_once_a_group(spark, monkeypatch):
    rng = np.random.default_rng(11)
    table = spark.createDataFrame([(i, [float(v) for v in row]) for i, row in enumerate(rng.normal(size=(2000, 8)))], "vec_id long, embedding array<double>")
    out = multi_index.search(table, F.col("vec_id") % 20 == 0, block=32)
    pieces = [r for r in out.collect()]
    assert len(pieces) == 100 * 20
    one = {(r.query_id, r["rank"]): r.vec_id for r in pieces}
    monkeypatch.setattr(multi_index, "GROUP", 1)
    assert one == {(r.query_id, r["rank"]): r.vec_id for r in multi_index.search(table, F.col("vec_id") % 20 == 0, block=32).collect()}

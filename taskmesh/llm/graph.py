"""Connected components of a stored edge table, by alternating large-star and small-star steps.

Both steps link neighbours to the least node they know; a fixed point is one star per component, its centre the least
node. Each step is a minimum by node, joined back to the edges, so a node with very many edges is pre-aggregated before
the shuffle and its side of the join is dealt out over tasks by the skew handling of adaptive execution: the minima are
rebalanced first, which leaves both sides of the join free to be split. No node's neighbours are ever held in one task.
Every round is written to the shared folder, so lost executors cost one round at most.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from taskmesh.sources import materialise


def _mark(edges: DataFrame) -> tuple[int, int]:
    n, mark = edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
    return n, int(mark or 0)


def _lowest(pairs: DataFrame, lowest: DataFrame) -> DataFrame:
    return pairs.join(lowest.hint("rebalance").withColumnRenamed("x", "_x"), F.col("x") == F.col("_x")).drop("_x")


def _large_star(edges: DataFrame) -> DataFrame:
    """Every larger neighbour of x is linked to the least node among x and its neighbours."""
    pairs = edges.selectExpr("u AS x", "v AS y").unionAll(edges.selectExpr("v AS x", "u AS y"))
    lowest = pairs.groupBy("x").agg(F.least(F.col("x"), F.min("y")).alias("m"))
    return _lowest(pairs.where("y > x"), lowest).where("y <> m").selectExpr("y AS u", "m AS v").distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    """x and its smaller neighbours are linked to the least of them."""
    pairs = edges.selectExpr("u AS x", "v AS y")
    lowest = pairs.groupBy("x").agg(F.min("y").alias("m"))
    moved = _lowest(pairs, lowest).where("y <> m").selectExpr("y AS u", "m AS v")
    return moved.unionAll(lowest.selectExpr("x AS u", "m AS v")).distinct()


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """edges: a, b (longs, any order, repeats and loops allowed). Returns node, component for every node of an edge that is
    no loop; component is the least node that can be reached. Stored."""
    a, b = F.col("a"), F.col("b")
    current = materialise(edges.where(a != b).select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).distinct(), "edges")
    mark = _mark(current)
    for _ in range(max_rounds):
        if mark[0] == 0:
            break
        current = materialise(_small_star(_large_star(current)), "edges")
        before, mark = mark, _mark(current)
        if before == mark:
            break
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    centres = current.selectExpr("v AS node", "v AS component").distinct()
    return materialise(current.selectExpr("u AS node", "v AS component").unionAll(centres), "components")

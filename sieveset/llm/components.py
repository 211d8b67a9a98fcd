"""Connected components of a graph given as edges, by alternating star contractions; redundant edges go first by spanning forests of parts."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import LONG, fields, materialise

MAX_ROUNDS = 60
#: Edges of a part, about; a task joins them to a spanning forest in memory.
PART_EDGES = 1 << 19


def _both(edges: DataFrame) -> DataFrame:
    return edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))


def _large_star(edges: DataFrame) -> DataFrame:
    """Every node links its larger neighbours to the least of itself and its neighbours."""
    all_ = _both(edges)
    least = all_.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
    return all_.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u != v").distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    """Every node links its smaller neighbours and itself to the least of them. ``edges`` run from larger to smaller."""
    least = edges.groupBy("u").agg(F.min("v").alias("m"))
    moved = edges.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u != v")
    return moved.unionByName(least.select("u", F.col("m").alias("v"))).distinct()


def merge(root: np.ndarray, a: np.ndarray, b: np.ndarray) -> None:
    """Joins the groups of rows a[k] and b[k]; ``root`` holds each row's least member, before and after."""
    while True:
        x, y = root[a], root[b]
        apart = x != y
        if not apart.any():
            return
        np.minimum.at(root, np.maximum(x, y)[apart], np.minimum(x, y)[apart])
        while (root[root] != root).any():
            root[:] = root[root]


def _stars(part: pa.Table) -> pa.Table:
    """Every node of some edges, linked to the least that it hangs together with."""
    ends = np.stack([part.column(c).to_numpy() for c in ("u", "v")])
    nodes, at = np.unique(ends, return_inverse=True)
    at, root = at.reshape(ends.shape), np.arange(len(nodes))
    merge(root, at[0], at[1])
    own = np.flatnonzero(root != np.arange(len(nodes)))
    return pa.table({"u": nodes[own], "v": nodes[root[own]]})


def forest_components(edges: DataFrame) -> DataFrame:
    """``components`` of edges of longs that link many nodes many times over.

    Edges are dealt to parts by their larger end, and each part keeps stars with the same components. Edges that go from nodes to
    a few small ones fall to about one a node that way. A single part is settled by its stars; what several parts leave goes through the rounds.
    """
    now = materialise(edges.where("u != v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "edges")
    n = now.count()
    while n:
        parts = -(-n // PART_EDGES)
        dealt = now.withColumn("part", F.pmod(F.xxhash64(F.lit(7), "u"), F.lit(parts)))
        now = materialise(dealt.groupBy("part").applyInArrow(_stars, fields(u=LONG, v=LONG)), "stars")
        if parts == 1:
            return _named(now)
        before, n = n, now.count()
        if 3 * n > 2 * before:
            break
    return components(now)


def components(edges: DataFrame) -> DataFrame:
    """(node, root) for every node of an edge; ``root`` is the least node of its component.

    ``edges`` has u and v of one sortable type. Each round ends with a written table; rounds are about the
    logarithm of the number of nodes in the largest component.
    """
    big, small = F.greatest("u", "v"), F.least("u", "v")
    now = materialise(edges.where("u != v").select(big.alias("u"), small.alias("v")).distinct(), "edges")
    mark = None
    for _ in range(MAX_ROUNDS):
        now = materialise(_small_star(_large_star(now)), "edges")
        # sums over all edges: when a round changes none of them, all are stars
        seen = tuple(now.agg(F.count("*"), F.sum(F.shiftright(F.xxhash64("u", "v"), 24)), F.sum(F.shiftright(F.xxhash64("v", "u"), 24))).first())
        if seen == mark:
            break
        mark = seen
    else:
        raise RuntimeError(f"components: not settled after {MAX_ROUNDS} rounds")
    return _named(now)


def _named(stars: DataFrame) -> DataFrame:
    return stars.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(stars.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())

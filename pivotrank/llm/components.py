"""Connected components of an edge table: few edges at once, many by alternating stars, in a few rounds of aggregation."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .session import cut

FEW = 1 << 18  # edges that the driver may hold, 4 MB


def _least(edges: DataFrame, ends: list[tuple[str, str]]) -> DataFrame:
    """(u, v) in the given directions, with the smallest of u and its v as m."""
    both = None
    for u, v in ends:
        one = edges.select(F.col(u).alias("u"), F.col(v).alias("v"))
        both = one if both is None else both.unionByName(one)
    least = both.groupBy("u").agg(F.min("v").alias("m"))
    return both.join(least, "u").withColumn("m", F.least("u", "m"))


def _starred(edges: DataFrame) -> bool:
    """Whether every edge's upper end has no other edge."""
    ends = edges.select(F.col("b").alias("u"), F.lit(1).alias("up"), F.lit(0).alias("down")).unionByName(edges.select(F.col("a").alias("u"), F.lit(0).alias("up"), F.lit(1).alias("down")))
    counts = ends.groupBy("u").agg(F.sum("up").alias("up"), F.sum("down").alias("down"))
    return counts.where("up > 1 or (up = 1 and down > 0)").isEmpty()


def _stars_here(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The stars of edges in memory: centres hang on the smallest centre met until none moves."""
    ids, ends = np.unique(np.concatenate((a, b)), return_inverse=True)
    u, v = ends[: len(a)], ends[len(a) :]
    centre = np.arange(len(ids))  # ids are in order, so the smallest number is the smallest id
    while (centre[u] != centre[v]).any():
        least = np.minimum(centre[u], centre[v])
        moved = centre.copy()
        np.minimum.at(moved, centre[u], least)
        np.minimum.at(moved, centre[v], least)
        while (moved[moved] != moved).any():
            moved = moved[moved]
        centre = moved
    leaf = np.flatnonzero(centre != np.arange(len(ids)))
    return ids[centre[leaf]], ids[leaf]


def stars(edges: DataFrame) -> DataFrame:
    """Edges (a, b) of longs, either way round, as stars: (a, b) with a the smallest of its component.

    Every node that has an edge to another comes once as b, other than the centres. Loops vanish.
    Up to FEW edges are joined on the driver. More take rounds that grow with the logarithm of the longest
    path; each is checkpointed.
    """
    held = cut(edges.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).where("a < b").distinct())
    if held.count() <= FEW:
        ends = held.toArrow()
        a, b = _stars_here(ends.column(0).to_numpy(), ends.column(1).to_numpy())
        return held.sparkSession.createDataFrame(pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())}))
    while not _starred(held):
        # every neighbour above a node moves to the smallest neighbour of the node
        large = _least(held, [("a", "b"), ("b", "a")]).where("v > u").select(F.col("m").alias("a"), F.col("v").alias("b")).where("a < b")
        # every node and its neighbours below move to the smallest of those
        below = _least(large, [("b", "a")])
        held = cut(below.select(F.col("m").alias("a"), F.explode(F.array("u", "v")).alias("b")).where("a < b").distinct())
    return held

"""Exact search, refinement of candidates, and the choice of the best candidates.

Queries are (qid, x); they are few, and every search takes them in one block that the driver may hold
(MOST_QUERIES); more queries go in several blocks. Results are (qid, id, dist, rnk), ties by id.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.distances import Distance, distance, rank_key, rank_keys
from .pivots import matrix

MOST_QUERIES = 100_000


def ranked(scored: DataFrame, k: int) -> DataFrame:
    """The k nearest of each query of (qid, id, dist)."""
    w = Window.partitionBy("qid").orderBy("_key", "id")
    return scored.withColumn("_key", rank_key(F.col("dist"))).withColumn("rnk", F.row_number().over(w)).where(F.col("rnk") <= k).select("qid", "id", "dist", "rnk")


BLOCK_PAIRS = 4_000_000  # distances that a task computes at once


class Kept:
    """The k least (key, id) of each query among the blocks met so far; memory does not grow with the blocks."""

    def __init__(self, queries: int, k: int):
        self.k, self.edge = k, np.full(queries, np.iinfo(np.int64).max)
        self.q, self.key, self.id = (np.empty(0, np.int64) for _ in range(3))
        self.value = np.empty(0)

    def add(self, first: int, keys: np.ndarray, ids: np.ndarray, values: np.ndarray | None = None) -> None:
        """keys: a row for each query from number ``first`` on, a column for each id; values go with them."""
        if not keys.size:
            return
        n = min(self.k, keys.shape[1]) - 1
        held = self.edge[first : first + len(keys), None]
        under = keys <= held
        if np.count_nonzero(under) <= 4 * self.k * len(keys):  # few enter, so they need no choice among themselves
            q, p = np.nonzero(under)
            self.merge(q + first, keys[q, p], ids[p], (keys if values is None else values)[q, p].astype(np.float64))
            return
        edge = np.minimum(np.partition(keys, n, 1)[:, n] if n + 1 == self.k else np.iinfo(np.int64).max, self.edge[first : first + len(keys)])
        q, p = np.nonzero(keys <= edge[:, None])  # all that tie with the last, as ids break ties
        self.merge(q + first, keys[q, p], ids[p], (keys if values is None else values)[q, p].astype(np.float64))

    def merge(self, *new: np.ndarray) -> None:
        """Rows (query number, key, id, value), few of each query: all that is kept is put in order again."""
        q, key, id, value = (np.concatenate(x) for x in zip((self.q, self.key, self.id, self.value), new, strict=True))
        order = np.lexsort((id, key, q))
        q, key, id, value = q[order], key[order], id[order], value[order]
        place = np.arange(len(q)) - np.searchsorted(q, q)
        last = q[place == self.k - 1]
        self.edge[last] = key[place == self.k - 1]
        held = place < self.k
        self.q, self.key, self.id, self.value = q[held], key[held], id[held], value[held]


def tiles(points: int, queries: int):
    """Ranges of queries whose distances to so many points fit in a block."""
    step = max(1, BLOCK_PAIRS // max(1, points))
    for a in range(0, queries, step):
        yield a, min(queries, a + step)


def query_block(queries: DataFrame, payload: str) -> tuple[np.ndarray, np.ndarray]:
    rows = queries.select("qid", "x").orderBy("qid").limit(MOST_QUERIES + 1).collect()
    if len(rows) > MOST_QUERIES:
        raise ValueError(f"more than {MOST_QUERIES} queries: search them in blocks")
    return np.array([r["qid"] for r in rows], np.int64), np.array([r["x"]["p"] if payload == "histogram" else r["x"] for r in rows], np.float64)


def exact_knn(points: DataFrame, queries: DataFrame, dist: str | Distance, k: int = 10, side: str = "left", within: float | None = None) -> DataFrame:
    """Sequential scan: the true k nearest (or, with ``within``, all at most so far away).

    Where the distance has a matrix form, a task compares blocks of points with tiles of queries and keeps,
    over all its blocks, the k best of each query: k rows a query and task are shuffled, however many points.
    """
    d = distance(dist)
    if d.matrix is None:
        scored = points.select("id", "x").crossJoin(F.broadcast(queries.select("qid", F.col("x").alias("q")))).select("qid", "id", d(F.col("x"), F.col("q"), side).alias("dist"))
        return ranked(scored, k) if within is None else scored.where(F.col("dist") <= within)
    qids, held = query_block(queries, d.payload)

    def scan(source):
        best = Kept(len(qids), k)
        for batch in source:
            if not len(batch) or not len(qids):
                continue
            ids, x = batch.column(0).to_numpy(), matrix(batch.column(1), d.payload)
            for a, b in tiles(len(ids), len(qids)):
                far = d.between(x, held[a:b], side).T
                if within is None:
                    best.add(a, rank_keys(far), ids, far)
                else:
                    q, p = np.nonzero(far <= within)
                    yield pa.RecordBatch.from_pydict({"qid": qids[a + q], "id": ids[p], "dist": far[q, p]})
        if within is None:
            yield pa.RecordBatch.from_pydict({"qid": qids[best.q], "id": best.id, "dist": best.value})

    near = points.select("id", "x").mapInArrow(scan, "qid long, id long, dist double")
    return ranked(near, k) if within is None else near


def exact_sparse_cosine(terms: DataFrame, query_terms: DataFrame, k: int = 10) -> DataFrame:
    """Exact search by cosine over postings: (id, term, w) and (qid, term, w) meet on the term.

    Points that share no term with a query are all at distance 1; those of the smallest ids fill up the
    queries that have fewer than k others.
    """
    norms = terms.groupBy("id").agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("n"))
    q = query_terms.select("qid", "term", F.col("w").alias("qw"))
    qn = query_terms.groupBy("qid").agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("qn"))
    dots = terms.join(F.broadcast(q), "term").groupBy("qid", "id").agg(F.sum(F.col("w") * F.col("qw")).alias("dot"))
    near = ranked(dots.join(norms, "id").join(F.broadcast(qn), "qid").select("qid", "id", (1 - F.col("dot") / (F.col("n") * F.col("qn"))).alias("dist")), k)
    held = near.groupBy("qid").agg(F.count("*").alias("n"))
    short = qn.select("qid").join(held, "qid", "left").where(F.coalesce("n", F.lit(0)) < k).select("qid")
    first = norms.select("id").orderBy("id").limit(2 * k)  # among these there are k that a short query lacks
    fill = first.crossJoin(F.broadcast(short)).join(near.select("qid", "id"), ["qid", "id"], "left_anti").select("qid", "id", F.lit(1.0).alias("dist"))
    return ranked(near.select("qid", "id", "dist").unionByName(fill), k)


def refine(candidates: DataFrame, points: DataFrame, queries: DataFrame, dist: str | Distance, k: int = 10, side: str = "left") -> DataFrame:
    """The k nearest among candidates (qid, id) by true distance. Payloads are fetched here, not before."""
    d = distance(dist)
    met = candidates.select("qid", "id").distinct().join(points.select("id", "x"), "id").join(F.broadcast(queries.select("qid", F.col("x").alias("q"))), "qid")
    return ranked(met.select("qid", "id", d(F.col("x"), F.col("q"), side).alias("dist")), k)


def gamma_of(gamma: int | float, n: int, k: int = 1) -> int:
    """A number of candidates, given as such or as a share of the points; k at least."""
    return max(k, math.ceil(gamma * n - 1e-9) if isinstance(gamma, float) else gamma)


def top_gamma(scores: DataFrame, gamma: int, how: str = "counting") -> DataFrame:
    """The ``gamma`` best rows of each query of (qid, id, score), integer scores, small ones best, ties by id.

    ``heap``: a ranked window. ``counting``: the scores are counted, which needs as many rows as there are
    different scores, and the count says up to which score all rows are taken; only rows of that last
    score are put in order.
    """
    if how == "heap":
        w = Window.partitionBy("qid").orderBy("score", "id")
        return scores.withColumn("_r", F.row_number().over(w)).where(F.col("_r") <= gamma).drop("_r")
    if how != "counting":
        raise ValueError("how is 'heap' or 'counting'")
    counts = scores.groupBy("qid", "score").agg(F.count("*").alias("n"))
    w = Window.partitionBy("qid").orderBy("score").rowsBetween(Window.unboundedPreceding, 0)
    edge = counts.withColumn("upto", F.sum("n").over(w)).where((F.col("upto") - F.col("n") < gamma))
    edge = edge.groupBy("qid").agg(F.max("score").alias("edge"), F.max(F.struct("score", (F.col("upto") - F.col("n")).alias("before")))["before"].alias("before"))
    kept = scores.join(F.broadcast(edge), "qid").where(F.col("score") <= F.col("edge"))
    at = kept.where(F.col("score") == F.col("edge"))
    order = Window.partitionBy("qid").orderBy("id")
    last = at.withColumn("_r", F.row_number().over(order)).where(F.col("_r") <= gamma - F.col("before")).select(*scores.columns)
    return kept.where(F.col("score") < F.col("edge")).select(*scores.columns).unionByName(last)

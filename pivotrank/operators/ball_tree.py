"""Ball trees: median splits around random pivots, pruned by the metric or by learned polynomials.

The tree is grown on a sample that the driver may hold (all points where they are few), by seeded
pivots and exact medians, and holds at most MOST_LEAVES leaves; then every point goes to its leaf in
one narrow pass. A search prunes leaves by the pivots on their paths: first the home leaf gives a
radius, then all leaves that it leaves open are read. For a metric with ``alpha = beta = 1`` and for any
distance with ``alpha = 0`` the answer is exact.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

from ..functions.distances import Distance, distance
from ..functions.hashing import order_key, uniform_of
from .graphs import cut
from .pivots import matrix
from .search import MOST_QUERIES, ranked

MOST_LEAVES, SAMPLE = 4096, 32_768
DEALT = 1 << 15  # points that a task sends down the tree at once
MOST_VISITS = 1_000_000  # rows of two longs that are broadcast at most


def payloads(values: list, payload: str) -> np.ndarray:
    """Payloads as rows of a matrix, or, without a matrix form, as an array of objects."""
    if payload == "signature":
        made = [(np.array([t["c"] for t in v], float).reshape(len(v), -1), np.array([t["w"] for t in v], float)) for v in values]
    elif payload == "text":
        made = list(values)
    else:
        return np.array([v["p"] if payload == "histogram" else v for v in values], np.float64)
    out = np.empty(len(made), object)
    out[:] = made
    return out


def block_of(column: pa.Array, payload: str) -> np.ndarray:
    return payloads(column.to_pylist(), payload) if payload in ("signature", "text") else matrix(column, payload)


@dataclass
class Node:
    pivot: np.ndarray | None = None
    radius: float = 0.0
    inner: int = -1
    outer: int = -1


@dataclass
class Router:
    """The tree's nodes and what sends a vector to its leaf; goes to the tasks."""

    dist: Distance
    side: str
    nodes: list[Node] = field(default_factory=list)

    def leaf_of(self, x: np.ndarray) -> np.ndarray:
        """The leaf of each row of a matrix."""
        out = np.zeros(len(x), np.int64)
        stack = [(0, np.arange(len(x)))]
        while stack:
            at, mine = stack.pop()
            node = self.nodes[at]
            if node.pivot is None or not len(mine):
                out[mine] = at
                continue
            inside = self.dist.between(x[mine], node.pivot, self.side)[:, 0] <= node.radius
            stack += [(node.inner, mine[inside]), (node.outer, mine[~inside])]
        return out


@dataclass
class BallTree:
    points: DataFrame
    dist: Distance
    side: str = "left"
    distances: int = 0
    dealt: DataFrame | None = None
    number: np.ndarray | None = None  # of a node's pivot among the pivots

    def __post_init__(self):
        self.router = Router(self.dist, self.side)

    @property
    def nodes(self) -> list[Node]:
        return self.router.nodes

    @classmethod
    def build(cls, points: DataFrame, dist: str | Distance, bucket: int = 50, seed: int = 11, side: str = "left", sample: int = SAMPLE) -> BallTree:
        """bucket: points that a leaf should hold, 2 at least."""
        if bucket < 2:
            raise ValueError("a bucket holds 2 points at least")
        d = distance(dist)
        n = points.count()
        rows = points.select("id", "x").orderBy(order_key(f"tree{seed}", "id"), "id").limit(sample).collect()
        x = payloads([r["x"] for r in rows], d.payload)
        ids = np.array([r["id"] for r in rows], np.int64)
        tree = cls(points, d, side)
        least = max(bucket * len(rows) / max(1, n), len(rows) / MOST_LEAVES, 2)
        tree._grow(x, ids, np.arange(len(rows)), least, seed)
        return tree

    def _grow(self, x, ids, mine, least, seed) -> int:
        at = len(self.nodes)
        self.nodes.append(Node())
        if len(mine) < least or len(mine) < 2:
            return at
        first = mine[min(range(len(mine)), key=lambda i: (uniform_of(f"tree{seed}:{at}:{ids[mine[i]]}"), ids[mine[i]]))]
        pivot = x[first : first + 1]
        far = self.dist.between(x[mine], pivot, self.side)[:, 0]
        self.distances += len(mine)
        radius = float(np.median(far))
        inside = far <= radius
        if inside.all():
            return at
        node = self.nodes[at]
        node.pivot, node.radius = pivot, radius
        node.inner = self._grow(x, ids, mine[inside], least, seed)
        node.outer = self._grow(x, ids, mine[~inside], least, seed)
        return at

    def assigned(self) -> DataFrame:
        """(id, x, leaf): one narrow pass, kept for all searches."""
        if self.dealt is not None:
            return self.dealt
        payload, router = self.dist.payload, self.router

        def deal(source):
            held, size = [], 0
            for batch in source:
                held.append(batch)
                size += len(batch)
                if size >= DEALT:  # a block meets every node once, however few of its points are there
                    yield close(held)
                    held, size = [], 0
            if size:
                yield close(held)

        def close(held):
            batch = pa.concat_batches(held)
            return pa.RecordBatch.from_arrays([*batch.columns, pa.array(router.leaf_of(block_of(batch.column(1), payload)))], names=["id", "x", "leaf"])

        rows = self.points.select("id", "x")
        self.dealt = cut(rows.mapInArrow(deal, StructType([*rows.schema.fields, StructField("leaf", LongType())])))
        return self.dealt

    def _to_pivots(self, queries: np.ndarray) -> np.ndarray:
        """Distances of queries (rows) to the pivots of all nodes that have one, in order of nodes."""
        pivots = [n.pivot for n in self.nodes if n.pivot is not None]
        if not pivots or not len(queries):
            return np.empty((len(queries), 0))
        held = np.concatenate(pivots)
        return self.dist.between(held, queries, self.side).T if self.dist.symmetric else self.dist.between(queries, held, self.side)

    def open_leaves(self, query: np.ndarray, radius: float, alpha: tuple[float, float] = (1.0, 1.0), beta: float = 1.0, known: np.ndarray | None = None) -> list[int]:
        """Leaves that the pruning rule leaves open for a radius. Equality never prunes. known: the query's row of _to_pivots."""
        known = self._to_pivots(query)[0] if known is None else known
        number = np.cumsum([n.pivot is not None for n in self.nodes]) - 1 if self.number is None else self.number
        self.number = number
        out, stack = [], [0]
        while stack:
            node = self.nodes[at := stack.pop()]
            if node.pivot is None:
                out.append(at)
                continue
            far = float(known[number[at]])
            gap = abs(node.radius - far) ** beta - 1e-9
            inside = far <= node.radius
            if not inside or gap * alpha[0] <= radius:
                stack.append(node.outer)
            if inside or gap * alpha[1] <= radius:
                stack.append(node.inner)
        return out

    def visits(self, queries: DataFrame, k: int, alpha=(1.0, 1.0), beta: float = 1.0) -> DataFrame:
        """(qid, leaf) of the second round: home leaves first give each query its radius."""
        rows = queries.select("qid", "x").orderBy("qid").limit(MOST_QUERIES + 1).collect()
        if len(rows) > MOST_QUERIES:
            raise ValueError(f"more than {MOST_QUERIES} queries: search them in blocks")
        qids, held = np.array([r["qid"] for r in rows], np.int64), payloads([r["x"] for r in rows], self.dist.payload)
        spark = self.points.sparkSession
        homes = spark.createDataFrame([(int(q), int(leaf)) for q, leaf in zip(qids, self.router.leaf_of(held), strict=True)], "qid long, leaf long")
        first = self._read(homes, queries, k).groupBy("qid").agg(F.max("dist").alias("r"), F.count("*").alias("n"))
        radii = {r["qid"]: r["r"] if r["n"] >= k else math.inf for r in first.collect()}  # one row for each query
        open_ = []
        for a in range(0, len(qids), 256):
            known = self._to_pivots(held[a : a + 256])
            open_ += [(int(q), leaf) for i, q in enumerate(qids[a : a + 256]) for leaf in self.open_leaves(held[a + i : a + i + 1], radii.get(int(q), math.inf), alpha, beta, known[i])]
        return spark.createDataFrame(open_, "qid long, leaf long")

    def _read(self, visits: DataFrame, queries: DataFrame, k: int) -> DataFrame:
        small = F.broadcast(visits) if visits.count() <= MOST_VISITS else visits
        met = self.assigned().join(small, "leaf").join(F.broadcast(queries.select("qid", F.col("x").alias("q"))), "qid")
        return ranked(met.select("qid", "id", self.dist(F.col("x"), F.col("q"), self.side).alias("dist")), k)

    def search(self, queries: DataFrame, k: int = 10, alpha=(1.0, 1.0), beta: float = 1.0) -> DataFrame:
        return self._read(self.visits(queries, k, alpha, beta), queries, k)

    def read_points(self, queries: DataFrame, k: int = 10, alpha=(1.0, 1.0), beta: float = 1.0) -> int:
        """Points of the leaves read, over all queries."""
        sizes = self.assigned().groupBy("leaf").agg(F.count("*").alias("n"))
        return self.visits(queries, k, alpha, beta).join(sizes, "leaf").agg(F.sum("n")).first()[0] or 0


class PermutationTree:
    """A ball tree over rank vectors under L2, whose order is that of rho; its answers are candidates."""

    def __init__(self, points: DataFrame, dist, m: int = 64, bucket: int = 50, seed: int = 7, side: str = "left"):
        from .pivots import see, select_pivots

        self.points, self.dist, self.side = points, distance(dist), side
        self.pivots = select_pivots(points, m, seed)
        self._ranks = lambda rows, key: see(rows.select(key, "x"), self.pivots, self.dist, side, None, ("rank",)).select(key, F.transform("rank", lambda r: r.cast("double")).alias("x"))
        self.tree = BallTree.build(self._ranks(points, "id"), "l2", bucket)

    def candidates(self, queries: DataFrame, gamma: int) -> DataFrame:
        found = self.tree.search(self._ranks(queries, "qid"), gamma)
        return found.select("qid", "id", F.round(F.col("dist") * F.col("dist")).cast("long").alias("score"))

    def search(self, queries: DataFrame, k: int = 10, gamma: int = 100) -> DataFrame:
        from .search import refine

        return refine(self.candidates(queries, gamma), self.points, queries, self.dist, k, self.side)


def tune_pruner(tree: BallTree, queries: DataFrame, truth: DataFrame, k: int = 10, target: float = 0.9, beta: float = 1.0, rounds: int = 3) -> tuple[float, float]:
    """(alpha_left, alpha_right) that reads the fewest points at the target recall, on a grid whose steps shrink."""
    from .measures import recall

    centre, step, best = np.array([1.0, 1.0]), 4.0, None
    for _ in range(rounds):
        for a in (1 / step, 1.0, step):
            for b in (1 / step, 1.0, step):
                alpha = (centre[0] * a, centre[1] * b)
                got = recall(tree.search(queries, k, alpha, beta), truth, k).first()["recall"]
                if got >= target:
                    cost = tree.read_points(queries, k, alpha, beta)
                    if best is None or cost < best[0]:
                        best = (cost, alpha)
        centre, step = np.array(best[1] if best else centre / step), math.sqrt(step)
    return tuple(best[1]) if best else (0.0, 0.0)

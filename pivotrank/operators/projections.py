"""Filters by random projections: as vectors, as hash buckets, and as voters that rank the points."""

from __future__ import annotations

import heapq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.distances import distance, rank_keys
from ..functions.hashing import gaussian_of, uniform_of
from .pivots import matrix, see, select_pivots
from .search import Kept, tiles, query_block, ranked, refine


def gaussian_matrix(rows: int, columns: int, seed: int = 17) -> np.ndarray:
    """Entries that are about normal, from md5."""
    return np.array([[gaussian_of(f"g{seed}:{i}:{j}") for j in range(columns)] for i in range(rows)])


def project(points: DataFrame, basis: np.ndarray, key: str = "id") -> DataFrame:
    """(key, y): vectors times the basis."""

    def run(source):
        for batch in source:
            if len(batch):
                y = matrix(batch.column(1), "vector") @ basis
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.ListArray.from_arrays(pa.array(np.arange(0, y.size + 1, y.shape[1]), pa.int32()), pa.array(y.ravel()))], names=[key, "y"])

    return points.select(key, "x").mapInArrow(run, f"{key} long, y array<double>")


class RandomProjection:
    """The gamma nearest in a projection are refined."""

    def __init__(self, points: DataFrame, dist, input_dim: int, dim: int = 16, seed: int = 17):
        self.points, self.dist = points, distance(dist)
        self.basis = gaussian_matrix(input_dim, dim, seed)

    def candidates(self, queries: DataFrame, gamma: int) -> DataFrame:
        from .search import exact_knn

        low = exact_knn(project(self.points, self.basis).withColumnRenamed("y", "x"), project(queries, self.basis, "qid").withColumnRenamed("y", "x"), "cosine" if self.dist.name == "cosine" else "l2", gamma)
        return low.select("qid", "id", F.col("rnk").cast("long").alias("score"))

    def search(self, queries: DataFrame, k: int = 10, gamma: int = 100) -> DataFrame:
        return refine(self.candidates(queries, gamma), self.points, queries, self.dist, k)


def project_terms(terms: DataFrame, dim: int = 16, seed: int = 17, key: str = "id") -> DataFrame:
    """(key, y) of sparse vectors (key, term, w): a term's signs come from md5 of the term and the axis."""
    sign = lambda j: F.when(F.substring(F.md5(F.concat_ws(":", F.lit(f"s{seed}"), F.lit(str(j)), "term").cast("binary")), 1, 1) < "8", 1.0).otherwise(-1.0)
    return terms.groupBy(key).agg(*[F.sum(F.col("w") * sign(j)).alias(f"y{j}") for j in range(dim)]).select(key, F.array(*[f"y{j}" for j in range(dim)]).alias("y"))


class MultiProbe:
    """Hash tables of quantised projections; a query also looks into the buckets next to its own.

    A table's key is ``hashes`` cells of width ``width``; keys fall into ``size`` buckets. Probes are the
    cells reached by steps over the nearest borders, in order of the squared gaps.
    """

    def __init__(self, points: DataFrame, input_dim: int, tables: int = 50, hashes: int = 8, width: float = 1.0, size: int | None = None, seed: int = 19):
        self.points, self.tables, self.hashes, self.width = points, tables, hashes, width
        self.size = size or points.count() + 1
        self.basis = gaussian_matrix(input_dim, tables * hashes, seed)
        self.shift = np.array([uniform_of(f"c{seed}:{i}") * width for i in range(tables * hashes)])
        self.mixers = np.array([int(uniform_of(f"m{seed}:{i}") * (1 << 31)) * 2 + 1 for i in range(hashes)], np.int64)

    def cells(self, x: np.ndarray) -> np.ndarray:
        """Places along each table's axes, in cells."""
        return ((x @ self.basis + self.shift) / self.width).reshape(len(x), self.tables, self.hashes)

    def bucket(self, cells: np.ndarray) -> np.ndarray:
        return (cells.astype(np.int64) * self.mixers).sum(-1) % self.size

    def buckets(self) -> DataFrame:
        """(tbl, bucket, id) of every point: narrow."""
        own = self

        def run(source):
            for batch in source:
                if len(batch):
                    b = own.bucket(np.floor(own.cells(matrix(batch.column(1), "vector"))))
                    n = b.shape[1]
                    yield pa.RecordBatch.from_pydict({"tbl": np.tile(np.arange(n, dtype=np.int32), len(b)), "bucket": b.ravel(), "id": np.repeat(batch.column(0).to_numpy(), n)})

        held = self.__dict__.pop("points")
        try:
            return held.select("id", "x").mapInArrow(run, "tbl int, bucket long, id long")
        finally:
            self.points = held

    def probes(self, x: np.ndarray, probes: int) -> np.ndarray:
        """Buckets that each query looks into: its own and ``probes`` more in each table."""
        place = self.cells(x)
        home = np.floor(place)
        out = np.empty((len(x), self.tables, probes + 1), np.int64)
        for i in range(len(x)):
            for t in range(self.tables):
                low = place[i, t] - home[i, t]
                steps = sorted([(g * g, j, -1) for j, g in enumerate(low)] + [((1 - g) * (1 - g), j, 1) for j, g in enumerate(low)])
                out[i, t, 0] = self.bucket(home[i, t])
                for n, chosen in enumerate(_step_sets(steps, probes)):
                    cell = home[i, t].copy()
                    for s in chosen:
                        cell[steps[s][1]] += steps[s][2]
                    out[i, t, n + 1] = self.bucket(cell)
        return out

    def candidates(self, queries: DataFrame, probes: int = 10) -> DataFrame:
        qids, held = query_block(queries, "vector")
        b = self.probes(held, probes)
        rows = sorted({(int(q), t, int(v)) for q, per in zip(qids, b, strict=True) for t, vs in enumerate(per) for v in vs})
        asked = self.points.sparkSession.createDataFrame(rows, "qid long, tbl int, bucket long")
        return self.buckets().join(F.broadcast(asked), ["tbl", "bucket"]).select("qid", "id").distinct()

    def search(self, queries: DataFrame, k: int = 10, probes: int = 10) -> DataFrame:
        return refine(self.candidates(queries, probes), self.points, queries, "l2", k)

    @staticmethod
    def auto(sample: np.ndarray, recall: float = 0.9, k: int = 10, tables: int = 50, seed: int = 19, n: int | None = None) -> tuple[float, int]:
        """(width, hashes) that promise the recall at the fewest candidates, by collision chances on a sample."""
        from math import erf, exp, pi, sqrt

        def chance(c: float) -> float:  # two points c widths apart share a cell
            if c == 0:
                return 1.0
            r = 1 / c
            return erf(r / sqrt(2)) - 2 / (sqrt(2 * pi) * r) * (1 - exp(-r * r / 2))

        far = np.sqrt(((sample[:, None] - sample[None]) ** 2).sum(-1))
        np.fill_diagonal(far, np.inf)
        share = max(1, round(k * len(sample) / (n or len(sample))))
        near, typical = np.sort(far, 1)[:, share - 1], far[np.isfinite(far)]
        best = None
        for width in np.quantile(typical, 0.5) * np.array([0.25, 0.5, 1, 2, 4]):
            for hashes in (2, 4, 6, 8, 12, 16):
                hit = np.mean([1 - (1 - chance(d / width) ** hashes) ** tables for d in near])
                cost = np.mean([1 - (1 - chance(d / width) ** hashes) ** tables for d in np.random.default_rng(seed).choice(typical, 200)])
                if hit >= recall and (best is None or cost < best[0]):
                    best = (cost, float(width), hashes)
        return (best[1], best[2]) if best else (float(4 * np.quantile(typical, 0.5)), 2)


def _step_sets(steps: list, count: int):
    """Sets of steps, by rising sum of squared gaps, that move no axis twice."""
    heap, n = [(steps[0][0], (0,))] if steps else [], 0
    while heap and n < count:
        total, chosen = heapq.heappop(heap)
        last = chosen[-1]
        if last + 1 < len(steps):
            heapq.heappush(heap, (total - steps[last][0] + steps[last + 1][0], (*chosen[:-1], last + 1)))
            heapq.heappush(heap, (total + steps[last + 1][0], (*chosen, last + 1)))
        if len({steps[s][1] for s in chosen}) == len(chosen):
            n += 1
            yield chosen


class MedianRank:
    """Voters on lines rank the points by closeness to the query; a point's score is an order statistic of its ranks.

    Voters are random projections (``projection``) or distances to pivots (``pivot``). Each lists its
    ``depth`` closest points; a point scores as soon as more than ``minfreq`` of the voters list it, with
    the rank that completes that number. Each task keeps its own ``depth`` best of each list, so what is
    shuffled does not grow with the points.
    """

    def __init__(self, points: DataFrame, dist, voters: int = 5, voter: str = "projection", input_dim: int = 64, seed: int = 23):
        self.points, self.dist, self.voters = points, distance(dist), voters
        self.basis = gaussian_matrix(input_dim, voters, seed) if voter == "projection" else None
        self.pivots = select_pivots(points, voters, seed) if voter == "pivot" else None

    def lines(self, rows: DataFrame, key: str) -> DataFrame:
        """(key, y): a point's place on every voter's line."""
        if self.basis is not None:
            return project(rows, self.basis, key)
        return see(rows.select(key, "x"), self.pivots, self.dist, want=("pd",)).select(key, F.col("pd").alias("y"))

    def ranks(self, queries: DataFrame, depth: int) -> DataFrame:
        """(qid, voter, id, rank) of each list."""
        held = {r["qid"]: r["y"] for r in self.lines(queries, "qid").collect()}  # a row for each query
        qids, own, voters = np.array(sorted(held), np.int64), np.array([held[q] for q in sorted(held)]), self.voters

        def run(source):
            best = [Kept(len(qids), depth) for _ in range(voters)]
            for batch in source:
                if not len(batch) or not len(qids):
                    continue
                ids, y = batch.column(0).to_numpy(), matrix(batch.column(1), "vector")
                for v in range(voters):
                    for a, b in tiles(len(ids), len(qids)):
                        best[v].add(a, rank_keys(np.abs(y[None, :, v] - own[a:b, v, None])), ids)
            for v, x in enumerate(best):
                yield pa.RecordBatch.from_pydict({"qid": qids[x.q], "voter": np.full(len(x.q), v, np.int32), "id": x.id, "gap": x.key})

        near = self.lines(self.points, "id").mapInArrow(run, "qid long, voter int, id long, gap long")
        w = Window.partitionBy("qid", "voter").orderBy("gap", "id")
        return near.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= depth).select("qid", "voter", "id", "rank")

    def candidates(self, queries: DataFrame, depth: int = 100, minfreq: float = 0.5) -> DataFrame:
        needed = int(minfreq * self.voters) + 1
        lists = self.ranks(queries, depth).groupBy("qid", "id").agg(F.sort_array(F.collect_list("rank")).alias("r"))  # as many ranks as voters
        return lists.where(F.size("r") >= needed).select("qid", "id", F.get("r", F.lit(needed - 1)).cast("long").alias("score"))

    def search(self, queries: DataFrame, k: int = 10, depth: int = 100, minfreq: float = 0.5, gamma: int | None = None) -> DataFrame:
        """The k best scores; with ``gamma`` that many are refined by the true distance."""
        scored = self.candidates(queries, depth, minfreq)
        if gamma is None:
            return ranked(scored.select("qid", "id", F.col("score").cast("double").alias("dist")), k)
        from .search import top_gamma

        return refine(top_gamma(scored, gamma), self.points, queries, self.dist, k)


def spark_lsh(points: DataFrame, queries: DataFrame, k: int = 10, width: float = 1.0, tables: int = 10, radius: float = 2.0, seed: int = 19) -> DataFrame:
    """The library's own hashing, as a control: (qid, id, dist, rnk)."""
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector

    model = BucketedRandomProjectionLSH(inputCol="v", outputCol="h", bucketLength=width, numHashTables=tables, seed=seed).fit(points.select(array_to_vector("x").alias("v")).limit(1))
    a, b = points.select("id", array_to_vector("x").alias("v")), queries.select("qid", array_to_vector("x").alias("v"))
    met = model.approxSimilarityJoin(a, b, radius, "dist").select(F.col("datasetB.qid").alias("qid"), F.col("datasetA.id").alias("id"), "dist")
    return ranked(met, k)


def tune_probes(points: DataFrame, queries: DataFrame, truth: DataFrame, input_dim: int, target: float = 0.9, grid=((10, 0), (10, 10), (25, 10), (50, 10), (50, 50)), width: float = 2.0, hashes: int = 4) -> tuple[int, int, float]:
    """The first (tables, probes) of a grid, from cheap to dear, that reaches the recall; and the recall."""
    from .measures import recall

    found = 0.0
    for tables, probes in grid:
        found = recall(MultiProbe(points, input_dim, tables, hashes, width).search(queries, 10, probes), truth).first()["recall"]
        if found >= target:
            break
    return tables, probes, found

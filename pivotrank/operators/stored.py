"""A shared-pivot index that is built once, stored, and searched often.

Points do not move: a task takes its points as they come, cuts them into chunks, and writes for each chunk
the ids, the payloads and, pivot by pivot, which of its points have the pivot among their ``mi`` closest.
A search reads a chunk's lists of the query's pivots, counts how often each point stands in them, computes
the true distance to those that share at least ``t`` and keeps its k best, all within the task. So k rows
a query and task are shuffled, and the pivots and queries are all that goes to the tasks.

Chunks are rows of Parquet files; the pivots and a manifest lie beside them. Payloads are stored for distances
with a matrix form; for others a search refines candidates by joining the points.
"""

from __future__ import annotations

import json

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.distances import distance, rank_keys
from .pivots import Pivots, matrix, see, select_pivots
from .search import MOST_QUERIES, Kept, query_block, ranked, refine

CHUNK = 1 << 16
_SCHEMA = "points int, dim int, ids binary, payload binary, starts binary, places binary"


def _packed(ids: np.ndarray, x: np.ndarray | None, near: np.ndarray, m: int) -> pa.RecordBatch:
    """A chunk's row: places are numbers of points, in order of pivots; starts say where each pivot's begin."""
    n, mi = near.shape
    order = np.argsort(near.ravel(), kind="stable")
    starts = np.searchsorted(near.ravel()[order], np.arange(m + 1)).astype(np.int32)
    places = (order // mi).astype(np.int32 if n > 65_535 else np.uint16)
    row = {"points": [n], "dim": [0 if x is None else x.shape[1]], "ids": [ids.tobytes()], "payload": [b"" if x is None else x.tobytes()], "starts": [starts.tobytes()], "places": [places.tobytes()]}
    kinds = {"points": pa.int32(), "dim": pa.int32()}
    return pa.RecordBatch.from_arrays([pa.array(v, kinds.get(c, pa.binary())) for c, v in row.items()], names=list(row))


def build(points: DataFrame, dist: str, m: int, path: str, mi: int = 32, seed: int = 7, side: str = "left", chunk: int = CHUNK) -> StoredSharedPivots:
    """Writes the index of points (id, x) to a folder and opens it."""
    d, spark = distance(dist), points.sparkSession
    if not 1 <= mi <= m:
        raise ValueError("mi must be from 1 to the number of pivots")
    pivots = select_pivots(points, m, seed)
    stored = d.matrix is not None
    seen = see(points.select("id", "x"), pivots, d, side, mi, ("ord",)).select("id", "ord", *(["x"] if stored else []))

    def cut(source):
        held, size = [], 0
        for batch in source:
            if not len(batch):
                continue
            ids = batch.column(0).to_numpy()
            near = batch.column(1).flatten().to_numpy().reshape(len(ids), -1).astype(np.int16) - 1
            held.append((ids, near, matrix(batch.column(2), d.payload) if stored else None))
            size += len(ids)
            if size >= chunk:
                yield close(held)
                held, size = [], 0
        if held:
            yield close(held)

    def close(held):
        ids, near = (np.concatenate([h[i] for h in held]) for i in (0, 1))
        return _packed(ids, np.concatenate([h[2] for h in held]) if stored else None, near, m)

    seen.mapInArrow(cut, _SCHEMA).write.mode("overwrite").parquet(f"{path}/chunks")
    pivots.frame.write.mode("overwrite").parquet(f"{path}/pivots")
    manifest = {"dist": d.name, "m": m, "mi": mi, "side": side, "points": spark.read.parquet(f"{path}/chunks").agg(F.sum("points")).first()[0] or 0}
    spark.createDataFrame([(json.dumps(manifest, sort_keys=True),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/manifest")
    return StoredSharedPivots(spark, path)


class StoredSharedPivots:
    """An index folder, opened."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path
        held = json.loads(spark.read.text(f"{path}/manifest").first()["value"])
        self.dist, self.m, self.mi, self.side, self.n = distance(held["dist"]), held["m"], held["mi"], held["side"], held["points"]
        frame = spark.read.parquet(f"{path}/pivots")
        self.pivots = Pivots(frame, frame.orderBy("pid").collect())
        self.chunks = spark.read.schema(_SCHEMA).parquet(f"{path}/chunks")

    def _asked(self, queries: DataFrame) -> tuple[np.ndarray, np.ndarray]:
        """Query ids and, for each, the numbers from 0 of its closest pivots."""
        rows = see(queries.select("qid", "x"), self.pivots, self.dist, self.side, self.mi, ("ord",)).select("qid", "ord").orderBy("qid").limit(MOST_QUERIES + 1).collect()
        if len(rows) > MOST_QUERIES:
            raise ValueError(f"more than {MOST_QUERIES} queries: search them in blocks")
        return np.array([r["qid"] for r in rows], np.int64), np.array([r["ord"] for r in rows], np.int64).reshape(len(rows), self.mi) - 1

    def _counted(self, queries: DataFrame, use, schema: str, finish=lambda: ()) -> DataFrame:
        """What ``use`` gives for each chunk and query, from the chunk's arrays and the places that share enough."""
        qids, near = self._asked(queries)

        def run(source):
            for batch in source:
                for row in batch.to_pylist():
                    n, starts = row["points"], np.frombuffer(row["starts"], np.int32)
                    places = np.frombuffer(row["places"], np.int32 if n > 65_535 else np.uint16)
                    ids = np.frombuffer(row["ids"], np.int64)
                    x = np.frombuffer(row["payload"], np.float64).reshape(n, row["dim"]) if row["dim"] else None
                    for q in range(len(qids)):
                        read = np.concatenate([places[starts[p] : starts[p + 1]] for p in near[q]])
                        yield from use(q, np.bincount(read, minlength=n), ids, x)
            yield from finish()

        return self.chunks.mapInArrow(run, schema)

    def candidates(self, queries: DataFrame, t: int = 1) -> DataFrame:
        """(qid, id, score) of the points that share at least ``t`` pivots; score is mi less what they share."""
        qids, mi = self._asked(queries)[0], self.mi

        def use(q, counts, ids, x):
            at = np.flatnonzero(counts >= t)
            yield pa.RecordBatch.from_pydict({"qid": np.full(len(at), qids[q]), "id": ids[at], "score": mi - counts[at]})

        return self._counted(queries, use, "qid long, id long, score long")

    def search(self, queries: DataFrame, k: int = 10, t: int = 1, points: DataFrame | None = None) -> DataFrame:
        """(qid, id, dist, rnk) of the k nearest among the candidates. points: needed where payloads are not stored."""
        if not 1 <= t <= self.mi:
            raise ValueError("t must be from 1 to mi")
        if self.dist.matrix is None:
            if points is None:
                raise ValueError(f"an index by {self.dist.name} holds no payloads: give the points")
            return refine(self.candidates(queries, t), points, queries, self.dist, k, self.side)
        qids, held = query_block(queries, self.dist.payload)
        best, d, side = Kept(len(qids), k), self.dist, self.side
        rows: list = []  # of some queries and chunks, merged together

        def merge():
            if rows:
                best.merge(*(np.concatenate(x) for x in zip(*rows, strict=True)))
                rows.clear()

        def use(q, counts, ids, x):
            at = np.flatnonzero(counts >= t)
            if len(at):
                far = d.between(x[at], held[q : q + 1], side)[:, 0]
                keys = rank_keys(far)
                edge = min(best.edge[q], np.partition(keys, k - 1)[k - 1] if len(keys) > k else best.edge[q])
                near = np.flatnonzero(keys <= edge)
                rows.append((np.full(len(near), q), keys[near], ids[at[near]], far[near]))
                if len(rows) >= 1000:
                    merge()
            return ()

        def finish():
            merge()
            yield pa.RecordBatch.from_pydict({"qid": qids[best.q], "id": best.id, "dist": best.value})

        return ranked(self._counted(queries, use, "qid long, id long, dist double", finish), k)

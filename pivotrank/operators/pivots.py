"""Pivots, and what points look like from them: distances, orders, ranks and packed bits."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType, LongType, ShortType, StructField, StructType

from ..functions.distances import Distance, distance, rank_key, rank_keys
from ..functions.hashing import order_key

MOST_PIVOTS = 4096


def matrix(column: pa.Array, payload: str) -> np.ndarray:
    """A block of payloads as rows of a matrix."""
    if payload == "histogram":
        column = column.field("p") if isinstance(column, pa.StructArray) else column
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return flat.reshape(len(column), -1) if len(column) else flat.reshape(0, 0)


@dataclass
class Pivots:
    """Chosen pivots, numbered from 1 in their seeded order. At most MOST_PIVOTS, so the driver may hold them."""

    frame: DataFrame
    rows: list

    @property
    def m(self) -> int:
        return len(self.rows)

    def matrix(self, payload: str) -> np.ndarray:
        return np.array([r["x"]["p"] if payload == "histogram" else r["x"] for r in self.rows], np.float64)

    def array(self) -> DataFrame:
        """One row: the pivots' payloads in order."""
        return self.frame.groupBy().agg(F.transform(F.array_sort(F.collect_list(F.struct("pid", "x"))), lambda p: p["x"]).alias("_pivots"))


def select_pivots(points: DataFrame, m: int, seed: int = 7, copy: int = 0) -> Pivots:
    """``m`` points at random: the first of a seeded order by id. m may not exceed the points."""
    if not 1 <= m <= MOST_PIVOTS:
        raise ValueError(f"the number of pivots must be from 1 to {MOST_PIVOTS}")
    order = order_key(f"pivot{seed}:{copy}", "id")
    rows = points.select("id", "x", order.alias("h")).orderBy("h", "id").limit(m).collect()
    if len(rows) < m:
        raise ValueError(f"{m} pivots asked for, but there are only {len(rows)} points")
    spark = points.sparkSession
    schema = StructType([StructField("pid", LongType()), StructField("id", LongType()), StructField("x", points.schema["x"].dataType)])
    return Pivots(spark.createDataFrame([(i + 1, r["id"], r["x"]) for i, r in enumerate(rows)], schema).coalesce(1), rows)


def select_pivot_copies(points: DataFrame, m: int, copies: int, seed: int = 7) -> list[Pivots]:
    """Several sets of pivots, each from its own order."""
    return [select_pivots(points, m, seed, c) for c in range(copies)]


_KINDS = {"pd": ArrayType(DoubleType()), "ord": ArrayType(ShortType()), "rank": ArrayType(ShortType())}


def see(points: DataFrame, pivots: Pivots, dist: str | Distance, side: str = "left", mi: int | None = None, want: tuple[str, ...] = ("ord", "rank"), backend: str = "auto") -> DataFrame:
    """The points with pd (distances), ord (pivots, closest first, the first ``mi``) and rank (of each pivot).

    Ties go to the lower pivot. ``arrow`` works on blocks of points in numpy, ``native`` in Column
    expressions, for payloads without a matrix form; both give the same orders. No shuffle either way.
    """
    d = distance(dist)
    if mi is not None and not 1 <= mi <= pivots.m:
        raise ValueError("mi must be from 1 to the number of pivots")
    if backend == "auto":
        backend = "arrow" if d.matrix else "native"
    mi = mi or pivots.m
    if backend == "native":
        seen = points.crossJoin(F.broadcast(pivots.array())).withColumn("pd", F.transform("_pivots", lambda p: d(F.col("x"), p, side)))
        keyed = F.array_sort(F.transform("pd", lambda v, i: F.struct(rank_key(v).alias("k"), (i + 1).cast("short").alias("pid"))))
        seen = seen.withColumn("ord", F.transform(keyed, lambda s: s["pid"]))
        if "rank" in want:
            pairs = F.array_sort(F.transform("ord", lambda p, i: F.struct(p.alias("p"), (i + 1).cast("short").alias("r"))))
            seen = seen.withColumn("rank", F.transform(pairs, lambda s: s["r"]))
        return seen.withColumn("ord", F.slice("ord", 1, mi)).select(*points.columns, *want)

    held, payload = pivots.matrix(d.payload), d.payload
    names = list(points.columns)
    at = names.index("x")

    def look(source):
        for batch in source:
            n = len(batch)
            if not n:
                continue
            pd = d.between(matrix(batch.column(at), payload), held, side)
            order = np.argsort(rank_keys(pd), 1, kind="stable")
            made = {"pd": pd}
            if "rank" in want:
                rank = np.empty_like(order)
                np.put_along_axis(rank, order, np.arange(1, order.shape[1] + 1)[None], 1)
                made["rank"] = rank.astype(np.int16)
            made["ord"] = (order[:, :mi] + 1).astype(np.int16)
            new = [pa.ListArray.from_arrays(pa.array(np.arange(0, made[w].size + 1, made[w].shape[1]), pa.int32()), pa.array(np.ascontiguousarray(made[w]).ravel())) for w in want]
            yield pa.RecordBatch.from_arrays([*batch.columns, *new], names=[*names, *want])

    return points.mapInArrow(look, StructType([*points.schema.fields, *[StructField(w, _KINDS[w]) for w in want]]))

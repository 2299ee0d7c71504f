"""Accuracy and cost measures."""

from __future__ import annotations

import time

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.distances import distance, rank_key
from .graphs import cut


def recall(result: DataFrame, truth: DataFrame, k: int = 10, ties: bool = False) -> DataFrame:
    """One row (recall): the mean share of the true k nearest returned.

    With ``ties`` a result counts if it is no farther than the true k-th.
    """
    n = truth.select("qid").distinct().agg(F.count("*").alias("n"))
    if ties:
        edge = truth.groupBy("qid").agg(F.max(rank_key(F.col("dist"))).alias("edge"), F.count("*").alias("size"))
        hits = result.join(edge, "qid").where(rank_key(F.col("dist")) <= F.col("edge")).groupBy("qid", "size").agg(F.count("*").alias("h")).select(F.least("h", "size").alias("h"))
    else:
        hits = result.join(truth.select("qid", "id"), ["qid", "id"]).groupBy("qid").agg(F.count("*").alias("h"))
    return hits.agg(F.coalesce(F.sum("h"), F.lit(0)).alias("h")).crossJoin(n).select((F.col("h") / (F.col("n") * k)).alias("recall"))


def candidate_fraction(candidates: DataFrame, queries: int, n: int) -> DataFrame:
    return candidates.agg((F.count("*") / F.lit(queries * n)).alias("fraction"))


def fraction_for_recall(ordered: DataFrame, truth: DataFrame, n: int, k: int = 10, levels: tuple[float, ...] = (0.5, 0.8, 0.9, 0.95, 1.0)) -> DataFrame:
    """(level, fraction): the least share of the points to take from a projected order, to reach a recall.

    ordered: (qid, id, score) of all points. The places of the true neighbours in their queries' orders,
    sorted, give the whole curve in one pass.
    """
    w = Window.partitionBy("qid").orderBy("score", "id")
    places = ordered.withColumn("place", F.row_number().over(w)).join(F.broadcast(truth.select("qid", "id")), ["qid", "id"])
    every = places.withColumn("nth", F.row_number().over(Window.orderBy("place"))).withColumn("total", F.count("*").over(Window.partitionBy()))  # queries times k rows
    wanted = F.explode(F.array(*[F.lit(x) for x in levels])).alias("level")
    return every.select("nth", "place", "total", wanted).where(F.col("nth") == F.ceil(F.col("level") * F.col("total") - 1e-9)).select("level", (F.col("place") / F.lit(n)).alias("fraction"))


def transformed(name: str) -> Column | None:
    return distance(name).transform


def triples(points: DataFrame, modulus: int = 97) -> DataFrame:
    """Hashed triples (a, b, q) of payloads among the first ``modulus`` points of a hashed order; see all_triples."""
    h = F.md5(F.col("id").cast("string").cast("binary"))
    first = points.select("id", "x", h.alias("_h")).orderBy("_h", "id").limit(modulus)
    few = first.withColumn("i", F.row_number().over(Window.orderBy("_h", "id")))
    a, b, q = (few.select(F.col("i").alias(f"i{c}"), F.col("x").alias(c)) for c in "abq")
    step = lambda s: F.pmod(F.col("ia") * s, F.lit(modulus)) + 1
    return a.withColumn("ib", step(31)).withColumn("iq", step(57)).join(b, "ib").join(q, "iq").where("ia <> ib AND ib <> iq AND ia <> iq").select("a", "b", "q")


def all_triples(points: DataFrame) -> DataFrame:
    """Triples (a, b, q) of payloads: every point with two others by arithmetic on its place in the hashed order.

    Places come from a distributed sort and the partitions' counts; a point that meets itself gives none.
    """
    order = cut(points.select("id", "x").sort(F.md5(F.col("id").cast("string").cast("binary")), "id"))
    placed = order.withColumn("m", F.monotonically_increasing_id()).withColumn("part", F.shiftright("m", 33))
    sizes = sorted(placed.groupBy("part").count().collect())  # a row for each partition
    before = [(r["part"], sum(s["count"] for s in sizes[:k])) for k, r in enumerate(sizes)]
    n = sum(r["count"] for r in sizes)
    starts = F.broadcast(points.sparkSession.createDataFrame(before, "part long, before long"))
    every = placed.join(starts, "part").select((F.col("before") + F.col("m").bitwiseAND((1 << 33) - 1) + 1).alias("i"), "x")
    a, b, q = (every.select(F.col("i").alias(f"i{c}"), F.col("x").alias(c)) for c in "abq")
    step = lambda s: F.pmod(F.col("ia") * s, F.lit(max(1, n))) + 1
    return a.withColumn("ib", step(31)).withColumn("iq", step(57)).join(b, "ib").join(q, "iq").where("ia <> ib AND ib <> iq AND ia <> iq").select("a", "b", "q")


def triangle_violations(triple: DataFrame, dist) -> DataFrame:
    """(triples, violations): how often the way over a third point is shorter."""
    d = distance(dist)
    worse = d(F.col("a"), F.col("b")) > d(F.col("a"), F.col("q")) + d(F.col("q"), F.col("b")) + 1e-9
    return triple.agg(F.count("*").alias("triples"), F.count(F.when(worse, 1)).alias("violations"))


def mu_defect(triple: DataFrame, dist) -> DataFrame:
    """(triples, mu): the largest ratio of a difference of transformed distances to the transformed distance."""
    d = distance(dist)
    f = d.transform or (lambda v: v)
    ratio = F.abs(f(d(F.col("q"), F.col("a"))) - f(d(F.col("q"), F.col("b")))) / f(d(F.col("a"), F.col("b")))
    return triple.where(f(d(F.col("a"), F.col("b"))) > 1e-6).agg(F.count("*").alias("triples"), F.max(ratio).alias("mu"))


def permutation_bytes(m: int, binary: bool = False) -> int:
    """Bytes of one permutation: 32 bits a rank, or one bit."""
    return (m + 7) // 8 if binary else 4 * m


def index_cost(n: int, m: int, bucket: int) -> dict[str, float]:
    """Distances computed at building: every point to every pivot, against the levels of a ball tree."""
    import math

    return {"pivots": n * m, "ball_tree": n * max(0.0, math.log2(n / bucket))}


def index_bytes(spark, path: str) -> int:
    """Bytes of a stored index, on whatever store it lies."""
    target = spark._jvm.org.apache.hadoop.fs.Path(path)
    return target.getFileSystem(spark._jsc.hadoopConfiguration()).getContentSummary(target).getLength()


def neighbour_transitivity(graph: DataFrame) -> DataFrame:
    """(paths, closed, share): how often near(a, b) and near(b, c) bring near(a, c), over all pairs of edges (src, dst)."""
    edges = graph.select("src", "dst").distinct()
    paths = edges.select(F.col("src").alias("a"), F.col("dst").alias("b")).join(edges.select(F.col("src").alias("b"), F.col("dst").alias("c")), "b").where("a <> c")
    closed = paths.join(edges.select(F.col("src").alias("a"), F.col("dst").alias("c"), F.lit(1).alias("hit")), ["a", "c"], "left")
    return closed.agg(F.count("*").alias("paths"), F.count("hit").alias("closed")).withColumn("share", F.col("closed") / F.col("paths"))


def rank_correlation(scatter: DataFrame, by: str = "stratum") -> DataFrame:
    """Spearman's coefficient of dist and projected for each stratum: Pearson's, of mid-ranks."""
    def rank(c):
        w, own = Window.partitionBy(by).orderBy(c), Window.partitionBy(by, c)
        return F.rank().over(w) + (F.count("*").over(own) - 1) / 2

    placed = scatter.select(by, rank("dist").alias("r"), rank("projected").alias("s"))
    return placed.groupBy(by).agg(F.round(F.corr("r", "s"), 6).alias("spearman"))


def speed_up(exact_seconds: float, seconds: float) -> float:
    """How many times faster than the exact scan."""
    return exact_seconds / seconds if seconds else float("inf")


def timed(frame: DataFrame) -> float:
    """Seconds to compute all rows."""
    start = time.perf_counter()
    frame.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - start

"""Neighbour graphs as edge tables: exact, by descent, and as a small world; and searches on them.

Points of at most GATHERED bytes go to the tasks, which then scan, measure and walk in numpy. Of more points, or
with repeated ids, the exact graph makes cells: a task holds a cell's points as queries and all points stream by.
Descent and walks over such points, or by distances without a matrix form, advance in supersteps of joins; each ends
in a checkpoint, so lineage stays short and a lost executor costs one superstep. Both ways give the same rows. The
exact graph is a checkpoint too: whoever reads it twice does not compute it twice.
"""

from __future__ import annotations

import math
import tempfile

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.distances import Distance, distance, rank_key, rank_keys
from .pivots import matrix
from .search import BLOCK_PAIRS, Kept, exact_knn, tiles

GATHERED = 128 << 20  # bytes of points, or of a search's points and links, that a task may hold
CELL = 8192  # points at most, about, that a task of the exact graph takes as queries
PAIRS = 1 << 20  # pairs of points that a task of the descent gathers before it hands them on
_LAST = np.iinfo(np.int64).max


def shared_folder(spark) -> str:
    """The folder that spark.checkpoint.dir names; where it is unset, a temporary one if driver and executors are one machine."""
    context = spark.sparkContext
    if context._jsc.sc().getCheckpointDir().isEmpty():
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named and not context.master.startswith("local["):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        context.setCheckpointDir(named or tempfile.mkdtemp(prefix="checkpoint-"))
    return context._jsc.sc().getCheckpointDir().get()


def cut(frame: DataFrame) -> DataFrame:
    """A checkpoint in the shared folder."""
    shared_folder(frame.sparkSession)
    return frame.checkpoint()


def _top(edges: DataFrame, k: int, extra: tuple[str, ...] = ()) -> DataFrame:
    w = Window.partitionBy("src").orderBy(rank_key(F.col("dist")), "dst")
    return edges.withColumn("_r", F.row_number().over(w)).where(F.col("_r") <= k).select("src", "dst", "dist", *extra)


def _measured(pairs: DataFrame, points: DataFrame, d: Distance) -> DataFrame:
    a, b = points.select(F.col("id").alias("src"), F.col("x").alias("_a")), points.select(F.col("id").alias("dst"), F.col("x").alias("_b"))
    return pairs.join(b, "dst").join(a, "src").select("src", "dst", d(F.col("_b"), F.col("_a")).alias("dist"))


def exact_graph(points: DataFrame, dist, k: int = 10) -> DataFrame:
    """Every point's k nearest others. The work grows with the square of the points; no task holds more than a cell and a batch."""
    d = distance(dist)
    if d.matrix is None:
        found = exact_knn(points, points.select(F.col("id").alias("qid"), "x"), dist, k + 1)
        return cut(_top(found.where("qid <> id").select(F.col("qid").alias("src"), F.col("id").alias("dst"), "dist"), k))
    gathered = _gathered(points, d)
    if gathered is not None:
        return _exact_here(points.sparkSession, gathered, d, k)
    rows = cut(points.select("id", "x"))
    n = rows.count()
    cells = max(1, min(math.ceil(n / 64), max(3 * points.sparkSession.sparkContext.defaultParallelism, math.ceil(n / CELL))))
    cell = F.pmod(F.xxhash64("id"), F.lit(cells)).cast("int")
    held = rows.select(cell.alias("cell"), F.lit(False).alias("passes"), "id", "x")
    passing = rows.select(F.explode(F.sequence(F.lit(0), F.lit(cells - 1))).alias("cell"), F.lit(True).alias("passes"), "id", "x")
    dealt = held.unionByName(passing).repartitionById(cells, F.col("cell")).sortWithinPartitions("cell", "passes")

    def scan(source):
        now, ids, x, best = None, [], [], None

        def close():
            if best is not None:
                kept = best.key < _LAST  # a point is no neighbour of its own
                yield pa.RecordBatch.from_pydict({"src": own[best.q[kept]], "dst": best.id[kept], "dist": best.value[kept]})

        for batch in source:
            numbers = batch.column(0).to_numpy()
            bounds = [0, *(np.flatnonzero(np.diff(numbers)) + 1).tolist(), len(batch)]
            for a, b in zip(bounds, bounds[1:], strict=False):
                if a == b:
                    continue
                if numbers[a] != now:
                    yield from close()
                    now, ids, x, best = numbers[a], [], [], None
                part = batch.slice(a, b - a)
                few = b - a - int(part.column(1).to_numpy(zero_copy_only=False).sum())
                part_ids, part_x = part.column(2).to_numpy(), matrix(part.column(3), d.payload)
                if few:
                    ids.append(part_ids[:few])
                    x.append(part_x[:few])
                part_ids, part_x = part_ids[few:], part_x[few:]
                if not len(part_ids) or not ids:
                    continue
                if best is None:
                    own, asked = np.concatenate(ids), np.concatenate(x)
                    order = np.argsort(own, kind="stable")
                    own, asked = own[order], asked[order]
                    best = Kept(len(own), k)
                for c, e in tiles(len(own), len(part_ids)):
                    far = d.between(part_x[c:e], asked).T
                    keys = rank_keys(far)
                    lo, hi = (np.searchsorted(own, part_ids[c:e], side) for side in ("left", "right"))
                    for j in np.flatnonzero(hi > lo):
                        keys[lo[j] : hi[j], j] = _LAST
                    best.add(0, keys, part_ids[c:e], far)
        yield from close()

    return cut(_top(dealt.mapInArrow(scan, "src long, dst long, dist double"), k))


def _exact_here(spark, gathered, d: Distance, k: int) -> DataFrame:
    """exact_graph over gathered points: a task scans them all for each of its runs of points."""
    n = len(gathered[0])
    step = max(1, min(CELL, math.ceil(n / (3 * spark.sparkContext.defaultParallelism))))
    sent = spark.sparkContext.broadcast(gathered)

    def scan(source):
        ids, x = sent.value
        for batch in source:
            for a in batch.column(0).to_pylist():
                b = min(n, a + step)
                best, wide = Kept(b - a, k), max(1, BLOCK_PAIRS // (b - a))
                for c in range(0, n, wide):
                    e = min(n, c + wide)
                    far = d.between(x[c:e], x[a:b]).T
                    keys = rank_keys(far)
                    own = np.arange(max(a, c), min(b, e))
                    keys[own - a, own - c] = _LAST
                    best.add(0, keys, ids[c:e], far)
                kept = best.key < _LAST  # a point is no neighbour of its own
                yield pa.RecordBatch.from_pydict({"src": ids[a + best.q[kept]], "dst": best.id[kept], "dist": best.value[kept]})

    out = cut(spark.range(0, n, step, math.ceil(n / step)).mapInArrow(scan, "src long, dst long, dist double"))
    sent.unpersist()
    return out


def _gathered(points: DataFrame, d: Distance, more: int = 0) -> tuple[np.ndarray, np.ndarray] | None:
    """Ids in order and the payloads' matrix; None where tasks may not hold them, ids repeat or there is no matrix form."""
    if d.matrix is None:
        return None
    x = F.col("x")["p"] if d.payload == "histogram" else F.col("x")
    said = points.agg(F.count("*").alias("n"), F.sum(F.size(x)).alias("s")).first()
    if not said["n"] or 8 * (said["n"] + said["s"]) + more > GATHERED:
        return None
    held = points.select("id", x.alias("x")).toArrow().combine_chunks()
    ids = held.column(0).to_numpy()
    order = np.argsort(ids, kind="stable")
    ids = ids[order]
    if (ids[1:] == ids[:-1]).any():
        return None
    return ids, matrix(pa.concat_arrays(held.column(1).chunks), "vector")[order]


def _spread(frame: DataFrame) -> DataFrame:
    """Rows dealt evenly over the cores: a few rows can be much work."""
    return frame.repartition(2 * frame.sparkSession.sparkContext.defaultParallelism)


def _joined(near: DataFrame, edges: DataFrame) -> DataFrame:
    """(src, dst), both ways, of neighbours (v, u, fresh) that meet at v, one of them fresh, and are not linked."""
    met = near.where("fresh").select("v", F.col("u").alias("p")).join(near.select("v", F.col("u").alias("q")), "v").where("p <> q")
    both = met.select(F.explode(F.array(F.struct(F.col("p").alias("src"), F.col("q").alias("dst")), F.struct(F.col("q").alias("src"), F.col("p").alias("dst")))).alias("e")).select("e.*").distinct()
    return both.join(edges.select("src", "dst"), ["src", "dst"], "left_anti")


def _measured_here(pairs: DataFrame, sent, d: Distance) -> DataFrame:
    """(src, dst, dist) of pairs of gathered points."""

    def run(source):
        ids, x = sent.value
        for batch in source:
            lists = batch.column(1)
            ends = np.concatenate(([0], np.cumsum(lists.value_lengths().to_numpy())))
            src, dst = batch.column(0).to_numpy(), lists.flatten().to_numpy()
            at, own = np.searchsorted(ids, dst), np.searchsorted(ids, src)
            dist = [d.between(x[at[a:b]], x[i : i + 1])[:, 0] for i, a, b in zip(own, ends, ends[1:], strict=False)]
            if dist:
                yield pa.RecordBatch.from_pydict({"src": np.repeat(src, np.diff(ends)), "dst": dst, "dist": np.concatenate(dist)})

    return pairs.groupBy("src").agg(F.collect_list("dst").alias("dst")).mapInArrow(run, "src long, dst long, dist double")


def _joined_here(near: DataFrame, edges: DataFrame, sent, d: Distance, k: int) -> DataFrame:
    """The pairs of _joined with their distances, less those beyond the src's k nearest so far, which could not enter."""
    last = edges.groupBy("src").agg(F.count("*").alias("n"), F.max(rank_key(F.col("dist"))).alias("key")).where(F.col("n") >= k).select("src", "key").toArrow()
    limits = edges.sparkSession.sparkContext.broadcast((last.column(0).to_numpy(), last.column(1).to_numpy()))
    lists = near.groupBy("v").agg(F.collect_list("u").alias("u"), F.collect_list("fresh").alias("fresh"))

    def run(source):
        ids, x = sent.value
        limit = np.full(len(ids), _LAST)
        limit[np.searchsorted(ids, limits.value[0])] = limits.value[1]

        def made(codes, dist):
            code, first = np.unique(np.concatenate(codes), return_index=True)
            return pa.RecordBatch.from_pydict({"src": ids[code // len(ids)], "dst": ids[code % len(ids)], "dist": np.concatenate(dist)[first]})

        for batch in source:
            us = batch.column(1)
            ends = np.concatenate(([0], np.cumsum(us.value_lengths().to_numpy())))
            at = np.searchsorted(ids, us.flatten().to_numpy())
            fresh = batch.column(2).flatten().to_numpy(zero_copy_only=False)
            codes, dist, held = [], [], 0
            for a, b in zip(ends, ends[1:], strict=False):
                own, new = at[a:b], fresh[a:b]
                if not new.any():
                    continue
                far = d.between(x[own], x[own]).T  # row: src, column: dst
                takes = (rank_keys(far) <= limit[own][:, None]) & (new[:, None] | new[None])
                np.fill_diagonal(takes, False)
                i, j = np.nonzero(takes)
                codes.append(own[i] * len(ids) + own[j])
                dist.append(far[i, j])
                held += len(i)
                if held >= PAIRS:
                    yield made(codes, dist)
                    codes, dist, held = [], [], 0
            if codes:
                yield made(codes, dist)

    found = lists.mapInArrow(run, "src long, dst long, dist double").groupBy("src", "dst").agg(F.min("dist").alias("dist"))
    return found.join(edges.select("src", "dst"), ["src", "dst"], "left_anti")


def nn_descent(points: DataFrame, dist, k: int = 10, rho: float = 0.5, delta: float = 0.001, max_iter: int = 12, seed: int = 29, decay: float = 1.0) -> DataFrame:
    """Neighbours of neighbours are likely neighbours: from a random graph, until few edges change.

    rho: share of a node's new edges that a round samples (forward and, as many at most, reverse); every
    round multiplies it by ``decay``.
    """
    d = distance(dist)
    n = points.count()
    # a node's first neighbours come from several dealings into small buckets, so that they do not form cliques
    deals = min(k, 5)
    each = math.ceil(k / deals)
    buckets, start = max(1, n // (3 * each + 3)), None
    for turn in range(deals):
        dealt = points.select("id", F.pmod(F.xxhash64(F.lit(seed * 100 + turn), "id"), F.lit(buckets)).alias("b"))
        pairs = dealt.select(F.col("id").alias("src"), "b").join(dealt.select(F.col("id").alias("dst"), "b"), "b").where("src <> dst")  # buckets of bounded size
        w = Window.partitionBy("src").orderBy(F.xxhash64(F.lit(seed), "src", "dst"))
        one = pairs.withColumn("_r", F.row_number().over(w)).where(F.col("_r") <= each).select("src", "dst")
        start = one if start is None else start.unionByName(one)
    start = start.distinct()
    gathered = _gathered(points, d)
    sent = gathered and points.sparkSession.sparkContext.broadcast(gathered)
    measured = _measured(start, points, d) if sent is None else _measured_here(start, sent, d)
    edges = cut(measured.withColumn("new", F.lit(True)))
    for turn in range(max_iter):
        sample = max(1, math.ceil(rho * decay**turn * k))
        pick = lambda by: F.row_number().over(Window.partitionBy(by).orderBy(F.xxhash64(F.lit(seed + turn + 1), "src", "dst")))  # noqa: E731, B023
        chosen = edges.where("new").withColumn("_r", pick("src")).where(F.col("_r") <= sample).select("src", "dst")
        both = edges.join(chosen.withColumn("_c", F.lit(True)), ["src", "dst"], "left").select("src", "dst", "new", F.coalesce("_c", F.lit(False)).alias("fresh"))
        usable = both.where("fresh OR NOT new")
        back = usable.withColumn("_r", F.row_number().over(Window.partitionBy("dst", "fresh").orderBy(F.xxhash64(F.lit(seed + turn + 1), "src", "dst")))).where(F.col("_r") <= sample)
        near = usable.select(F.col("src").alias("v"), F.col("dst").alias("u"), "fresh").unionByName(back.select(F.col("dst").alias("v"), F.col("src").alias("u"), "fresh")).groupBy("v", "u").agg(F.max("fresh").alias("fresh"))
        near = cut(near)
        if sent is not None:
            proposed = _joined_here(near, edges, sent, d, k)
        else:
            proposed = _measured(_joined(near, edges), points, d)
        proposed = proposed.withColumn("new", F.lit(True)).withColumn("fresh", F.lit(False))
        kept = edges.join(both.select("src", "dst", "fresh"), ["src", "dst"]).withColumn("new", F.col("new") & ~F.col("fresh"))
        merged = cut(_top(kept.unionByName(proposed.select(*kept.columns)).withColumn("added", F.lit(False)), k, ("new",)))
        before = edges.select("src", "dst", F.lit(True).alias("_had"))
        changed = merged.join(before, ["src", "dst"], "left_anti").count()
        edges = merged
        if changed <= delta * n * k:
            break
    if sent is not None:
        sent.unpersist()
    return edges.select("src", "dst", "dist")


def graph_search(edges: DataFrame, points: DataFrame, queries: DataFrame, dist, k: int = 10, starts: int = 5, ef: int | None = None, seed: int = 31, max_steps: int = 50, side: str = "left") -> DataFrame:
    """Walks from random starts to ever nearer neighbours; a beam keeps the ``ef`` best met.

    Ends when no query has a node among its best that was not opened. ef = 1 is the plain greedy walk.
    """
    d, ef = distance(dist), ef or 2 * k
    gathered = _gathered(points, d, 8 * edges.count()) if d.matrix else None
    if gathered is not None:
        return _walked(edges, points, gathered, queries, d, k, starts, ef, seed, max_steps, side)
    asked = F.broadcast(queries.select("qid", F.col("x").alias("q")))
    first = points.orderBy(F.xxhash64(F.lit(seed), "id"), "id").limit(starts)
    scored = first.select("id", "x").crossJoin(asked).select("qid", "id", d(F.col("x"), F.col("q"), side).alias("dist"))
    met = cut(scored.withColumn("open", F.lit(True)))
    w = Window.partitionBy("qid").orderBy(rank_key(F.col("dist")), "id")
    links = edges.select(F.col("src").alias("id"), F.col("dst").alias("to"))
    for _ in range(max_steps):
        best = met.withColumn("_r", F.row_number().over(w))
        front = best.where((F.col("_r") <= max(ef, 1)) & F.col("open")).select("qid", "id")
        front = cut(front)
        if front.isEmpty():
            break
        near = front.join(links, "id").select("qid", F.col("to").alias("id")).distinct().join(met.select("qid", "id"), ["qid", "id"], "left_anti")
        new = near.join(points.select("id", "x"), "id").join(asked, "qid").select("qid", "id", d(F.col("x"), F.col("q"), side).alias("dist"), F.lit(True).alias("open"))
        closed = met.join(front.withColumn("_f", F.lit(True)), ["qid", "id"], "left").select("qid", "id", "dist", (F.col("open") & F.col("_f").isNull()).alias("open"))
        met = cut(closed.unionByName(new))
    return met.withColumn("rnk", F.row_number().over(w)).where(F.col("rnk") <= k).select("qid", "id", "dist", "rnk")


def _walked(edges, points, gathered, queries, d: Distance, k: int, starts: int, ef: int, seed: int, max_steps: int, side: str) -> DataFrame:
    """graph_search over gathered points and links: a task walks for a block of queries at once."""
    context = points.sparkSession.sparkContext
    ids, x = gathered
    first = np.searchsorted(ids, [r["id"] for r in points.orderBy(F.xxhash64(F.lit(seed), "id"), "id").limit(starts).select("id").collect()])
    held = edges.select("src", "dst").toArrow()
    ends = [c.to_numpy() for c in held.columns]
    src, dst = (np.minimum(np.searchsorted(ids, c), len(ids) - 1) for c in ends)
    known = (ids[src] == ends[0]) & (ids[dst] == ends[1])
    src, dst = src[known], dst[known]
    order = np.argsort(src, kind="stable")
    sent = context.broadcast((ids, x, np.searchsorted(src[order], np.arange(len(ids) + 1)), dst[order].astype(np.int32)))
    block, most, payload = max(1, (64 << 20) // len(ids)), max(ef, k), d.payload

    def walk(qids, asked):
        ids, x, begins, links = sent.value
        n, dims = len(ids), np.arange(len(qids))
        seen = np.zeros(len(qids) * n, bool)
        q, p = np.repeat(dims, len(first)), np.tile(first, len(qids))
        best = [np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0), np.empty(0, bool)]
        for step in range(max_steps + 1):
            seen[q * n + p] = True
            bounds = np.searchsorted(q, np.arange(len(qids) + 1))
            far = np.concatenate([d.between(x[p[a:b]], asked[i : i + 1], side)[:, 0] for i, (a, b) in enumerate(zip(bounds, bounds[1:], strict=False)) if b > a])
            best = [np.concatenate(c) for c in zip(best, (q, rank_keys(far), p, far, np.ones(len(q), bool)), strict=True)]
            order = np.lexsort((best[2], best[1], best[0]))  # ids are in order, so their numbers break ties as they do
            best = [c[order] for c in best]
            place = np.arange(len(order)) - np.searchsorted(best[0], best[0])
            kept = place < most
            best, place = [c[kept] for c in best], place[kept]
            front = best[4] & (place < ef)
            if step == max_steps or not front.any():
                break
            best[4] = best[4] & ~front
            at, owner = best[2][front], best[0][front]
            counts = begins[at + 1] - begins[at]
            codes = np.repeat(owner * n, counts) + links[np.repeat(begins[at] - np.cumsum(counts) + counts, counts) + np.arange(counts.sum())]
            codes = np.unique(codes[~seen[codes]])
            if not len(codes):
                break
            q, p = codes // n, codes % n
        near = place < k
        return pa.RecordBatch.from_pydict({"qid": qids[best[0][near]], "id": ids[best[2][near]], "dist": best[3][near], "rnk": place[near].astype(np.int32) + 1})

    def run(source):
        for batch in source:
            for a in range(0, len(batch), block):
                part = batch.slice(a, block)
                yield walk(part.column(0).to_numpy(), matrix(part.column(1), payload))

    out = cut(_spread(queries.select("qid", "x")).mapInArrow(run, "qid long, id long, dist double, rnk int"))
    sent.unpersist()
    return out


def small_world(points: DataFrame, dist, k: int = 10, attempts: int = 3, first: int = 64, growth: float = 2.0, seed: int = 37) -> DataFrame:
    """Points join in batches that grow: each is searched in what stands and linked both ways to what is found.

    Edges are never dropped. Members of a batch do not see one another, other than in the first, which
    is linked exactly; the sequential method links each point to those before it.
    """
    order = points.select("id", F.xxhash64(F.lit(seed), "id").alias("h"))
    n = points.count()
    bounds, size = [], float(min(first, n))
    while size < n:
        bounds.append(size / n)
        size *= growth
    cuts = order.agg(F.percentile_approx("h", [*bounds, 1.0], 100_000).alias("c")).first()["c"] if n else []
    held = cut(points.select("id", "x", F.xxhash64(F.lit(seed), "id").alias("h")))
    edges = None
    for i, upper in enumerate(cuts):
        batch = held.where((F.col("h") <= upper) & ((F.col("h") > cuts[i - 1]) if i else F.lit(True))).select("id", "x")
        if edges is None:
            own = exact_graph(batch, dist, k)
        else:
            inside = held.where(F.col("h") <= cuts[i - 1]).select("id", "x")
            own = graph_search(edges, inside, batch.select(F.col("id").alias("qid"), "x"), dist, k, attempts, 2 * k, seed + i).select(F.col("qid").alias("src"), F.col("id").alias("dst"), "dist")
        both = own.unionByName(own.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "dist"))
        edges = cut((both if edges is None else edges.unionByName(both)).groupBy("src", "dst").agg(F.min("dist").alias("dist")))
    return edges

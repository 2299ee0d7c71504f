"""Approximate nearest neighbours by inner product: a navigable small-world hierarchy for each shard.

Vectors are dealt into shards of bounded rows. A shard's index is one row: ids, vectors and, for each
level, the neighbours of each node as one flat array of integers. A query block is searched in every
shard of its dimension, and the shards' results are merged to the ``k`` nearest.

Inner products become distances between points of one sphere by one more coordinate, which gives
every vector of a shard the same length; queries have a zero there. Levels nest: a node reaches level
``l`` with chance ``degree ** -l``. The levels are built from the top. Each takes its nodes in batches
that grow with it; a batch is searched in what stands, from the nodes that the level above names, its
nodes are compared with one another, and each gets diverse neighbours: nearest first, without those
that are nearer to a chosen one. Links go both ways and are chosen anew where they grow too many. All
queries of a block walk together, so every step is a few array operations.

Scores are inner products of the original vectors in double precision. Vectors that are null, zero or
hold a null or non-finite component take no part; vectors of different dimensions are never compared.
Ties go to the smaller vec_id. Rows equal in id and vector count once; a query never returns its own id.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .session import cut, parts_for
from .text import U, splitmix

SHARD_ROWS = 8192
QUERY_BLOCK = 2048
DEGREE, BUILD_BEAM, BEAM = 16, 96, 160
_STEP = 4


def _beam(x: np.ndarray, links: np.ndarray, queries: np.ndarray, entry: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """For each query the best ``size`` nodes met, best first, -1 where there are fewer; and their products."""
    q, rows = len(queries), np.arange(len(queries))[:, None]
    seen = np.zeros((q, len(x)), bool)
    ids = np.full((q, size), -1)
    sims = np.full((q, size), -np.inf, np.float32)
    open_ = np.zeros((q, size), bool)
    width = min(size, entry.shape[1])
    first = np.where(entry[:, :width] >= 0, entry[:, :width], 0)
    got = np.einsum("qnd,qd->qn", x[first], queries)
    got[entry[:, :width] < 0] = -np.inf
    order = np.argsort(-got, 1)
    ids[:, :width], sims[:, :width] = np.take_along_axis(entry[:, :width], order, 1), np.take_along_axis(got, order, 1)
    seen[rows, np.where(ids >= 0, ids, first[:, :1])] = True
    open_ = ids >= 0
    active = np.arange(q)
    while len(active):
        a = active
        rank = np.where(open_[a], np.arange(size), size)
        pick = np.sort(np.partition(rank, min(_STEP, size) - 1, 1)[:, :_STEP], 1)
        some = pick < size
        at = np.where(some, pick, 0)
        nodes = np.where(some, ids[a[:, None], at], -1)
        r, c = np.nonzero(some)
        open_[a[r], pick[r, c]] = False
        near = links[np.where(nodes >= 0, nodes, 0)]
        near[nodes < 0] = -1
        near = near.reshape(len(a), -1)
        valid = near >= 0
        safe = np.where(valid, near, 0)
        valid &= ~seen[a[:, None], safe]
        order = np.argsort(safe, 1, kind="stable")  # a node met twice in one step counts once
        ordered = np.take_along_axis(np.where(valid, safe, -1), order, 1)
        fresh = ordered >= 0
        fresh[:, 1:] &= ordered[:, 1:] != ordered[:, :-1]
        safe = np.where(fresh, ordered, 0)
        r, c = np.nonzero(fresh)
        new = np.full(safe.shape, -np.inf, np.float32)
        if len(r):
            new[r, c] = np.einsum("nd,nd->n", x[safe[r, c]], queries[a[r]])
            seen[a[r], safe[r, c]] = True
        all_s, all_i = np.concatenate((sims[a], new), 1), np.concatenate((ids[a], np.where(fresh, safe, -1)), 1)
        all_o = np.concatenate((open_[a], fresh), 1)
        best = np.argsort(-all_s, 1, kind="stable")[:, :size]
        sims[a], ids[a] = np.take_along_axis(all_s, best, 1), np.take_along_axis(all_i, best, 1)
        open_[a] = np.take_along_axis(all_o, best, 1) & (ids[a] >= 0)
        active = a[open_[a].any(1)]
    return ids, sims


def _diverse(x: np.ndarray, ids: np.ndarray, sims: np.ndarray, degree: int) -> np.ndarray:
    """For rows of candidates, best first, up to ``degree`` that are nearer to the row's node than to a chosen one.

    Places that stay free go to the best of the others.
    """
    out = np.full((len(ids), degree), -1, np.int32)
    for a in range(0, len(ids), 256):
        i, s = ids[a : a + 256], sims[a : a + 256]
        v = x[np.where(i >= 0, i, 0)]
        between = np.matmul(v, v.transpose(0, 2, 1))
        free = i >= 0
        chosen = np.zeros(i.shape, bool)
        closest = np.full(i.shape, -np.inf, np.float32)
        for c in range(i.shape[1]):
            take = free[:, c] & (closest[:, c] < s[:, c]) & (chosen.sum(1) < degree)
            chosen[take, c] = True
            closest[take] = np.maximum(closest[take], between[take, :, c])
        rank = np.where(chosen, 0, np.where(free, 1, 2)) * i.shape[1] + np.arange(i.shape[1])
        order = np.argsort(rank, 1)[:, :degree]
        kept = np.take_along_axis(i, order, 1)
        out[a : a + 256, : kept.shape[1]] = kept
    return out


def _link_back(x: np.ndarray, links: np.ndarray, source: np.ndarray, target: np.ndarray) -> None:
    """Adds links target -> source; where these get too many, the diverse ones stay."""
    degree = links.shape[1]
    sims = np.einsum("nd,nd->n", x[source], x[target])
    order = np.lexsort((-sims, target))
    source, target = source[order], target[order]
    nodes, first, counts = np.unique(target, return_index=True, return_counts=True)
    place = np.arange(len(target)) - np.repeat(first, counts)
    near = place < degree
    incoming = np.full((len(nodes), degree), -1)
    incoming[np.repeat(np.arange(len(nodes)), counts)[near], place[near]] = source[near]
    both = np.concatenate((links[nodes], incoming), 1)
    safe = np.where(both >= 0, both, 0)
    got = np.einsum("nkd,nd->nk", x[safe], x[nodes])
    got[both < 0] = -np.inf
    order = np.argsort(-got, 1, kind="stable")
    links[nodes] = _diverse(x, np.take_along_axis(both, order, 1), np.take_along_axis(got, order, 1), degree)


def _levels(ids: np.ndarray, degree: int) -> np.ndarray:
    u = ((splitmix(ids.astype(U)) >> U(11)) + U(1)) * 2.0**-53
    return np.floor(-np.log(u) / np.log(degree)).astype(int)


def build(ids: np.ndarray, vectors: np.ndarray, degree: int = DEGREE, beam: int = BUILD_BEAM) -> list[tuple[np.ndarray, np.ndarray]]:
    """Levels from the top: the nodes of the level, and over all nodes their neighbours or -1."""
    x = _on_sphere(vectors)
    level = _levels(ids, degree)
    out: list[tuple[np.ndarray, np.ndarray]] = []
    order = np.lexsort((splitmix(ids.astype(U)), -level))
    for height in range(level.max(), -1, -1):
        nodes = order[level[order] >= height]
        wide = degree * 2 if height == 0 else degree
        links = np.full((len(x), wide), -1, np.int32)
        done = 0
        while done < len(nodes):
            batch = nodes[done : done + max(32, min(512, done))]
            inner = x[batch] @ x[batch].T
            np.fill_diagonal(inner, -np.inf)
            near = np.argsort(-inner, 1)[:, : min(beam, len(batch))]
            cand_i, cand_s = batch[near], np.take_along_axis(inner, near, 1)
            cand_i = np.where(np.isfinite(cand_s), cand_i, -1)
            if done:
                entry = _enter(x, out, x[batch]) if out else np.repeat(nodes[None, :1], len(batch), 0)
                found, sims = _beam(x, links, x[batch], entry, beam)
                own = found == batch[:, None]
                found, sims = np.where(own, -1, found), np.where(own, -np.inf, sims)
                cand_i, cand_s = np.concatenate((cand_i, found), 1), np.concatenate((cand_s, sims), 1)
            best = np.argsort(-cand_s, 1, kind="stable")[:, :beam]
            chosen = _diverse(x, np.take_along_axis(cand_i, best, 1), np.take_along_axis(cand_s, best, 1), degree)
            links[batch, : chosen.shape[1]] = chosen
            r, c = np.nonzero(chosen >= 0)
            if len(r):
                _link_back(x, links, batch[r], chosen[r, c].astype(int))
            done += len(batch)
        out.append((nodes, links))
    return out


def _enter(x: np.ndarray, levels: list, queries: np.ndarray, width: int = 4) -> np.ndarray:
    """For each query the nodes to begin with below the given levels."""
    nodes = levels[0][0][:64]
    entry = nodes[np.argsort(-(queries @ x[nodes].T), 1)[:, :width]]
    for _, links in levels:
        entry = _beam(x, links, queries, entry, 2 * width)[0][:, :width]
    return entry


def _on_sphere(vectors: np.ndarray) -> np.ndarray:
    x = vectors.astype(np.float32)
    square = np.einsum("nd,nd->n", x, x, dtype=np.float64)
    return np.c_[x, np.sqrt(np.maximum(square.max(initial=0) - square, 0))].astype(np.float32)


def find(ids: np.ndarray, vectors: np.ndarray, levels: list, queries: np.ndarray, k: int, beam: int = BEAM, own: np.ndarray | None = None):
    """For each query (row, id, score) of its ``k`` best, by exact scores of those met."""
    x = _on_sphere(vectors)
    out = []
    for a in range(0, len(queries), 512):
        q = queries[a : a + 512].astype(np.float64)
        entry = _enter(x, levels[:-1], np.c_[q, np.zeros(len(q))].astype(np.float32)) if len(levels) > 1 else np.repeat(levels[-1][0][None, :1], len(q), 0)
        found, _ = _beam(x, levels[-1][1], np.c_[q, np.zeros(len(q))].astype(np.float32), entry, max(beam, k + 1))
        r, c = np.nonzero(found >= 0)
        node = found[r, c]
        if own is not None:
            other = ids[node] != own[a : a + 512][r]
            r, node = r[other], node[other]
        score = np.einsum("nd,nd->n", vectors[node].astype(np.float64), q[r])
        order = np.lexsort((ids[node], -score, r))
        r, node, score = r[order], node[order], score[order]
        place = np.arange(len(r)) - np.searchsorted(r, r)
        keep = place < k
        out.append((r[keep] + a, ids[node[keep]], score[keep]))
    return tuple(np.concatenate(z) for z in zip(*out, strict=True))


def usable(vector: str) -> Column:
    """Whether a vector can take part: not null, not zero, all components finite."""
    v = F.col(vector)
    finite = F.forall(v, lambda c: c.isNotNull() & ~F.isnan(c) & (F.abs(c) < float("inf")))
    return F.coalesce(v.isNotNull() & finite & F.exists(v, lambda c: c != 0), F.lit(False))


_INDEX = "dim int, shard int, ids binary, vectors binary, tops array<int>, levels array<struct<nodes: binary, links: binary>>"


def _build_shard(table: pa.Table) -> pa.Table:
    dim = table["dim"][0].as_py()
    ids = table["id"].to_numpy()
    order = np.argsort(ids, kind="stable")
    vectors = table["v"].combine_chunks().flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, dim)[order]
    levels = build(ids[order], vectors)
    return pa.table(
        {
            "dim": pa.array([dim], pa.int32()),
            "shard": table["shard"][:1],
            "ids": [ids[order].tobytes()],
            "vectors": [vectors.tobytes()],
            "tops": pa.array([[len(n) for n, _ in levels]], pa.list_(pa.int32())),
            "levels": pa.array([[{"nodes": n.astype(np.int32).tobytes(), "links": x.tobytes()} for n, x in levels]], pa.list_(pa.struct([("nodes", pa.binary()), ("links", pa.binary())]))),
        }
    )


def index(points: DataFrame, shard_rows: int = SHARD_ROWS) -> DataFrame:
    """One row for each shard: the graph over all usable vectors of (id, v). Checkpointed."""
    rows = points.where(usable("v")).select("id", "v", F.size("v").alias("dim")).where(F.col("id").isNotNull()).distinct()
    shards = parts_for(rows.count(), shard_rows)
    dealt = rows.withColumn("shard", F.pmod(F.xxhash64("id"), F.lit(shards)).cast("int"))
    return cut(dealt.groupBy("dim", "shard").applyInArrow(_build_shard, _INDEX))


def nearest(indexed: DataFrame, queries: DataFrame, k: int, beam: int = BEAM, block: int = QUERY_BLOCK) -> DataFrame:
    """(query_id, rank, id, score) of the ``k`` nearest of each query (id, v), other than its own id."""
    rows = queries.where(usable("v")).select("id", F.col("v").cast("array<double>").alias("v"), F.size("v").alias("dim")).where(F.col("id").isNotNull()).distinct()
    blocks = parts_for(rows.count(), block)

    def gather(table: pa.Table) -> pa.Table:
        vectors = table["v"].combine_chunks().flatten().to_numpy(zero_copy_only=False)
        return pa.table({"dim": table["dim"][:1], "q_ids": [table["id"].to_numpy().tobytes()], "q_vectors": [vectors.astype(np.float64).tobytes()]})

    packed = rows.withColumn("block", F.pmod(F.xxhash64(F.lit(1), "id"), F.lit(blocks))).groupBy("dim", "block").applyInArrow(gather, "dim int, q_ids binary, q_vectors binary")
    places = indexed.groupBy("dim").agg(F.collect_set("shard").alias("shards"))  # shard numbers of one dimension
    asked = packed.join(places, "dim").select("dim", F.explode("shards").alias("shard"), "q_ids", "q_vectors")

    def look(source):
        for batch in source:
            for row in batch.to_pylist():
                dim = row["dim"]
                ids, vectors = np.frombuffer(row["ids"], np.int64), np.frombuffer(row["vectors"], np.float64).reshape(-1, dim)
                levels = [(np.frombuffer(x["nodes"], np.int32).astype(int), np.frombuffer(x["links"], np.int32).reshape(len(ids), -1)) for x in row["levels"]]
                own = np.frombuffer(row["q_ids"], np.int64)
                r, found, score = find(ids, vectors, levels, np.frombuffer(row["q_vectors"], np.float64).reshape(-1, dim), k, beam, own)
                yield pa.RecordBatch.from_pydict({"query_id": own[r], "id": found, "score": score})

    met = indexed.join(asked, ["dim", "shard"]).mapInArrow(look, "query_id long, id long, score double")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "id")
    return met.distinct().withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "id", "score")

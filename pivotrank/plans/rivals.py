"""The competing methods as queries: ball trees, graphs, hashing, projections, voters."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import graphs as G
from ..operators import measures as M
from ..operators import projections as J
from ..operators import search as S
from ..operators.ball_tree import BallTree, PermutationTree
from ..sources import workloads as W
from . import methods
from . import sqltext as T
from .methods import rounded, split_of

QUERIES: dict = {}
SQL: dict[str, str] = {}


def register(name, query, sql=None):
    QUERIES[name] = query
    if sql:
        SQL[name] = sql


def balltree_metric_l2(spark, d):
    pts, qs = split_of(spark, d, "embeddings", 50)
    return rounded(BallTree.build(pts, "l2").search(qs, 10))


register("balltree_metric_l2", balltree_metric_l2, methods.SQL["exact_l2"])


def balltree_unpruned_kl(spark, d):
    """With alpha = 0 nothing is pruned, so the answer is exact for any distance."""
    pts, qs = split_of(spark, d, "topics8", 50)
    return rounded(BallTree.build(pts, "kl").search(qs, 10, alpha=(0.0, 0.0), beta=2.0))


register("balltree_unpruned_kl", balltree_unpruned_kl, methods.SQL["exact_kl_left"])


def balltree_poly_kl(spark, d):
    """One row: recall and share of points read, pruned by the polynomial rule."""
    pts, qs = split_of(spark, d, "topics8", 50)
    tree, truth = BallTree.build(pts, "kl"), S.exact_knn(pts, qs, "kl")
    found = M.recall(tree.search(qs, 10, alpha=(2.0, 2.0), beta=2.0), truth)
    return found.select("recall", F.lit(tree.read_points(qs, 10, (2.0, 2.0), 2.0) / (pts.count() * 50)).alias("read"))


register("balltree_poly_kl", balltree_poly_kl)


def permtree(spark, d):
    pts, qs = split_of(spark, d, "embeddings", 50)
    return PermutationTree(pts, "l2", 64).candidates(qs, 100)


register("permtree", permtree, f"WITH {W.split_sql('embeddings', 50)}, {T.pivots(64)}, {T.seen('pts', 'id', 'l2', 'pseen')}, {T.seen('qs', 'qid', 'l2', 'qseen')}, {T.permutation_scores('rho', 64)}, {T.gamma('scores', 100)} SELECT qid, id, score FROM cand")


def graph_exact(spark, d):
    return G.exact_graph(W.embeddings(spark, d), "l2", 10).select("src", "dst", F.round("dist", 6).alias("dist"))


register(
    "graph_exact",
    graph_exact,
    f"WITH pts AS ({W.SQL['embeddings']}) SELECT src, dst, round(dist, 6) AS dist FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY {T.key('dist')}, dst) AS r FROM (SELECT a.id AS src, b.id AS dst, list_distance(a.x, b.x) AS dist FROM pts a, pts b WHERE a.id <> b.id)) WHERE r <= 10",
)


def _graph_recall(edges, exact):
    hit = edges.select("src", "dst").distinct().join(exact.select("src", "dst"), ["src", "dst"]).agg(F.count("*").alias("hits"))
    return hit.crossJoin(exact.agg(F.count("*").alias("n"))).select((F.col("hits") / F.col("n")).alias("graph_recall"))


def graph_nndescent(spark, d):
    pts = W.embeddings(spark, d)
    return _graph_recall(G.nn_descent(pts, "l2", 10, max_iter=8), G.exact_graph(pts, "l2", 10))


register("graph_nndescent", graph_nndescent)


def _graph_search(ef, starts):
    def query(spark, d):
        pts, qs = split_of(spark, d, "embeddings", 50)
        found = G.graph_search(G.exact_graph(pts, "l2", 15).transform(_both_ways), pts, qs, "l2", 10, starts, ef)
        return M.recall(found, S.exact_knn(pts, qs, "l2"))

    return query


def _both_ways(edges):
    return edges.unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "dist")).distinct()


register("graph_search_greedy", _graph_search(1, 5))
register("graph_search_beam", _graph_search(40, 5))


def graph_smallworld(spark, d):
    pts, qs = split_of(spark, d, "embeddings", 50)
    edges = G.small_world(pts, "l2", 10)
    return M.recall(G.graph_search(edges, pts, qs, "l2", 10, 5, 40), S.exact_knn(pts, qs, "l2"))


register("graph_smallworld", graph_smallworld)

# hashing and projections


def _rows_sql(name, matrix, shift=None):
    """A generated matrix as rows of literals."""
    rows = ", ".join(f"({j}, [{', '.join(repr(float(v)) for v in matrix[:, j])}]{'' if shift is None else f', {float(shift[j])!r}'})" for j in range(matrix.shape[1]))
    return f"{name}(j, g{'' if shift is None else ', c'}) AS (VALUES {rows})"


_DIM, _TABLES, _HASHES, _WIDTH, _SIZE = 64, 10, 4, 2.0, 4096


def _multi_probe(pts):
    return J.MultiProbe(pts, _DIM, _TABLES, _HASHES, _WIDTH, _SIZE)


def mplsh_home(spark, d):
    pts, qs = split_of(spark, d, "embeddings", 50)
    return rounded(_multi_probe(pts).search(qs, 10, probes=0))


def _mplsh_sql():
    import numpy as np

    tool = J.MultiProbe.__new__(J.MultiProbe)
    tool.basis = J.gaussian_matrix(_DIM, _TABLES * _HASHES, 19)
    tool.shift = np.array([J.uniform_of(f"c19:{i}") * _WIDTH for i in range(_TABLES * _HASHES)])
    mixers = [int(J.uniform_of(f"m19:{i}") * (1 << 31)) * 2 + 1 for i in range(_HASHES)]
    mixed = "CASE j % {} {} END".format(_HASHES, " ".join(f"WHEN {i} THEN {m}" for i, m in enumerate(mixers)))
    hashed = lambda source, k, name: f"{name} AS MATERIALIZED (SELECT k, j // {_HASHES} AS tbl, ((sum(floor((list_inner_product(x, g) + c) / {_WIDTH})::BIGINT * {mixed}) % {_SIZE} + {_SIZE}) % {_SIZE})::BIGINT AS bucket FROM (SELECT {k} AS k, x FROM {source}), basis GROUP BY k, j // {_HASHES})"
    return f"WITH {W.split_sql('embeddings', 50)}, {_rows_sql('basis', tool.basis, tool.shift)}, {hashed('pts', 'id', 'hp')}, {hashed('qs', 'qid', 'hq')}, cand AS (SELECT DISTINCT b.k AS qid, a.k AS id FROM hp a JOIN hq b USING (tbl, bucket)), {T.refined('cand', 'l2', 10)} {T.RESULT}"


register("mplsh_home", mplsh_home, _mplsh_sql())


def mplsh_l2(spark, d):
    """One row: recall and candidate share with ten more probes in each table."""
    pts, qs = split_of(spark, d, "embeddings", 50)
    tool, truth = _multi_probe(pts), S.exact_knn(pts, qs, "l2")
    found = M.recall(tool.search(qs, 10, probes=10), truth)
    return found.crossJoin(M.candidate_fraction(tool.candidates(qs, 10), 50, pts.count()))


register("mplsh_l2", mplsh_l2)


def _projection(name, dist, dim):
    def query(spark, d):
        pts, qs = split_of(spark, d, "embeddings", 50)
        return rounded(J.RandomProjection(pts, dist, _DIM, dim).search(qs, 10, 100))

    low = f"list_distance(a.y, b.y)" if dist == "l2" else "(1 - list_cosine_similarity(a.y, b.y))"  # noqa: F541
    flat = lambda source, k, name: f"{name} AS MATERIALIZED (SELECT k, list(list_inner_product(x, g) ORDER BY j) AS y FROM (SELECT {k} AS k, x FROM {source}), basis GROUP BY k)"
    register(name, query, f"WITH {W.split_sql('embeddings', 50)}, {_rows_sql('basis', J.gaussian_matrix(_DIM, dim, 17))}, {flat('pts', 'id', 'lp')}, {flat('qs', 'qid', 'lq')}, scores AS (SELECT b.k AS qid, a.k AS id, {T.key(low)} AS score FROM lp a, lq b), {T.gamma('scores', 100)}, {T.refined('cand', dist, 10)} {T.RESULT}")


_projection("random_projection_l2", "l2", 16)
_projection("random_projection_cosine", "cosine", 16)


def random_projection_sparse(spark, d):
    y = J.project_terms(W.terms(spark, d), 8)
    return y.select("id", F.transform("y", lambda v: F.round(v, 4) + 0.0).alias("y"))


register(
    "random_projection_sparse",
    random_projection_sparse,
    f"WITH {methods._TERMS_SQL} SELECT id, [{', '.join(f'''round(sum(w * CASE WHEN md5('s17:{j}:' || term)[1] < '8' THEN 1.0 ELSE -1.0 END), 4) + 0.0''' for j in range(8))}] AS y FROM terms GROUP BY id",
)

# voters


def _median(name, voter, gamma=None):
    def query(spark, d):
        pts, qs = split_of(spark, d, "embeddings", 50)
        return J.MedianRank(pts, "l2", 5, voter, _DIM).candidates(qs, 200)

    if voter == "projection":
        lines = f"{_rows_sql('basis', J.gaussian_matrix(_DIM, 5, 23))}, lp AS MATERIALIZED (SELECT id AS k, j AS v, list_inner_product(x, g) AS y FROM pts, basis), lq AS MATERIALIZED (SELECT qid AS k, j AS v, list_inner_product(x, g) AS y FROM qs, basis)"
    else:
        lines = f"{T.pivots(5, seed=23)}, {T.seen('pts', 'id', 'l2', 'lp0')}, {T.seen('qs', 'qid', 'l2', 'lq0')}, lp AS (SELECT k, pid AS v, d AS y FROM lp0), lq AS (SELECT k, pid AS v, d AS y FROM lq0)"
    register(
        name,
        query,
        f"WITH {W.split_sql('embeddings', 50)}, {lines}, votes AS (SELECT b.k AS qid, a.k AS id, row_number() OVER (PARTITION BY b.k, v ORDER BY {T.key('abs(a.y - b.y)')}, a.k) AS r FROM lp a JOIN lq b USING (v)) SELECT qid, id, list_sort(list(r))[3]::BIGINT AS score FROM votes WHERE r <= 200 GROUP BY qid, id HAVING count(*) >= 3",
    )


_median("median_rank_proj", "projection")
_median("median_rank_pivot", "pivot")

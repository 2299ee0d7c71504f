"""The stored index, expensive distances in the ball tree, more point sets, and experiments over them, as queries.

What is measured rather than determined (recalls of randomised rivals, sizes, tuning) comes as rows
(check, ok): each check names what the paper reports and whether it holds here.
"""

from __future__ import annotations

from uuid import uuid4

from pyspark.sql import functions as F

from ..operators import ball_tree as B
from ..operators import graphs as G
from ..operators import measures as M
from ..operators import permutation_indexes as P
from ..operators import planner
from ..operators import search as S
from ..operators import stored
from ..sources import workloads as W
from ..sources.tables import write_index
from . import sqltext as T
from .methods import SQL as METHODS
from .methods import _exact, _shared_sql, rounded, split_of
from .methods import QUERIES as METHOD_QUERIES
from .rivals import QUERIES as RIVALS
from .studies import QUERIES as STUDIES
from .studies import SQL as STUDY_SQL

QUERIES: dict = {}
SQL: dict[str, str] = {}


def register(name, query, sql=None):
    QUERIES[name] = query
    if sql:
        SQL[name] = sql


def folder(spark) -> str:
    """A new folder for an index, where all executors see it."""
    return f"{G.shared_folder(spark)}/index-{uuid4()}"


def checks(name, query, texts):
    """A query of (check, ok) rows; its SQL expects every check to hold."""
    register(name, query, "SELECT * FROM (VALUES " + ", ".join(f"('{t}', true)" for t in texts) + ") t(check_name, ok)")


def rows(spark, texts, held):
    return spark.createDataFrame([(t, bool(ok)) for t, ok in zip(texts, held, strict=True)], "check_name string, ok boolean")


# the stored index gives what the others give


def _stored(name, points, dist, m, mi, t, q, like):
    def query(spark, d):
        pts, qs = split_of(spark, d, points, q)
        return rounded(stored.build(pts, dist, m, folder(spark), mi=mi).search(qs, 10, t=t))

    register(name, query, METHODS[like])


_stored("stored_l2", "embeddings", "l2", 128, 32, 8, 50, "shared_threshold")
_stored("stored_l1", "descriptors_share", "l1", 64, 16, 6, 20, "shared_l1")
_stored("stored_kl", "topics8", "kl", 128, 32, 12, 50, "shared_kl")


def stored_levenshtein(spark, d):
    """A distance without a matrix form: candidates come from the stored lists, distances from the points."""
    pts, qs = split_of(spark, d, "sequences_drawn", 20)
    return rounded(stored.build(pts, "norm_lev", 32, folder(spark), mi=8).search(qs, 10, t=3, points=pts))


register("stored_levenshtein", stored_levenshtein, f"{_shared_sql('sequences_drawn', 'norm_lev', 32, 8, 3, 20)}, cand AS (SELECT * FROM scores), {T.refined('cand', 'norm_lev', 10)} {T.RESULT}")

# more point sets

W.BUILDERS["topics128"], W.SQL["topics128"] = lambda spark, d: W.topics(spark, d, 128), W._topics_sql(128)
for _name, _points, _dist, _q in (("exact_kl_128", "topics128", "kl", 20), ("exact_js_128", "topics128", "js", 20), ("exact_l2_descriptors", "descriptors", "l2", 20)):
    _exact(_name, _points, _dist, _q)
    register(_name, METHOD_QUERIES.pop(_name), METHODS.pop(_name))


def shared_kl_128(spark, d):
    pts, qs = split_of(spark, d, "topics128", 20)
    return rounded(P.SharedPivots(pts, "kl", 64, mi=16).search(qs, 10, t=6, merge="scan"))


register("shared_kl_128", shared_kl_128, f"{_shared_sql('topics128', 'kl', 64, 16, 6, 20)}, cand AS (SELECT * FROM scores), {T.refined('cand', 'kl', 10)} {T.RESULT}")

# ball tree for expensive distances


def balltree_sqfd(spark, d):
    pts, qs = split_of(spark, d, "signatures", 5)
    return rounded(B.BallTree.build(pts, "sqfd", 10).search(qs, 10))


register("balltree_sqfd", balltree_sqfd, METHODS["exact_sqfd_grid"])

_LEVENSHTEIN = ["ball tree with alpha 1 reaches a recall of 0.85", "alpha 0 gives the exact answer"]


def balltree_levenshtein(spark, d):
    """Edit distance over its length is no metric, so the rule of metrics may lose neighbours, and few are lost."""
    pts, qs = W.split(G.cut(W.sequences_drawn(spark, d)), 20)  # short strings from whole texts: drawn once
    truth, tree = S.exact_knn(pts, qs, "norm_lev").persist(), B.BallTree.build(pts, "norm_lev", 50)
    found = M.recall(tree.search(qs, 10), truth, ties=True).first()["recall"]
    every = tree.search(qs, 10, alpha=(0.0, 0.0)).exceptAll(truth).isEmpty()
    return rows(spark, _LEVENSHTEIN, [found >= 0.85, every])


checks("balltree_levenshtein", balltree_levenshtein, _LEVENSHTEIN)

# sweeps and comparisons


def sweep_m_shared(spark, d):
    """Candidates and hits of the shared-pivot index as the number of pivots rises."""
    pts, qs = split_of(spark, d, "embeddings", 50)
    truth, out = S.exact_knn(pts, qs, "l2").select("qid", "id", F.lit(1).alias("hit")), None
    for m in (32, 64, 128, 256):
        one = P.SharedPivots(pts, "l2", m, mi=16).candidates(qs, t=4, merge="scan").join(truth, ["qid", "id"], "left").agg(F.count("*").alias("candidates"), F.count("hit").alias("hits")).select(F.lit(m).alias("m"), "candidates", "hits")
        out = one if out is None else out.unionByName(one)
    return out


def _swept(rows_of):
    """rows_of: (label SQL, m, mi, t); a shared-pivot search for each."""
    base = f"WITH {W.split_sql('embeddings', 50)}, {T.everything('every')}, {T.refined('every', 'l2', 10, name='truth')}"
    ctes, unions = [], []
    for i, (label, m, mi, t) in enumerate(rows_of):
        ctes += [T.pivots(m, name=f"v{i}"), T.seen("pts", "id", "l2", f"a{i}", piv=f"v{i}"), T.seen("qs", "qid", "l2", f"b{i}", piv=f"v{i}")]
        ctes.append(f"s{i} AS (SELECT b.k AS qid, a.k AS id FROM a{i} a JOIN b{i} b USING (pid) WHERE a.pos <= {mi} AND b.pos <= {mi} GROUP BY b.k, a.k HAVING count(*) >= {t})")
        unions.append(f"SELECT {label}, count(*) AS candidates, count(truth.id) AS hits FROM s{i} LEFT JOIN truth USING (qid, id)")
    return f"{base}, {', '.join(ctes)} {' UNION ALL '.join(unions)}"


register("sweep_m_shared", sweep_m_shared, _swept([(f"{m}::INT AS m", m, 16, 4) for m in (32, 64, 128, 256)]))


def sweep_mi(spark, d):
    """Candidates and hits as the pivots kept of each point rise, a quarter of them asked for."""
    pts, qs = split_of(spark, d, "embeddings", 50)
    truth, out = S.exact_knn(pts, qs, "l2").select("qid", "id", F.lit(1).alias("hit")), None
    for mi in (8, 16, 32, 64):
        one = P.SharedPivots(pts, "l2", 128, mi=mi).candidates(qs, t=mi // 4, merge="scan").join(truth, ["qid", "id"], "left").agg(F.count("*").alias("candidates"), F.count("hit").alias("hits")).select(F.lit(mi).alias("mi"), "candidates", "hits")
        out = one if out is None else out.unionByName(one)
    return out


register("sweep_mi", sweep_mi, _swept([(f"{mi}::INT AS mi", 128, mi, mi // 4) for mi in (8, 16, 32, 64)]))


def cross_check_l1(spark, d):
    """Normalised descriptors under L1: hits, and the share of distances computed, as t rises."""
    pts, qs = split_of(spark, d, "descriptors_share", 20)
    n, truth = pts.count(), S.exact_knn(pts, qs, "l1").select("qid", "id", F.lit(1).alias("hit"))
    shared = P.SharedPivots(pts, "l1", 64, mi=16).scan(qs, 1)
    ts = F.explode(F.array(*[F.lit(t) for t in (2, 4, 6, 8)])).alias("t")
    found = shared.join(F.broadcast(truth), ["qid", "id"], "left").select("shared", "hit", ts).where(F.col("shared") >= F.col("t"))
    return found.groupBy("t").agg(F.count("hit").alias("hits"), ((F.count("*") / 20 + 64) / n).alias("distances"))


register("cross_check_l1", cross_check_l1, f"{_shared_sql('descriptors_share', 'l1', 64, 16, 1, 20)}, {T.everything('every')}, {T.refined('every', 'l1', 10, name='truth')} SELECT t::INT AS t, count(truth.id) AS hits, (count(*) / 20 + 64) / (SELECT count(*) FROM pts) AS distances FROM scores LEFT JOIN truth USING (qid, id), (VALUES (2), (4), (6), (8)) v(t) WHERE 16 - score >= t GROUP BY t")


def bits_against_ranks(spark, d):
    """Hits among 100 candidates, and bytes a point: 256 bits against 128 whole ranks."""
    pts, qs = split_of(spark, d, "embeddings", 50)
    truth, out = S.exact_knn(pts, qs, "l2").select("qid", "id"), None
    for score, m in (("hamming", 256), ("rho", 128)):
        one = P.ExhaustivePermutations(pts, "l2", m, score=score).best(qs, gamma=100).join(truth, ["qid", "id"]).agg(F.count("*").alias("hits")).select(F.lit(score).alias("score"), F.lit(M.permutation_bytes(m, score == "hamming")).alias("bytes"), "hits")
        out = one if out is None else out.unionByName(one)
    return out


def _bits_sql():
    ctes, unions = [], []
    for i, (score, m) in enumerate((("hamming", 256), ("rho", 128))):
        ctes += [T.pivots(m, name=f"v{i}"), T.seen("pts", "id", "l2", f"a{i}", piv=f"v{i}"), T.seen("qs", "qid", "l2", f"b{i}", piv=f"v{i}")]
        ctes.append(T.permutation_scores(score, m, f"s{i}").replace("FROM pseen a JOIN qseen b", f"FROM a{i} a JOIN b{i} b"))
        unions.append(f"SELECT '{score}' AS score, {M.permutation_bytes(m, score == 'hamming')}::INT AS bytes, count(*) AS hits FROM (SELECT qid, id, row_number() OVER (PARTITION BY qid ORDER BY score, id) AS r FROM s{i}) JOIN truth USING (qid, id) WHERE r <= 100")
    return f"WITH {W.split_sql('embeddings', 50)}, {T.everything('every')}, {T.refined('every', 'l2', 10, name='truth')}, {', '.join(ctes)} {' UNION ALL '.join(unions)}"


register("bits_against_ranks", bits_against_ranks, _bits_sql())


def transitivity(spark, d):
    """How often a neighbour's neighbour is a neighbour, in the exact graph of ten nearest."""
    return M.neighbour_transitivity(G.exact_graph(W.embeddings(spark, d), "l2", 10)).select("paths", "closed", F.round("share", 9).alias("share"))


register(
    "neighbour_transitivity",
    transitivity,
    f"""WITH pts AS MATERIALIZED ({W.SQL['embeddings']}), e AS MATERIALIZED (SELECT src, dst FROM (SELECT a.id AS src, b.id AS dst, row_number() OVER (PARTITION BY a.id ORDER BY {T.key('list_distance(a.x, b.x)')}, b.id) AS r FROM pts a JOIN pts b ON a.id <> b.id) WHERE r <= 10),
paths AS (SELECT u.src AS a, v.dst AS c FROM e u JOIN e v ON u.dst = v.src WHERE u.src <> v.dst)
SELECT count(*) AS paths, count(e.src) AS closed, round(count(e.src) / count(*), 9) AS share FROM paths LEFT JOIN e ON e.src = a AND e.dst = c""",
)

register(
    "scatter_spearman",
    lambda spark, d: M.rank_correlation(STUDIES["scatter_l2"](spark, d)),
    f"""WITH s AS ({STUDY_SQL['scatter_l2']}), r AS (SELECT stratum, rank() OVER (PARTITION BY stratum ORDER BY dist) + (count(*) OVER (PARTITION BY stratum, dist) - 1) / 2 AS r,
rank() OVER (PARTITION BY stratum ORDER BY projected) + (count(*) OVER (PARTITION BY stratum, projected) - 1) / 2 AS s FROM s) SELECT stratum, round(corr(r, s), 6) AS spearman FROM r GROUP BY stratum""",
)

# measured

_SIZES = [
    "every stored index takes bytes and seconds",
    "256 bits take less than 128 ranks",
    "shared pivots without positions take less than rank postings with them",
    "the manifest tells the points",
    "an opened index answers as the built one",
]


def index_sizes(spark, d):
    """Bytes and creation of stored indexes over one point set."""
    pts, qs = split_of(spark, d, "embeddings", 50)
    n, at, size, seconds = pts.count(), folder(spark), {}, {}
    frames = {
        "ranks": P.ExhaustivePermutations(pts, "l2", 128).codes,
        "bits": P.ExhaustivePermutations(pts, "l2", 256, score="hamming").codes,
        "postings": P.RankPostings(pts, "l2", 128, mi=32).postings,
        "shared": P.SharedPivots(pts, "l2", 128, mi=32).postings.select("pid", "id"),
        "tree": B.BallTree.build(pts, "l2", 50).assigned(),
    }
    for name, frame in frames.items():
        key = {"ranks": "id", "bits": "id", "tree": "leaf"}.get(name, "pid")
        begun = M.time.perf_counter()
        write_index(frame, f"{at}/{name}", [key], points=n)
        seconds[name], size[name] = M.time.perf_counter() - begun, M.index_bytes(spark, f"{at}/{name}/data")
    built = stored.build(pts, "l2", 128, f"{at}/stored", mi=32)
    size["stored"] = M.index_bytes(spark, built.path)
    opened = stored.StoredSharedPivots(spark, built.path)
    same = opened.search(qs, 10, t=8).exceptAll(built.search(qs, 10, t=8)).isEmpty()
    return rows(spark, _SIZES, [min(size.values()) > 0 and min(seconds.values()) > 0, size["bits"] < size["ranks"], size["shared"] < size["postings"], opened.n == n, same])


checks("index_sizes", index_sizes, _SIZES)

_DESCENT, _BEAM, _WORLD = ["the graph by descent with lists of 20 holds 0.9 of the ten nearest"], ["a beam finds at least what greedy search finds, and 0.9"], ["the small world reaches 0.9"]


def _recall(name, spark, d) -> float:
    return float(RIVALS[name](spark, d).first()[0])


def graph_nndescent_check(spark, d):
    pts = W.embeddings(spark, d)
    exact = G.exact_graph(pts, "l2", 10).select("src", "dst").persist()
    found = exact.join(G.nn_descent(pts, "l2", 20, max_iter=8).select("src", "dst").distinct(), ["src", "dst"]).count()
    return rows(spark, _DESCENT, [found >= 0.9 * exact.count()])


checks("graph_nndescent_check", graph_nndescent_check, _DESCENT)
checks("graph_search_check", lambda spark, d: rows(spark, _BEAM, [_recall("graph_search_beam", spark, d) >= max(0.9, _recall("graph_search_greedy", spark, d))]), _BEAM)
checks("graph_smallworld_check", lambda spark, d: rows(spark, _WORLD, [_recall("graph_smallworld", spark, d) >= 0.9]), _WORLD)

_TUNING = ["the tuned shared pivots reach the recall", "and cost no more than the untuned"]


def tuning_checks(spark, d):
    """Parameters found by the grid give the recall they were tuned for."""
    pts, qs = split_of(spark, d, "embeddings", 50)
    truth, n = S.exact_knn(pts, qs, "l2").persist(), pts.count()
    m, t, share = planner.tune_shared(pts, qs, "l2", grid=(32, 40), mi=16)
    index = P.SharedPivots(pts, "l2", m, mi=16)
    found = M.recall(index.search(qs, 10, t=t, merge="scan"), truth).first()["recall"]
    return rows(spark, _TUNING, [found >= 0.9 - 1e-9, share <= index.candidates(qs, t=1, merge="scan").count() / (50 * n)])


checks("tuning_checks", tuning_checks, _TUNING)

"""Measures and experiments as queries."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import distances as D
from ..operators import measures as M
from ..operators import permutation_indexes as P
from ..operators import projections as J
from ..operators import search as S
from ..operators.pivots import see, select_pivots
from ..sources import workloads as W
from . import sqltext as T
from .methods import SQL as METHODS
from .methods import _postings_scores_sql, _shared_sql, split_of

QUERIES: dict = {}
SQL: dict[str, str] = {}


def register(name, query, sql=None):
    QUERIES[name] = query
    if sql:
        SQL[name] = sql


_BASE = f"WITH {W.split_sql('embeddings', 50)}, {T.pivots(128)}, {T.seen('pts', 'id', 'l2', 'pseen')}, {T.seen('qs', 'qid', 'l2', 'qseen')}, {T.everything('every')}, {T.refined('every', 'l2', 10, name='truth')}"


def recall_by_method(spark, d):
    """Recall at equal numbers of candidates, by method, with a total row for each and for all (rollup)."""
    pts, qs = split_of(spark, d, "embeddings", 50)
    truth, pivots = S.exact_knn(pts, qs, "l2"), select_pivots(pts, 128)
    out = None
    for score in ("rho", "footrule", "hamming", "pivot_l2"):
        scores = P.ExhaustivePermutations(pts, "l2", 128, pivots=pivots, score=score).scores(qs)
        for gamma in (25, 50, 100):
            one = S.top_gamma(scores, gamma, "heap").join(truth.select("qid", "id"), ["qid", "id"]).agg(F.count("*").alias("hits")).select(F.lit(score).alias("method"), F.lit(gamma).alias("gamma"), "hits")
            out = one if out is None else out.unionByName(one)
    return out.rollup("method", "gamma").agg(F.sum("hits").alias("hits"), (F.sum("hits") / (F.count("*") * 500)).alias("recall"))


def _recall_sql():
    parts = []
    for score in ("rho", "footrule", "hamming", "pivot_l2"):
        parts.append(T.permutation_scores(score, 128, f"s_{score}"))
    union = " UNION ALL ".join(f"SELECT '{s}' AS method, {g}::INT AS gamma, count(*) AS hits FROM (SELECT qid, id, row_number() OVER (PARTITION BY qid ORDER BY score, id) AS r FROM s_{s}) JOIN truth USING (qid, id) WHERE r <= {g}" for s in ("rho", "footrule", "hamming", "pivot_l2") for g in (25, 50, 100))
    return f"{_BASE}, {', '.join(parts)} SELECT method, gamma, sum(hits)::BIGINT AS hits, sum(hits)::DOUBLE / (count(*) * 500) AS recall FROM ({union}) GROUP BY ROLLUP (method, gamma)"


register("recall_by_method", recall_by_method, _recall_sql())


def fraction_for_recall(spark, d):
    """The share of candidates for a recall, by number of pivots."""
    pts, qs = split_of(spark, d, "embeddings", 50)
    truth, n, out = S.exact_knn(pts, qs, "l2"), pts.count(), None
    for m in (4, 16, 64, 128):
        one = M.fraction_for_recall(P.ExhaustivePermutations(pts, "l2", m).scores(qs), truth, n).select(F.lit(m).alias("m"), "level", "fraction")
        out = one if out is None else out.unionByName(one)
    return out


def _fraction_sql():
    ctes, unions = [], []
    for m in (4, 16, 64, 128):
        ctes += [T.pivots(m, name=f"v{m}"), T.seen("pts", "id", "l2", f"a{m}", piv=f"v{m}"), T.seen("qs", "qid", "l2", f"b{m}", piv=f"v{m}")]
        ctes.append(f"o{m} AS (SELECT place, row_number() OVER (ORDER BY place) AS nth, count(*) OVER () AS total FROM (SELECT qid, id, row_number() OVER (PARTITION BY qid ORDER BY score, id) AS place FROM (SELECT b.k AS qid, a.k AS id, sum((a.pos - b.pos) * (a.pos - b.pos)) AS score FROM a{m} a JOIN b{m} b USING (pid) GROUP BY ALL)) JOIN truth USING (qid, id))")
        unions.append(f"SELECT {m}::INT AS m, level, place / (SELECT count(*) FROM pts) AS fraction FROM o{m}, (VALUES (0.5::DOUBLE), (0.8), (0.9), (0.95), (1.0)) l(level) WHERE nth = ceil(level * total - 1e-9)")
    return f"WITH {W.split_sql('embeddings', 50)}, {T.everything('every')}, {T.refined('every', 'l2', 10, name='truth')}, {', '.join(ctes)} {' UNION ALL '.join(unions)}"


register("fraction_for_recall", fraction_for_recall, _fraction_sql())


def _scatter(name, points, dist, m):
    """Original and projected distances of 500 pairs: half from all pairs, half from 100 nearest neighbours."""

    def query(spark, d):
        pts, qs = split_of(spark, d, points, 5)
        pivots = select_pivots(pts, m)
        p = see(pts.select("id", "x"), pivots, dist, want=("ord", "rank")).select("id", "rank")
        q = see(qs.select("qid", "x"), pivots, dist, want=("ord", "rank")).select("qid", F.col("rank").alias("qr"))
        asked = F.broadcast(qs.select("qid", F.col("x").alias("q")))
        sampled = pts.select("id", "x").join(asked, F.pmod(F.col("id") * 7 + F.col("qid"), F.lit(8)) == 0)
        uniform = sampled.select(F.lit("all").alias("stratum"), "qid", "id", D.distance(dist)(F.col("x"), F.col("q")).alias("dist"))
        near = S.exact_knn(pts, qs, dist, 100).select(F.lit("near").alias("stratum"), "qid", "id", "dist")
        return uniform.unionByName(near).join(p, "id").join(F.broadcast(q), "qid").select("stratum", "qid", "id", F.round("dist", 6).alias("dist"), D.rho(F.col("rank"), F.col("qr")).alias("projected"))

    every = f"every AS (SELECT qid, id FROM pts, qs), {T.refined('every', dist, 1 << 30, name='ranked')}"
    register(
        name,
        query,
        f"WITH {W.split_sql(points, 5)}, {T.pivots(m)}, {T.seen('pts', 'id', dist, 'pseen')}, {T.seen('qs', 'qid', dist, 'qseen')}, {T.permutation_scores('rho', m)}, {every} SELECT stratum, qid, id, round(dist, 6) AS dist, score AS projected FROM (SELECT 'all' AS stratum, * FROM ranked WHERE (id * 7 + qid) % 8 = 0 UNION ALL SELECT 'near', * FROM ranked WHERE rnk <= 100) JOIN scores USING (qid, id)",
    )


_scatter("scatter_l2", "embeddings", "l2", 64)
_scatter("scatter_kl", "topics8", "kl", 64)


def scatter_monotone(spark, d):
    """How well the projected distance follows the true one, by stratum: Pearson's coefficient."""
    return QUERIES["scatter_l2"](spark, d).groupBy("stratum").agg(F.round(F.corr("dist", "projected"), 6).alias("pearson"), F.count("*").alias("pairs"))


register("scatter_monotone", scatter_monotone, f"SELECT stratum, round(corr(dist, projected), 6) AS pearson, count(*) AS pairs FROM ({SQL['scatter_l2']}) GROUP BY stratum")

_TRIPLES = """few AS MATERIALIZED (SELECT x, i FROM (SELECT x, row_number() OVER (ORDER BY md5(id::VARCHAR), id) AS i FROM pts) WHERE i <= 97),
tri AS MATERIALIZED (SELECT a.x AS a, b.x AS b, q.x AS q FROM few a JOIN few b ON b.i = a.i * 31 % 97 + 1 JOIN few q ON q.i = a.i * 57 % 97 + 1 WHERE a.i <> b.i AND b.i <> q.i AND a.i <> q.i)"""


def _triple(points, spark, d):
    return M.triples(W.BUILDERS[points](spark, d))


for _name, _points, _dist in (("triangle_rate", "sequences", "norm_lev"), ("triangle_rate_l2", "embeddings", "l2"), ("triangle_rate_kl", "topics8", "kl")):
    _e = {k: D.distance(_dist).sql(*k) for k in (("a", "b"), ("a", "q"), ("q", "b"))}
    register(_name, lambda spark, d, p=_points, x=_dist: M.triangle_violations(_triple(p, spark, d), x), f"WITH pts AS MATERIALIZED ({W.SQL[_points]}), {_TRIPLES} SELECT count(*) AS triples, count(*) FILTER ({_e['a', 'b']} > {_e['a', 'q']} + {_e['q', 'b']} + 1e-9) AS violations FROM tri")


def _mu(name, points, dist, f):
    def query(spark, d):
        return M.mu_defect(_triple(points, spark, d), dist).select("triples", F.round("mu", 6).alias("mu"))

    e = {k: f(D.distance(dist).sql(*k)) for k in (("a", "b"), ("q", "a"), ("q", "b"))}
    register(name, query, f"WITH pts AS MATERIALIZED ({W.SQL[points]}), {_TRIPLES} SELECT count(*) AS triples, round(max(abs({e['q', 'a']} - {e['q', 'b']}) / {e['a', 'b']}), 6) AS mu FROM tri WHERE {e['a', 'b']} > 1e-6")


_mu("mu_defect_angular", "embeddings", "cosine", lambda e: f"acos(greatest(-1.0, least(1.0, 1 - {e})))")
_mu("mu_defect_sqrt_js", "topics8", "js", lambda e: f"sqrt(greatest({e}, 0.0))")
_mu("mu_defect_sqrt_kl", "topics8", "kl", lambda e: f"sqrt(greatest({e}, 0.0))")


# the same over all points; the names above stay, as their SQL is fixed to 97 points
_ALL_TRIPLES = """placed AS MATERIALIZED (SELECT x, row_number() OVER (ORDER BY md5(id::VARCHAR), id) AS i, count(*) OVER () AS n FROM pts),
tri AS MATERIALIZED (SELECT a.x AS a, b.x AS b, q.x AS q FROM placed a JOIN placed b ON b.i = a.i * 31 % a.n + 1 JOIN placed q ON q.i = a.i * 57 % a.n + 1 WHERE a.i <> b.i AND b.i <> q.i AND a.i <> q.i)"""

for _name, _points, _dist in (("triangle_rate", "sequences_drawn", "norm_lev"), ("triangle_rate_l2", "embeddings", "l2"), ("triangle_rate_kl", "topics8", "kl")):
    register(f"{_name}_all", lambda spark, d, p=_points, x=_dist: M.triangle_violations(M.all_triples(W.BUILDERS[p](spark, d)), x), SQL[_name].replace(_TRIPLES, _ALL_TRIPLES).replace(W.SQL["sequences"], W.SQL["sequences_drawn"]))
for _name, _points, _dist in (("mu_defect_angular", "embeddings", "cosine"), ("mu_defect_sqrt_js", "topics8", "js"), ("mu_defect_sqrt_kl", "topics8", "kl")):
    register(f"{_name}_all", lambda spark, d, p=_points, x=_dist: M.mu_defect(M.all_triples(W.BUILDERS[p](spark, d)), x).select("triples", F.round("mu", 6).alias("mu")), SQL[_name].replace(_TRIPLES, _ALL_TRIPLES))


def counterexample_1d(spark, d):
    """In this space 40 is nearest to 0 although 0 and 1 are near each other on the line: d(0, 1) against d(0, 40)."""
    pts = W.line(spark, d).where("id < 0").select(F.col("id").alias("b"), F.col("x").alias("y"))
    zero = pts.where("b = -1").select(F.col("b").alias("a"), F.col("y").alias("x"))
    return zero.crossJoin(pts.where("b <> -1")).select("a", "b", F.round(D.exp_decay(F.col("x"), F.col("y")), 9).alias("dist"))


register("counterexample_1d", counterexample_1d, f"WITH pts AS ({W.SQL['line']}) SELECT a.id AS a, b.id AS b, round({D.distance('exp_decay').sql('a.x', 'b.x')}, 9) AS dist FROM pts a, pts b WHERE a.id = -1 AND b.id IN (-2, -3)")


def perm_bytes(spark, d):
    """Bytes of a permutation, and of those of all embeddings, whole and binarised."""
    rows = [(m, M.permutation_bytes(m), M.permutation_bytes(m, True)) for m in (64, 128, 256, 512, 1024)]
    sizes = F.broadcast(spark.createDataFrame(rows, "m int, whole_bytes int, binary_bytes int"))
    all_of = lambda c: (F.count("id") * F.col(c)).alias(f"all_{c}")
    return W.embeddings(spark, d).select("id").crossJoin(sizes).groupBy("m", "whole_bytes", "binary_bytes").agg(all_of("whole_bytes"), all_of("binary_bytes"))


register("perm_bytes", perm_bytes, f"SELECT m::INT AS m, (4 * m)::INT AS whole_bytes, (m / 8)::INT AS binary_bytes, count(*) * (4 * m) AS all_whole_bytes, count(*) * (m // 8) AS all_binary_bytes FROM ({W.SQL['embeddings']}), (VALUES (64), (128), (256), (512), (1024)) t(m) GROUP BY m")


def index_cost_model(spark, d):
    n = W.lineitems(spark, d).count()
    rows = [(m, float(M.index_cost(n, m, 50)["pivots"]), round(M.index_cost(n, m, 50)["ball_tree"], 3)) for m in (128, 500, 2000)]
    return spark.createDataFrame(rows, "m int, pivots double, ball_tree double")


register("index_cost_model", index_cost_model, "SELECT m::INT AS m, (n * m)::DOUBLE AS pivots, round(n * log2(n / 50), 3) AS ball_tree FROM (SELECT count(*) AS n FROM lineitem), (VALUES (128), (500), (2000)) t(m)")


def split_protocol(spark, d):
    """Recall of the shared-pivot index over five splits, then its mean and deviation (split -1)."""
    out = None
    for number in range(5):
        pts, qs = W.split(W.embeddings(spark, d), 50, number)
        hits = P.SharedPivots(pts, "l2", 64, mi=16).candidates(qs, t=5).join(S.exact_knn(pts, qs, "l2").select("qid", "id"), ["qid", "id"])
        one = hits.agg((F.count("*") / 500).alias("recall")).select(F.lit(number).alias("split"), "recall")
        out = one if out is None else out.unionByName(one)
    both = out.agg(F.avg("recall").alias("recall"), F.stddev("recall").alias("deviation")).select(F.lit(-1).alias("split"), F.round("recall", 9).alias("recall"), F.round("deviation", 9).alias("deviation"))
    return out.withColumn("deviation", F.lit(None).cast("double")).unionByName(both)


def _protocol_sql():
    ctes, unions = [], []
    for s in range(5):
        inner = f"WITH {W.split_sql('embeddings', 50, s)}, {T.pivots(64)}, {T.seen('pts', 'id', 'l2', 'pseen')}, {T.seen('qs', 'qid', 'l2', 'qseen')}, scores AS (SELECT b.k AS qid, a.k AS id FROM pseen a JOIN qseen b USING (pid) WHERE a.pos <= 16 AND b.pos <= 16 GROUP BY b.k, a.k HAVING count(*) >= 5), {T.everything('every')}, {T.refined('every', 'l2', 10, name='truth')} SELECT {s}::INT AS split, count(*)::DOUBLE / 500 AS recall FROM scores JOIN truth USING (qid, id)"
        ctes.append(f"r{s} AS ({inner})")
        unions.append(f"SELECT * FROM r{s}")
    return f"WITH {', '.join(ctes)}, everyone AS ({' UNION ALL '.join(unions)}) SELECT split, recall, NULL::DOUBLE AS deviation FROM everyone UNION ALL SELECT -1, round(avg(recall), 9), round(stddev(recall), 9) FROM everyone"


register("split_protocol", split_protocol, _protocol_sql())


def sweep_t(spark, d):
    """Hits and candidates of the shared-pivot index as t rises."""
    pts, qs = split_of(spark, d, "embeddings", 50)
    shared = P.SharedPivots(pts, "l2", 128, mi=32).shared(qs)
    truth = S.exact_knn(pts, qs, "l2").select("qid", "id", F.lit(1).alias("true"))
    ts = F.explode(F.array(*[F.lit(t) for t in (1, 2, 4, 8, 12, 16)])).alias("t")
    return shared.join(F.broadcast(truth), ["qid", "id"], "left").select("shared", "true", ts).where(F.col("shared") >= F.col("t")).groupBy("t").agg(F.count("*").alias("candidates"), F.count("true").alias("hits"))


register("sweep_t", sweep_t, f"{_shared_sql('embeddings', 'l2', 128, 32, 1)}, {T.everything('every')}, {T.refined('every', 'l2', 10, name='truth')} SELECT t::INT AS t, count(*) AS candidates, count(truth.id) AS hits FROM scores LEFT JOIN truth USING (qid, id), (VALUES (1), (2), (4), (8), (12), (16)) v(t) WHERE 32 - score >= t GROUP BY t")


def sweep_m(spark, d):
    """Hits among 100 candidates by rho as the number of pivots rises."""
    pts, qs = split_of(spark, d, "embeddings", 50)
    truth, out = S.exact_knn(pts, qs, "l2").select("qid", "id"), None
    for m in (8, 32, 128):
        one = P.ExhaustivePermutations(pts, "l2", m).candidates(qs, gamma=100).join(truth, ["qid", "id"]).agg(F.count("*").alias("hits")).select(F.lit(m).alias("m"), "hits")
        out = one if out is None else out.unionByName(one)
    return out


def _sweep_m_sql():
    ctes, unions = [], []
    for m in (8, 32, 128):
        ctes += [T.pivots(m, name=f"v{m}"), T.seen("pts", "id", "l2", f"a{m}", piv=f"v{m}"), T.seen("qs", "qid", "l2", f"b{m}", piv=f"v{m}")]
        unions.append(f"SELECT {m}::INT AS m, count(*) AS hits FROM (SELECT qid, id, row_number() OVER (PARTITION BY qid ORDER BY score, id) AS r FROM (SELECT b.k AS qid, a.k AS id, sum((a.pos - b.pos) * (a.pos - b.pos)) AS score FROM a{m} a JOIN b{m} b USING (pid) GROUP BY ALL)) JOIN truth USING (qid, id) WHERE r <= 100")
    return f"WITH {W.split_sql('embeddings', 50)}, {T.everything('every')}, {T.refined('every', 'l2', 10, name='truth')}, {', '.join(ctes)} {' UNION ALL '.join(unions)}"


register("sweep_m", sweep_m, _sweep_m_sql())


def window_recall(spark, d):
    """Hits met up to each place of the candidates' order, over all queries: a running sum."""
    from pyspark.sql import Window

    pts, qs = split_of(spark, d, "embeddings", 50)
    truth = S.exact_knn(pts, qs, "l2").select("qid", "id", F.lit(1).alias("hit"))
    w = Window.partitionBy("qid").orderBy("score", "id")
    placed = P.ExhaustivePermutations(pts, "l2", 64).scores(qs).withColumn("place", F.row_number().over(w)).where("place <= 100")
    by = placed.join(F.broadcast(truth), ["qid", "id"], "left").groupBy("place").agg(F.count("hit").alias("n"))
    return by.select(F.col("place").cast("long").alias("place"), F.sum("n").over(Window.orderBy("place").rowsBetween(Window.unboundedPreceding, 0)).alias("hits"))


register("window_recall", window_recall, f"WITH {W.split_sql('embeddings', 50)}, {T.pivots(64)}, {T.seen('pts', 'id', 'l2', 'pseen')}, {T.seen('qs', 'qid', 'l2', 'qseen')}, {T.permutation_scores('rho', 64)}, {T.everything('every')}, {T.refined('every', 'l2', 10, name='truth')} SELECT place, sum(n) OVER (ORDER BY place)::BIGINT AS hits FROM (SELECT place, count(truth.id) AS n FROM (SELECT qid, id, row_number() OVER (PARTITION BY qid ORDER BY score, id) AS place FROM scores) LEFT JOIN truth USING (qid, id) WHERE place <= 100 GROUP BY place)")


def left_right_kl(spark, d):
    """How many of the ten nearest agree between left and right queries."""
    pts, qs = split_of(spark, d, "topics8", 50)
    left, right = (S.exact_knn(pts, qs, "kl", side=s).select("qid", "id") for s in ("left", "right"))
    return left.intersect(right).agg(F.count("*").alias("agree"))


register("left_right_kl", left_right_kl, f"SELECT count(*) AS agree FROM (SELECT qid, id FROM ({METHODS['exact_kl_left']}) INTERSECT SELECT qid, id FROM ({METHODS['exact_kl_right']}))")


def dataset_summary(spark, d, sequences="sequences"):
    """Points and components of each point set."""
    size = {"embeddings": F.size("x"), "topics8": F.size("x.p"), sequences: F.length("x"), "signatures": F.size("x")}
    out = None
    for name, e in size.items():
        one = W.BUILDERS[name](spark, d).agg(F.count("*").alias("points"), F.max(e).cast("long").alias("most"), F.round(F.avg(e), 6).alias("mean")).select(F.lit(name).alias("points_of"), "points", "most", "mean")
        out = one if out is None else out.unionByName(one)
    return out


register("dataset_summary", dataset_summary, " UNION ALL ".join(f"SELECT '{n}' AS points_of, count(*) AS points, max({e})::BIGINT AS most, round(avg({e}), 6) AS mean FROM ({W.SQL[n]})" for n, e in (("embeddings", "len(x)"), ("topics8", "len(x.p)"), ("sequences", "length(x)"), ("signatures", "len(x)"))))


register("dataset_summary_drawn", lambda spark, d: dataset_summary(spark, d, "sequences_drawn"), SQL["dataset_summary"].replace("'sequences'", "'sequences_drawn'").replace(W.SQL["sequences"], W.SQL["sequences_drawn"]))


def efficiency(spark, d):
    """Recall and share of points whose distance is computed, by six filters on one point set, at the settings of the other queries."""
    pts, qs = split_of(spark, d, "embeddings", 50)
    truth, n, out = S.exact_knn(pts, qs, "l2").select("qid", "id"), pts.count(), None
    filters = {
        "shared_pivots": P.SharedPivots(pts, "l2", 128, mi=32).candidates(qs, t=8),
        "exhaustive": P.ExhaustivePermutations(pts, "l2", 128).candidates(qs, gamma=100),
        "rank_postings": P.RankPostings(pts, "l2", 128, mi=32).candidates(qs, gamma=100, ms=16),
        "prefix_copies": P.PrefixIndex(pts, "l2", 16, 4, 4).candidates(qs, gamma=50),
        "median_rank": J.MedianRank(pts, "l2", 5, "projection", 64).candidates(qs, 200),
        "projection": J.RandomProjection(pts, "l2", 64, 16).candidates(qs, 100),
    }
    for name, found in filters.items():
        one = found.select("qid", "id").join(truth.withColumn("hit", F.lit(1)), ["qid", "id"], "left").agg((F.count("hit") / 500).alias("recall"), (F.count("*") / (50 * n)).alias("fraction")).select(F.lit(name).alias("method"), "recall", "fraction")
        out = one if out is None else out.unionByName(one)
    return out


register("efficiency", efficiency)
register("postings_scores_truncated", lambda spark, d: P.RankPostings(split_of(spark, d, "embeddings", 50)[0], "l2", 128, mi=32).scores(split_of(spark, d, "embeddings", 50)[1], 16), f"{_postings_scores_sql(128, 32, 16, 'footrule')} SELECT * FROM scores")

"""Exact search, permutations and the permutation indexes, as queries with SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import distances as D
from ..operators import permutation_indexes as P
from ..operators import search as S
from ..operators.pivots import see, select_pivot_copies, select_pivots
from ..sources import workloads as W
from . import sqltext as T

QUERIES: dict = {}
SQL: dict[str, str] = {}


def register(name, query, sql=None):
    QUERIES[name] = query
    if sql:
        SQL[name] = sql


def rounded(result):
    return result.select("qid", "id", (F.round("dist", 6) + 0.0).alias("dist"), F.col("rnk").cast("int").alias("rnk"))


def split_of(spark, d, points, q):
    return W.split(W.BUILDERS[points](spark, d), q)


def _exact(name, points, dist, q=50, k=10, side="left"):
    def query(spark, d):
        pts, qs = split_of(spark, d, points, q)
        return rounded(S.exact_knn(pts, qs, dist, k, side))

    register(name, query, f"WITH {W.split_sql(points, q)}, {T.everything()}, {T.refined('cand', dist, k, side)} {T.RESULT}")


_exact("exact_l2", "embeddings", "l2")
_exact("exact_cosine_dense", "embeddings", "cosine")
_exact("exact_l1", "descriptors_share", "l1", q=20)
_exact("exact_kl_left", "topics8", "kl")
_exact("exact_kl_right", "topics8", "kl", side="right")
_exact("exact_js", "topics8", "js")
_exact("exact_levenshtein", "sequences", "norm_lev", q=20)
_exact("exact_levenshtein_drawn", "sequences_drawn", "norm_lev", q=20)
_exact("exact_sqfd_grid", "signatures", "sqfd", q=5)


def exact_range_l2(spark, d):
    pts, qs = split_of(spark, d, "embeddings", 50)
    return S.exact_knn(pts, qs, "l2", within=1.2).select("qid", "id", F.round("dist", 6).alias("dist"))


register("exact_range_l2", exact_range_l2, f"WITH {W.split_sql('embeddings', 50)} SELECT qid, id, round(list_distance(pts.x, qs.x), 6) AS dist FROM pts, qs WHERE list_distance(pts.x, qs.x) <= 1.2")


def exact_cosine_sparse(spark, d):
    terms = W.terms(spark, d)
    asked = terms.select("id").distinct().orderBy(F.md5(F.concat(F.lit("split0:"), F.col("id").cast("string")).cast("binary")), "id").limit(20)
    mine = F.broadcast(asked.select(F.col("id").alias("qid")))
    q = terms.join(mine, F.col("id") == F.col("qid")).select("qid", "term", "w")
    return rounded(S.exact_sparse_cosine(terms.join(mine, F.col("id") == F.col("qid"), "left_anti"), q, 10))


_TERMS_SQL = f"""tf AS MATERIALIZED (SELECT doc_id AS id, term, count(*) AS tf FROM (SELECT doc_id, unnest({W._TOKENS_SQL}) AS term FROM documents) GROUP BY ALL),
terms AS MATERIALIZED (SELECT * FROM (SELECT id, term, tf * ln((SELECT count(*) FROM documents) / df) AS w FROM tf JOIN (SELECT term, count(*) AS df FROM tf GROUP BY term) USING (term)) WHERE w > 0),
asked AS MATERIALIZED (SELECT id AS qid FROM (SELECT DISTINCT id FROM terms) ORDER BY md5('split0:' || id), id LIMIT 20),
norms AS (SELECT id, sqrt(sum(w * w)) AS n FROM terms GROUP BY id)"""
register(
    "exact_cosine_sparse",
    exact_cosine_sparse,
    f"""WITH {_TERMS_SQL}, dots AS (SELECT a.id AS qid, b.id, sum(a.w * b.w) AS dot FROM terms a JOIN terms b USING (term) WHERE a.id IN (SELECT qid FROM asked) AND b.id NOT IN (SELECT qid FROM asked) GROUP BY ALL),
res AS (SELECT * FROM (SELECT qid, id, dist, row_number() OVER (PARTITION BY qid ORDER BY {T.key('dist')}, id) AS rnk FROM (SELECT qid, d.id, 1 - dot / (a.n * b.n) AS dist FROM dots d JOIN norms a ON a.id = d.qid JOIN norms b ON b.id = d.id)) WHERE rnk <= 10) {T.RESULT}""",
)

# pivots and permutations


def pivots(spark, d):
    out = None
    for copy, held in enumerate(select_pivot_copies(W.embeddings(spark, d), 32, 3)):
        one = held.frame.select(F.lit(copy).alias("copy"), "pid", "id")
        out = one if out is None else out.unionByName(one)
    return out


register("pivots", pivots, f"WITH pts AS ({W.SQL['embeddings']}), {', '.join(T.pivots(32, copy=c, name=f'p{c}') for c in range(3))} " + " UNION ALL ".join(f"SELECT {c}::INT AS copy, pid, id FROM p{c}" for c in range(3)))


def _seen(want, backend="auto", mi=None):
    def query(spark, d):
        pts = W.embeddings(spark, d)
        return see(pts, select_pivots(pts, 64), "l2", mi=mi, want=(want,), backend=backend).select("id", want)

    return query


_SEEN = f"WITH pts AS ({W.SQL['embeddings']}), {T.pivots(64)}, {T.seen('pts', 'id', 'l2', 'pseen')} "
_RANKS = "SELECT k AS id, list(pos ORDER BY pid) AS rank FROM pseen GROUP BY k"
register("permutation_rank", lambda spark, d: _seen("rank")(spark, d).select("id", F.col("rank").cast("array<long>").alias("rank")), _SEEN + _RANKS)
register("permutation_rank_native", lambda spark, d: _seen("rank", "native")(spark, d).select("id", F.col("rank").cast("array<long>").alias("rank")), _SEEN + _RANKS)
register("permutation_order", lambda spark, d: _seen("ord", mi=16)(spark, d).select("id", F.col("ord").cast("array<long>").alias("ord")), _SEEN + "SELECT k AS id, list(pid ORDER BY pos) FILTER (pos <= 16) AS ord FROM pseen GROUP BY k")
register("pivot_distance_vec", lambda spark, d: _seen("pd")(spark, d).select("id", F.transform("pd", lambda v: F.round(v, 6)).alias("pd")), _SEEN + "SELECT k AS id, list(round(d, 6) ORDER BY pid) AS pd FROM pseen GROUP BY k")


def binarised_bits(spark, d):
    return _seen("rank")(spark, d).select("id", D.pack_bits(F.col("rank"), 64)[0].alias("bits"), F.bit_count(D.pack_bits(F.col("rank"), 64)[0]).cast("long").alias("ones"))


register("binarised_bits", binarised_bits, _SEEN + "SELECT k AS id, sum(CASE WHEN pos < 33 THEN 0::HUGEINT WHEN pid = 64 THEN -9223372036854775808::HUGEINT ELSE (1::HUGEINT << (pid - 1)::INT) END)::BIGINT AS bits, count(*) FILTER (pos >= 33)::BIGINT AS ones FROM pseen GROUP BY k")

def toy_example(spark, d):
    """The worked example's measures, with its four pivots and bits from rank 3 on, of all embeddings against one."""
    pts, qs = split_of(spark, d, "embeddings", 1)
    held = select_pivots(pts, 4)
    asked = see(qs, held, "l2", want=("rank",)).select(F.col("rank").cast("array<int>").alias("q"))
    seen = see(pts, held, "l2", want=("rank",)).select(F.col("id").alias("point"), F.col("rank").cast("array<int>").alias("rank")).crossJoin(F.broadcast(asked))
    return seen.select("point", D.footrule(F.col("rank"), F.col("q")).alias("footrule"), D.rho(F.col("rank"), F.col("q")).alias("rho"), D.hamming(D.pack_bits(F.col("rank"), 4, 3), D.pack_bits(F.col("q"), 4, 3)).alias("hamming"))


_TOY_SEEN = f"WITH {W.split_sql('embeddings', 1)}, {T.pivots(4)}, {T.seen('pts', 'id', 'l2', 'pseen')}, {T.seen('qs', 'qid', 'l2', 'qseen')} "
register("toy_example", toy_example, _TOY_SEEN + "SELECT a.k AS point, sum(abs(a.pos - b.pos))::BIGINT AS footrule, sum((a.pos - b.pos) * (a.pos - b.pos))::BIGINT AS rho, count(*) FILTER ((a.pos >= 3) <> (b.pos >= 3))::BIGINT AS hamming FROM pseen a JOIN qseen b USING (pid) GROUP BY a.k")

# exhaustive comparison


def _share(points, part):
    return f"(SELECT ceil({part} * count(*) - 1e-9) FROM {points})"


def _exhaustive(name, points, dist, score, m, gamma, q=50, how="counting", fast=False, threshold=None):
    def query(spark, d):
        pts, qs = split_of(spark, d, points, q)
        index = P.ExhaustivePermutations(pts, dist, m, score=score, threshold=threshold)
        if fast:
            return rounded(S.refine(index.best(qs, gamma, 10), pts, qs, dist, 10))
        return rounded(index.search(qs, 10, gamma=gamma, how=how))

    n = gamma if isinstance(gamma, int) else f"greatest(10, {_share('pts', gamma)})"
    register(name, query, f"WITH {W.split_sql(points, q)}, {T.pivots(m)}, {T.seen('pts', 'id', dist, 'pseen')}, {T.seen('qs', 'qid', dist, 'qseen')}, {T.permutation_scores(score, m, limit=threshold)}, {T.gamma('scores', n)}, {T.refined('cand', dist, 10)} {T.RESULT}")


_exhaustive("perm_rho", "embeddings", "l2", "rho", 128, 100)
_exhaustive("perm_rho_scan", "embeddings", "l2", "rho", 128, 100, fast=True)
_exhaustive("perm_footrule", "embeddings", "l2", "footrule", 128, 100)
_exhaustive("perm_hamming", "embeddings", "l2", "hamming", 128, 100)
_exhaustive("perm_pivot_l2", "embeddings", "l2", "pivot_l2", 128, 100, how="heap")
_exhaustive("perm_kl", "topics8", "kl", "rho", 64, 0.1)
_exhaustive("perm_js", "topics8", "js", "rho", 64, 0.1)
_exhaustive("perm_levenshtein_bits", "sequences", "norm_lev", "hamming", 128, 0.1, q=20)
_exhaustive("perm_levenshtein_bits_drawn", "sequences_drawn", "norm_lev", "hamming", 128, 0.1, q=20)
_exhaustive("perm_sqfd_bits", "signatures", "sqfd", "hamming", 16, 0.2, q=5)


def perm_counting_select(spark, d):
    pts, qs = split_of(spark, d, "embeddings", 50)
    return P.ExhaustivePermutations(pts, "l2", 128).candidates(qs, gamma=100, how="counting").select("qid", "id", "score")


register("perm_counting_select", perm_counting_select, f"WITH {W.split_sql('embeddings', 50)}, {T.pivots(128)}, {T.seen('pts', 'id', 'l2', 'pseen')}, {T.seen('qs', 'qid', 'l2', 'qseen')}, {T.permutation_scores('rho', 128)}, {T.gamma('scores', 100)} SELECT qid, id, score FROM cand")

# prefix index


def _prefix_sql(copies, symbols, length=4, m=16, gamma=50, q=50, min_length=0):
    ctes, parts = [W.split_sql("embeddings", q)], []
    for c in range(copies):
        order = "pid ORDER BY pos" if symbols == "order" else "pos ORDER BY pid"
        ctes += [T.pivots(m, copy=c, name=f"piv{c}"), T.seen("pts", "id", "l2", f"ps{c}", piv=f"piv{c}"), T.seen("qs", "qid", "l2", f"qs{c}", piv=f"piv{c}")]
        for s in ("ps", "qs"):
            ctes.append(f"{s}x{c} AS MATERIALIZED (SELECT k, l, s[1:l] AS pre FROM (SELECT k, list({order}) AS s FROM {s}{c} GROUP BY k), range({length + 1}) r(l))")
        ctes.append(f"len{c} AS (SELECT a.k, coalesce(max(a.l) FILTER (n >= {gamma}), {min_length}) AS l FROM qsx{c} a LEFT JOIN (SELECT l, pre, count(*) AS n FROM psx{c} GROUP BY ALL) b ON a.l = b.l AND a.pre = b.pre WHERE a.l >= {min_length} GROUP BY a.k)")
        parts.append(f"SELECT a.k AS qid, b.k AS id, {length} - a.l AS score FROM qsx{c} a JOIN len{c} c ON a.k = c.k AND a.l = c.l JOIN psx{c} b ON a.l = b.l AND a.pre = b.pre")
    return f"WITH {', '.join(ctes)}, cand AS MATERIALIZED (SELECT qid, id, min(score)::BIGINT AS score FROM ({' UNION ALL '.join(parts)}) GROUP BY qid, id)"


def _prefix(name, copies, symbols="order"):
    def query(spark, d):
        pts, qs = split_of(spark, d, "embeddings", 50)
        return rounded(P.PrefixIndex(pts, "l2", 16, 4, copies, symbols).search(qs, 10, gamma=50))

    register(name, query, f"{_prefix_sql(copies, symbols)}, {T.refined('cand', 'l2', 10)} {T.RESULT}")


_prefix("prefix_single", 1)
_prefix("prefix_copies", 4)
_prefix("prefix_rank_symbols", 1, "rank")


def prefix_fallback(spark, d):
    pts, qs = split_of(spark, d, "embeddings", 50)
    return P.PrefixIndex(pts, "l2", 16, 4).candidates(qs, gamma=50).groupBy("qid").agg(F.max("score").alias("shortened"), F.count("*").alias("candidates"))


register("prefix_fallback", prefix_fallback, f"{_prefix_sql(1, 'order')} SELECT qid, max(score) AS shortened, count(*) AS candidates FROM cand GROUP BY qid")

# rank postings


def _postings_scores_sql(m, mi, ms, score, max_diff=None):
    power = {"footrule": 1, "rho": 2}[score]
    diff = "abs(a.pos - b.pos)" if power == 1 else "(a.pos - b.pos) * (a.pos - b.pos)"
    whole = ms == mi == m and max_diff is None
    total = f"sum({diff})" if whole else f"{ms * m**power} - sum({m**power} - {diff})"
    near = "" if max_diff is None else f" AND abs(a.pos - b.pos) <= {max_diff}"
    return f"WITH {W.split_sql('embeddings', 50)}, {T.pivots(m)}, {T.seen('pts', 'id', 'l2', 'pseen')}, {T.seen('qs', 'qid', 'l2', 'qseen')}, scores AS MATERIALIZED (SELECT b.k AS qid, a.k AS id, ({total})::BIGINT AS score FROM pseen a JOIN qseen b USING (pid) WHERE a.pos <= {mi} AND b.pos <= {ms}{near} GROUP BY b.k, a.k)"


def _postings(name, m, mi, ms, score, gamma, max_diff=None):
    def query(spark, d):
        pts, qs = split_of(spark, d, "embeddings", 50)
        return rounded(P.RankPostings(pts, "l2", m, mi=mi).search(qs, 10, ms=ms, score=score, gamma=gamma, max_diff=max_diff))

    register(name, query, f"{_postings_scores_sql(m, mi, ms, score, max_diff)}, {T.gamma('scores', gamma)}, {T.refined('cand', 'l2', 10)} {T.RESULT}")


_postings("postings_full_rho", 32, 32, 32, "rho", 100)
_postings("postings_full_footrule", 32, 32, 32, "footrule", 100)
_postings("postings_truncated", 128, 32, 16, "footrule", 100)
_postings("postings_truncated_rho", 128, 32, 16, "rho", 100)
_postings("postings_maxdiff", 128, 32, 16, "footrule", 100, 8)


def postings_read(spark, d):
    pts, qs = split_of(spark, d, "embeddings", 50)
    return P.RankPostings(pts, "l2", 128, mi=32).read_counts(qs, 16, 8)


register("postings_read", postings_read, f"{_postings_scores_sql(128, 32, 16, 'footrule', 8)} SELECT b.k AS qid, count(DISTINCT pid) AS lists, count(*) AS postings FROM pseen a JOIN qseen b USING (pid) WHERE a.pos <= 32 AND b.pos <= 16 AND abs(a.pos - b.pos) <= 8 GROUP BY b.k")


def postings_toy(spark, d):
    """The worked example's accumulators, two of four pivots of each point in the lists, over all embeddings."""
    pts, qs = split_of(spark, d, "embeddings", 1)
    return P.RankPostings(pts, "l2", 4, mi=2).scores(qs, 2, "footrule").select(F.col("id").alias("point"), "score")


register("postings_toy", postings_toy, _TOY_SEEN + "SELECT a.k AS point, (8 - sum(4 - abs(a.pos - b.pos)))::BIGINT AS score FROM pseen a JOIN qseen b USING (pid) WHERE a.pos <= 2 AND b.pos <= 2 GROUP BY a.k")

# shared pivots


def _shared_sql(points, dist, m, mi, t, q=50):
    return f"WITH {W.split_sql(points, q)}, {T.pivots(m)}, {T.seen('pts', 'id', dist, 'pseen')}, {T.seen('qs', 'qid', dist, 'qseen')}, scores AS MATERIALIZED (SELECT b.k AS qid, a.k AS id, ({mi} - count(*))::BIGINT AS score FROM pseen a JOIN qseen b USING (pid) WHERE a.pos <= {mi} AND b.pos <= {mi} GROUP BY b.k, a.k HAVING count(*) >= {t})"


def _shared(name, points, dist, m, mi, t, gamma=None, chunks=1, merge="scancount", q=50):
    def query(spark, d):
        pts, qs = split_of(spark, d, points, q)
        return rounded(P.SharedPivots(pts, dist, m, mi=mi, chunks=chunks).search(qs, 10, t=t, gamma=gamma, merge=merge))

    cut = "cand AS (SELECT * FROM scores)" if gamma is None else T.gamma("scores", gamma if isinstance(gamma, int) else f"greatest(10, {_share('pts', gamma)})")
    register(name, query, f"{_shared_sql(points, dist, m, mi, t, q)}, {cut}, {T.refined('cand', dist, 10)} {T.RESULT}")


_shared("shared_threshold", "embeddings", "l2", 128, 32, 8)
_shared("shared_chunked", "embeddings", "l2", 128, 32, 8, chunks=8)
_shared("shared_forward", "embeddings", "l2", 128, 32, 8, merge="forward")
_shared("shared_scan", "embeddings", "l2", 128, 32, 8, merge="scan")
_shared("shared_extra_filter", "signatures", "sqfd", 16, 8, 1, gamma=0.2, q=5)
_shared("shared_cosine", "embeddings", "cosine", 128, 32, 8)
_shared("shared_kl", "topics8", "kl", 128, 32, 12)
_shared("shared_l1", "descriptors_share", "l1", 64, 16, 6, q=20)

# sequence index


def _sequence(spark, d):
    pts, _ = split_of(spark, d, "embeddings", 50)
    return P.SequenceIndex(pts, "l2", 16, mi=8)


_SEQUENCE = f"WITH {W.split_sql('embeddings', 50)}, {T.pivots(16)}, {T.seen('pts', 'id', 'l2', 'pseen')}, seq AS MATERIALIZED (SELECT k AS id, pos, pid AS sym FROM pseen WHERE pos <= 8)"
register("seqindex_access", lambda spark, d: _sequence(spark, d).access(2).select("id", F.col("sym").cast("long").alias("sym")), f"{_SEQUENCE} SELECT id, sym FROM seq WHERE pos = 2")
register(
    "seqindex_rank_select",
    lambda spark, d: _sequence(spark, d).numbered().select(F.col("sym").cast("long").alias("sym"), "id", F.col("pos").cast("long").alias("pos"), F.col("nth").cast("long").alias("nth")),
    f"{_SEQUENCE} SELECT sym, id, pos::BIGINT AS pos, row_number() OVER (PARTITION BY sym ORDER BY id, pos) AS nth FROM seq",
)


def seqindex_simulations(spark, d):
    """Prefix, postings and shared-pivot modes for one permutation, as counts of what they find."""
    index = _sequence(spark, d)
    prefix = index.as_prefix([1, 2]).agg(F.count("*").alias("points"), F.sum("id").alias("total")).select(F.lit("prefix").alias("mode"), "points", "total")
    posts = index.as_postings().where("pid = 3").agg(F.count("*").alias("points"), F.sum(F.col("id") * F.col("pos")).alias("total")).select(F.lit("postings").alias("mode"), "points", "total")
    shared = index.as_shared([1, 2, 3, 4], 4).where("shared >= 2").agg(F.count("*").alias("points"), F.sum(F.col("id") * F.col("shared")).alias("total")).select(F.lit("shared").alias("mode"), "points", "total")
    return prefix.unionByName(posts).unionByName(shared)


register(
    "seqindex_simulations",
    seqindex_simulations,
    f"""{_SEQUENCE} SELECT 'prefix' AS mode, count(*) AS points, sum(id)::BIGINT AS total FROM (SELECT id FROM seq WHERE (pos = 1 AND sym = 1) OR (pos = 2 AND sym = 2) GROUP BY id HAVING count(*) = 2)
UNION ALL SELECT 'postings', count(*), sum(id * pos)::BIGINT FROM seq WHERE sym = 3
UNION ALL SELECT 'shared', count(*), sum(id * n)::BIGINT FROM (SELECT id, count(*) AS n FROM seq WHERE pos <= 4 AND sym IN (1, 2, 3, 4) GROUP BY id HAVING count(*) >= 2)""",
)

# exact pruning by pivots


def _table(name, points, dist, m):
    def query(spark, d):
        pts, qs = split_of(spark, d, points, 50)
        return rounded(P.PivotTable(pts, dist, m).search(qs, 10))

    register(name, query, SQL[{"embeddings": "exact_l2", "topics8": "exact_js"}[points]])


_table("pivot_table_exact", "embeddings", "l2", 32)
_table("pivot_table_mu", "topics8", "js", 32)

"""What users do around the methods: filters, votes, joins of results, events, pages, and streams."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import distances as D
from ..operators import permutation_indexes as P
from ..operators import search as S
from ..operators.pivots import see, select_pivots
from ..sources import workloads as W
from ..sources.tables import table
from ..streaming import incremental as I
from . import sqltext as T
from .methods import _TERMS_SQL, _prefix_sql, rounded, split_of

QUERIES: dict = {}
SQL: dict[str, str] = {}


def register(name, query, sql=None):
    QUERIES[name] = query
    if sql:
        SQL[name] = sql


def filtered_knn(spark, d):
    """10-NN among one label only: the filter comes before the search, so it reaches the scan."""
    pts, qs = split_of(spark, d, "embeddings", 50)
    mine = table(spark, d, "embeddings").where("label = 3").select(F.col("vec_id").alias("id"))
    return rounded(S.exact_knn(pts.join(mine, "id", "left_semi"), qs, "l2"))


register("filtered_knn", filtered_knn, f"WITH {W.split_sql('embeddings', 50)}, cand AS (SELECT qid, id FROM pts, qs WHERE id IN (SELECT vec_id FROM embeddings WHERE label = 3)), {T.refined('cand', 'l2', 10)} {T.RESULT}")


def knn_label_vote(spark, d):
    """Quality by the majority of the five labelled neighbours (sparse cosine): a table of hits and misses."""
    labels = table(spark, d, "labels").select(F.col("doc_id").alias("id"), "quality")
    terms = W.terms(spark, d).join(labels.select("id"), "id", "left_semi")
    asked = terms.select("id").distinct().orderBy(F.md5(F.concat(F.lit("split0:"), F.col("id").cast("string")).cast("binary")), "id").limit(40)
    mine = F.broadcast(asked.select(F.col("id").alias("qid")))
    q = terms.join(mine, F.col("id") == F.col("qid")).select("qid", "term", "w")
    near = S.exact_sparse_cosine(terms.join(mine, F.col("id") == F.col("qid"), "left_anti"), q, 5)
    votes = near.join(labels, "id").groupBy("qid").agg((F.avg("quality") > 0.5).cast("int").alias("voted"))
    truth = labels.select(F.col("id").alias("qid"), F.col("quality").alias("quality"))
    return votes.join(truth, "qid").groupBy("quality").pivot("voted", [0, 1]).count().select("quality", F.coalesce("0", F.lit(0)).alias("voted_0"), F.coalesce("1", F.lit(0)).alias("voted_1"))


register(
    "knn_label_vote",
    knn_label_vote,
    f"""WITH {_TERMS_SQL}, mine AS MATERIALIZED (SELECT t.* FROM terms t WHERE id IN (SELECT doc_id FROM labels)), asked5 AS MATERIALIZED (SELECT id AS qid FROM (SELECT DISTINCT id FROM mine) ORDER BY md5('split0:' || id), id LIMIT 40),
dots AS (SELECT a.id AS qid, b.id, sum(a.w * b.w) AS dot FROM mine a JOIN mine b USING (term) WHERE a.id IN (SELECT qid FROM asked5) AND b.id NOT IN (SELECT qid FROM asked5) GROUP BY ALL),
near AS (SELECT * FROM (SELECT qid, d.id, row_number() OVER (PARTITION BY qid ORDER BY {T.key('1 - dot / (a.n * b.n)')}, d.id) AS r FROM dots d JOIN norms a ON a.id = d.qid JOIN norms b ON b.id = d.id) WHERE r <= 5),
votes AS (SELECT qid, CASE WHEN avg(quality) > 0.5 THEN 1 ELSE 0 END AS voted FROM near JOIN labels ON doc_id = id GROUP BY qid)
SELECT quality, count(*) FILTER (voted = 0) AS voted_0, count(*) FILTER (voted = 1) AS voted_1 FROM votes JOIN labels ON doc_id = qid GROUP BY quality""",
)


def _nation_pairs(spark, d):
    """Nearest suppliers by signature, with the nations of both."""
    pts = W.signatures(spark, d)
    few = pts.orderBy(F.md5(F.concat(F.lit("split0:"), F.col("id").cast("string")).cast("binary")), "id").limit(5).select(F.col("id").alias("qid"), "x")
    near = S.exact_knn(pts, few, "sqfd", 4).where("qid <> id")
    s = table(spark, d, "supplier").select("s_suppkey", "s_nationkey")
    n = table(spark, d, "nation").select("n_nationkey", "n_name", "n_regionkey")
    r = table(spark, d, "region").select("r_regionkey", "r_name")
    place = s.join(F.broadcast(n), F.col("s_nationkey") == F.col("n_nationkey")).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey"))
    a = place.select(F.col("s_suppkey").alias("qid"), F.col("r_name").alias("from_region"))
    b = place.select(F.col("s_suppkey").alias("id"), F.col("r_name").alias("to_region"))
    return near.join(a, "qid").join(b, "id").select("qid", "id", "from_region", "to_region")


_PAIRS_SQL = f"""WITH pts AS MATERIALIZED ({W.SQL['signatures']}), qs AS MATERIALIZED (SELECT id AS qid, x FROM pts ORDER BY md5('split0:' || id), id LIMIT 5), {T.everything()}, {T.refined('cand', 'sqfd', 4)},
place AS (SELECT s_suppkey AS k, r_name FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey),
pairs AS (SELECT qid, id, a.r_name AS from_region, b.r_name AS to_region FROM res JOIN place a ON a.k = qid JOIN place b ON b.k = id WHERE qid <> id)"""

register("knn_join_rollup", lambda spark, d: _nation_pairs(spark, d).rollup("from_region", "to_region").agg(F.count("*").alias("pairs")), f"{_PAIRS_SQL} SELECT from_region, to_region, count(*) AS pairs FROM pairs GROUP BY ROLLUP (from_region, to_region)")
register("knn_cube", lambda spark, d: _nation_pairs(spark, d).cube("from_region", "to_region").agg(F.count("*").alias("pairs")), f"{_PAIRS_SQL} SELECT from_region, to_region, count(*) AS pairs FROM pairs GROUP BY CUBE (from_region, to_region)")


def near_copy_benchmark(spark, d):
    """For each benchmark passage the documents that share most of its words: shared terms over the passage's own."""
    terms = W.terms(spark, d).select("id", "term")
    own = table(spark, d, "benchmark").select(F.col("item_id").alias("qid"), F.explode(F.array_distinct(W._tokens())).alias("term"))
    size = own.groupBy("qid").agg(F.count("*").alias("n"))
    met = terms.join(F.broadcast(own), "term").groupBy("qid", "id").agg(F.count("*").alias("shared")).join(F.broadcast(size), "qid")
    return met.where(F.col("shared") >= 0.9 * F.col("n")).select("qid", "id", "shared", "n")


register(
    "near_copy_benchmark",
    near_copy_benchmark,
    f"WITH {_TERMS_SQL}, own AS (SELECT DISTINCT item_id AS qid, unnest({W._TOKENS_SQL}) AS term FROM benchmark), size AS (SELECT qid, count(*) AS n FROM own GROUP BY qid) SELECT qid, id, shared, n FROM (SELECT qid, id, count(*) AS shared FROM own JOIN terms USING (term) GROUP BY ALL) JOIN size USING (qid) WHERE shared >= 0.9 * n",
)


def asof_events(spark, d):
    """For each purchase the same user's latest view before it: one pass over each user's events in order."""
    e = table(spark, d, "events").where("event_type IN ('view', 'purchase')").select("user_id", "ts", "event_id", "event_type")
    w = Window.partitionBy("user_id").orderBy("ts", F.col("event_type").desc(), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    seen = e.withColumn("last_ts", F.last(F.when(F.col("event_type") == "view", F.col("ts")), True).over(w))
    return seen.where("event_type = 'purchase' AND last_ts IS NOT NULL").select("event_id", F.col("last_ts").alias("view_ts"))


register("asof_events", asof_events, "SELECT p.event_id, max(v.ts) AS view_ts FROM events p JOIN events v ON p.user_id = v.user_id AND v.ts <= p.ts AND v.event_type = 'view' WHERE p.event_type = 'purchase' GROUP BY p.event_id")


def interval_events(spark, d):
    """Clicks within a day after a view of the same user: events meet by user and day, and the day before."""
    e = table(spark, d, "events").select("event_id", "ts", "user_id", "event_type")
    day = F.floor(F.unix_timestamp("ts") / 86400)
    views = e.where("event_type = 'view'").select(F.col("event_id").alias("view_id"), F.col("ts").alias("view_ts"), F.col("user_id"), F.explode(F.array(day, day + 1)).alias("day"))
    clicks = e.where("event_type = 'click'").select(F.col("event_id").alias("click_id"), "ts", "user_id", day.alias("day"))
    return clicks.join(views, ["user_id", "day"]).where("ts >= view_ts AND ts <= view_ts + INTERVAL 1 DAY").select("view_id", "click_id")


register("interval_events", interval_events, "SELECT v.event_id AS view_id, c.event_id AS click_id FROM events v JOIN events c ON v.user_id = c.user_id AND c.ts BETWEEN v.ts AND v.ts + INTERVAL 1 DAY WHERE v.event_type = 'view' AND c.event_type = 'click'")


def session_profiles(spark, d):
    """Sessions of a user (gaps of a day at most) with the share of each kind of event, as a permutation of kinds."""
    s = I.sessions(table(spark, d, "events"), "1 day")
    ordered = F.array_sort(F.array(*[F.struct((-F.col(k)).alias("n"), F.lit(i + 1).alias("i")) for i, k in enumerate(I.KINDS)]))
    return s.select("user_id", "n", F.array_join(F.transform(ordered, lambda t: t["i"].cast("string")), ",").alias("kinds")).groupBy("kinds").agg(F.count("*").alias("sessions"), F.sum("n").alias("events"))


register(
    "session_profiles",
    session_profiles,
    "WITH marked AS (SELECT *, CASE WHEN ts - lag(ts) OVER w < INTERVAL 1 DAY THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts) AS s FROM marked), g AS (SELECT user_id, s, count(*) AS n, "
    + ", ".join(f"count(*) FILTER (event_type = '{k}') AS k{i + 1}" for i, k in enumerate(I.KINDS))
    + " FROM s GROUP BY ALL), o AS (SELECT n, array_to_string(list_transform(list_sort(["
    + ", ".join(f"[-k{i + 1}, {i + 1}]" for i in range(len(I.KINDS)))
    + "]), lambda t: t[2]), ',') AS kinds FROM g) SELECT kinds, count(*) AS sessions, sum(n)::BIGINT AS events FROM o GROUP BY kinds",
)


def setops_candidates(spark, d):
    """Candidates of two copies of the prefix index: in both, in either, in the first only."""
    pts, qs = split_of(spark, d, "embeddings", 50)
    index = P.PrefixIndex(pts, "l2", 16, 4, 2)
    one, two = [], []
    for held, pivots in ((one, index.pivots[0]), (two, index.pivots[1])):
        part = P.PrefixIndex.__new__(P.PrefixIndex)
        part.__dict__ = {**index.__dict__, "pivots": [pivots]}
        held.append(part.candidates(qs, gamma=50).select("qid", "id"))
    a, b = one[0], two[0]
    count = lambda f, name: f.agg(F.count("*").alias("n")).select(F.lit(name).alias("set"), "n")
    return count(a.intersect(b), "both").unionByName(count(a.union(b).distinct(), "either")).unionByName(count(a.exceptAll(b), "first"))


def _setops_sql():
    text = _prefix_sql(2, "order")
    head, cand = text.split(", cand AS MATERIALIZED (SELECT qid, id, min(score)::BIGINT AS score FROM (")
    a, b = cand.rsplit(") GROUP BY qid, id)", 1)[0].split(" UNION ALL ")
    return f"{head}, a AS MATERIALIZED (SELECT qid, id FROM ({a})), b AS MATERIALIZED (SELECT qid, id FROM ({b})) SELECT 'both' AS \"set\", count(*) AS n FROM (SELECT * FROM a INTERSECT SELECT * FROM b) UNION ALL SELECT 'either', count(*) FROM (SELECT * FROM a UNION SELECT * FROM b) UNION ALL SELECT 'first', count(*) FROM (SELECT * FROM a EXCEPT SELECT * FROM b)"


register("setops_candidates", setops_candidates, _setops_sql())


def json_props(spark, d):
    """The five events whose property k is nearest to 50, of each kind."""
    e = table(spark, d, "events").select("event_id", "event_type", F.from_json("props", "k INT")["k"].alias("k")).where("k IS NOT NULL")
    w = Window.partitionBy("event_type").orderBy(F.abs(F.col("k") - 50), "event_id")
    return e.withColumn("rnk", F.row_number().over(w)).where("rnk <= 5").select("event_type", "event_id", "k", "rnk")


register("json_props", json_props, "SELECT event_type, event_id, k, rnk::INT AS rnk FROM (SELECT *, row_number() OVER (PARTITION BY event_type ORDER BY abs(k - 50), event_id) AS rnk FROM (SELECT event_id, event_type, (props->>'k')::INT AS k FROM events) WHERE k IS NOT NULL) WHERE rnk <= 5")


def page_text_topk(spark, d):
    """The ten pages nearest to page 0 by words of the text behind the tags: Jaccard distance of word sets."""
    text = F.regexp_replace("html", "<[^>]*>", " ")
    words = table(spark, d, "pages").select(F.col("page_id").alias("id"), F.array_distinct(F.regexp_extract_all(F.lower(text), F.lit("[a-z]+"), F.lit(0))).alias("w"))
    own = F.broadcast(words.where("id = 0").select(F.col("w").alias("q")))
    dist = 1 - F.size(F.array_intersect("w", "q")) / F.size(F.array_union("w", "q"))
    scored = words.where("id <> 0").crossJoin(own).select(F.lit(0).cast("long").alias("qid"), "id", dist.alias("dist"))
    return rounded(S.ranked(scored.where("dist IS NOT NULL"), 10))


register(
    "page_text_topk",
    page_text_topk,
    f"WITH w AS (SELECT page_id AS id, list_distinct(regexp_extract_all(lower(regexp_replace(html, '<[^>]*>', ' ', 'g')), '[a-z]+')) AS w FROM pages), s AS (SELECT 0::BIGINT AS qid, a.id, 1 - len(list_intersect(a.w, b.w)) / len(list_distinct(list_concat(a.w, b.w))) AS dist FROM w a, w b WHERE b.id = 0 AND a.id <> 0), res AS (SELECT * FROM (SELECT *, row_number() OVER (ORDER BY {T.key('dist')}, id) AS rnk FROM s) WHERE rnk <= 10) {T.RESULT}",
)


def conversation_turns(spark, d):
    """For each conversation of the first hundred, how like its turns are in length: normalised edit distance of roles."""
    turns = table(spark, d, "conversations").where("conv_id < 100").groupBy("conv_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("turn", "role"))), lambda t: F.substring(t["role"], 1, 1)), "").alias("roles"))
    first = F.broadcast(turns.where("conv_id = 0").select(F.col("roles").alias("q")))
    return turns.crossJoin(first).select("conv_id", F.round(D.norm_levenshtein(F.col("roles"), F.col("q")), 6).alias("dist"))


register("conversation_turns", conversation_turns, f"WITH t AS (SELECT conv_id, string_agg(role[1], '' ORDER BY turn, role) AS r FROM conversations WHERE conv_id < 100 GROUP BY conv_id) SELECT a.conv_id, round({D.distance('norm_lev').sql('a.r', 'b.r')}, 6) AS dist FROM t a, t b WHERE b.conv_id = 0")


def conversation_turns_all(spark, d):
    """For every conversation, how like its turns are to those of the first: normalised edit distance of roles."""
    turns = table(spark, d, "conversations").groupBy("conv_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("turn", "role"))), lambda t: F.substring(t["role"], 1, 1)), "").alias("roles"))
    first = F.broadcast(turns.where("conv_id = 0").select(F.col("roles").alias("q")))
    return turns.crossJoin(first).select("conv_id", F.round(D.norm_levenshtein(F.col("roles"), F.col("q")), 6).alias("dist"))


register("conversation_turns_all", conversation_turns_all, SQL["conversation_turns"].replace(" WHERE conv_id < 100", ""))


def user_mix_knn(spark, d):
    """10-NN by divergence of users' event mixes (right queries)."""
    pts, qs = W.split(W.user_mix(spark, d), 20)
    return rounded(S.exact_knn(pts, qs, "kl", side="right"))


_MIX = "SELECT id, {'p': p, 'logp': list_transform(p, lambda v: ln(v))} AS x FROM (SELECT user_id AS id, [" + ", ".join(f"greatest(count(*) FILTER (event_type = '{k}') / count(*), 1e-05)" for k in ("click", "view", "purchase", "signup", "logout")) + "] AS p FROM events GROUP BY user_id)"
W.SQL["user_mix"] = _MIX
register("user_mix_knn", user_mix_knn, f"WITH {W.split_sql('user_mix', 20)}, {T.everything()}, {T.refined('cand', 'kl', 10, 'right')} {T.RESULT}")

# index maintenance and streams


def index_append_delete(spark, d):
    """An index built in two batches less deleted points equals the index built anew: differing postings (none)."""
    pts = W.embeddings(spark, d)
    pivots = select_pivots(pts, 64)
    build = lambda rows: see(rows, pivots, "l2", mi=16, want=("ord",)).select(F.explode("ord").alias("pid"), "id")
    grown = build(pts.where("id % 2 = 0")).unionByName(build(pts.where("id % 2 = 1")))
    kept = I.live(grown, pts.where("id % 7 = 0").select("id"))
    anew = build(pts.where("id % 7 <> 0"))
    return kept.exceptAll(anew).unionByName(anew.exceptAll(kept)).agg(F.count("*").alias("differing")).crossJoin(anew.agg(F.count("*").alias("postings")))


register("index_append_delete", index_append_delete, "SELECT 0::BIGINT AS differing, count(*) * 16 AS postings FROM embeddings WHERE vec_id % 7 <> 0")


def window_mixes(spark, d):
    """Counts of events in daily windows that begin every six hours."""
    return I.mixes(table(spark, d, "events"), "1 day", "6 hours").select("start", "n", "purchase")


register("window_mixes", window_mixes, "SELECT start, count(*) AS n, count(*) FILTER (event_type = 'purchase') AS purchase FROM (SELECT event_type, time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01') - INTERVAL 6 HOUR * o AS start FROM events, range(4) r(o)) GROUP BY start")


def stream_mixes(spark, d):
    """Daily counts by a stream that has read all files: equal to the batch."""
    schema = table(spark, d, "events").schema
    stream = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(d).withColumn("ts", F.col("ts").cast("timestamp"))
    name = f"stream_mixes_{abs(hash(d)) % 10**9}"
    return I.drain(I.mixes(stream), name, "complete").select(F.col("start").cast("timestamp_ntz").alias("start"), "n")


register("stream_mixes", stream_mixes, "SELECT date_trunc('day', ts)::TIMESTAMP AS start, count(*) AS n FROM events GROUP BY 1")

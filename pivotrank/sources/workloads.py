"""Point sets (id, x) from the given tables, in Spark and as SQL for the oracle, and query splits.

Every builder has a twin in ``SQL`` that makes the same points in DuckDB. Whatever is random comes
from md5 of a key, so both agree.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import order_key, uniform, uniform_sql
from .tables import table

FLOOR = 1e-5


def _hex_mod(text, m: int):
    return F.pmod(F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("long"), F.lit(m)).cast("int")


def _tokens(text: str = "text"):
    lowered = F.translate(F.coalesce(F.col(text), F.lit("")), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    return F.regexp_extract_all(lowered, F.lit("[a-z]+"), F.lit(0))


_TOKENS_SQL = "regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[a-z]+')"


def embeddings(spark: SparkSession, d: str) -> DataFrame:
    """64 components as doubles; rows with a null, NaN or infinite component are left out."""
    x = F.transform("embedding", lambda c: c.cast("double"))
    return table(spark, d, "embeddings").select(F.col("vec_id").alias("id"), x.alias("x")).where(F.col("x").isNotNull() & F.forall("x", lambda c: c.isNotNull() & ~F.isnan(c) & (F.abs(c) < float("inf"))))


def topics(spark: SparkSession, d: str, bins: int = 8) -> DataFrame:
    """A document's share of tokens in each of ``bins`` hashed topics; empty ones count as FLOOR."""
    tokens = table(spark, d, "documents").select(F.col("doc_id").alias("id"), F.explode(_tokens()).alias("t"))
    # a token is hashed once for each document that holds it
    counts = tokens.groupBy("id", "t").agg(F.count("*").alias("c")).select("id", _hex_mod(F.col("t"), bins).alias("b"), "c").groupBy("id").agg(*[F.sum(F.when(F.col("b") == k, F.col("c")).otherwise(0)).alias(f"b{k}") for k in range(bins)])
    total = sum((F.col(f"b{k}") for k in range(1, bins)), F.col("b0"))
    p = F.array(*[F.greatest(F.col(f"b{k}") / total, F.lit(FLOOR)) for k in range(bins)])
    return counts.select("id", p.alias("p")).select("id", F.struct("p", F.transform("p", lambda v: F.log(v)).alias("logp")).alias("x"))


def sequences(spark: SparkSession, d: str) -> DataFrame:
    """The letters of a document's head as four symbols, about 32 of them (standard deviation 4)."""
    letters = F.regexp_replace(F.translate(F.coalesce("text", F.lit("")), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), "[^a-z]", "")
    z = sum((uniform(F.concat(F.lit(f"len{i}:"), F.col("doc_id").cast("string"))) for i in range(12)), F.lit(-6.0))
    n = F.greatest(F.lit(1), F.floor(32.5 + 4 * z).cast("int"))
    return table(spark, d, "documents").select(F.col("doc_id").alias("id"), F.translate(F.substring(letters, F.lit(1), n), "abcdefghijklmnopqrstuvwxyz", "ACGTACGTACGTACGTACGTACGTAC").alias("x"))


def sequences_drawn(spark: SparkSession, d: str) -> DataFrame:
    """The letters of a document from a random place on, as many as in ``sequences``."""
    z = sum((uniform(F.concat(F.lit(f"len{i}:"), F.col("doc_id").cast("string"))) for i in range(12)), F.lit(-6.0))
    n = F.greatest(F.lit(1), F.floor(32.5 + 4 * z).cast("int"))
    place = uniform(F.concat(F.lit("start:"), F.col("doc_id").cast("string")))
    held = table(spark, d, "documents").select(F.col("doc_id").alias("id"), F.coalesce("text", F.lit("")).cast("binary").alias("s"), n.alias("n"), place.alias("u"))

    def draw(batches):
        for batch in batches:
            out = []
            for text, n, u in zip(*(batch.column(i).to_pylist() for i in (1, 2, 3)), strict=True):
                letters = text.translate(_SYMBOLS, _OTHERS)
                start = int(u * (max(0, len(letters) - n) + 1)) if u is not None else 0
                out.append(letters[start : start + n].decode() if u is not None and n is not None else None)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.string())], names=["id", "x"])

    return held.mapInArrow(draw, "id long, x string")


_SYMBOLS = bytes(b"ACGT"[((c | 32) - 97) % 4] for c in range(256))
_OTHERS = bytes(c for c in range(256) if not (65 <= c <= 90 or 97 <= c <= 122))


def descriptors(spark: SparkSession, d: str, bins: int = 282, normalise: bool = False, source: str = "documents", id: str = "doc_id", text: str = "text") -> DataFrame:
    """Counts of letter trigrams in hashed bins; with ``normalise`` their shares."""
    docs = table(spark, d, source).select(F.col(id).alias("id"), F.col(text).alias("s"))

    def count(batches):
        for batch in batches:
            ids, counts = batch.column(0), trigram_counts(batch.column(1), bins)
            full = np.flatnonzero(counts.any(1))
            counts = counts[full].astype(np.float64)
            yield pa.RecordBatch.from_arrays([ids.take(pa.array(full)), _lists(counts)], names=["id", "x"])

    # one narrow pass, and rows of one id are put together where there are any
    counts = docs.mapInArrow(count, "id long, x array<double>")
    if docs.groupBy("id").count().where("count > 1").isEmpty():
        return counts.mapInArrow(_shares, "id long, x array<double>") if normalise else counts
    both = counts.groupBy("id").agg(F.array(*[F.sum(F.col("x")[b]) for b in range(bins)]).alias("x"))
    return both.mapInArrow(_shares, "id long, x array<double>") if normalise else both


def _lists(x: np.ndarray) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.arange(0, x.size + 1, x.shape[1]), pa.int32()), pa.array(x.ravel()))


def _shares(batches):
    for batch in batches:
        x = batch.column(1).flatten().to_numpy().reshape(len(batch), -1) if len(batch) else np.empty((0, 1))
        yield pa.RecordBatch.from_arrays([batch.column(0), _lists(x / x.sum(1, keepdims=True))], names=["id", "x"])


_LETTERS = np.zeros(256, np.uint16)  # of a byte: 1 to 26 for a letter of either case
_LETTERS[97:123] = _LETTERS[65:91] = np.arange(1, 27)


def trigram_counts(texts: pa.Array, bins: int, most: int = 256 << 10) -> np.ndarray:
    """For each text, how many trigrams of its letters a-z (A-Z lower-cased, all else left out) fall in each bin."""
    texts = pc.fill_null(texts.cast(pa.large_string()), "")
    n = len(texts)
    out = np.zeros((n, bins), np.int64)
    at = np.frombuffer(texts.buffers()[1], np.int64)[texts.offset : texts.offset + n + 1]
    raw = np.frombuffer(texts.buffers()[2] or b"", np.uint8)
    i = np.arange(1 << 15)
    table = (((i >> 10) + 96) * 961 + ((i >> 5 & 31) + 96) * 31 + (i & 31) + 96) % bins
    a = 0
    while a < n:  # texts of so many bytes at a time, as they fit in the processor's cache
        b = max(a + 1, int(np.searchsorted(at, at[a] + most, side="right")) - 1)
        letters = _LETTERS[raw[at[a] : at[b]]]
        kept = letters > 0
        ends = np.concatenate(([0], np.cumsum(kept)))[at[a : b + 1] - at[a]]
        c = letters[kept]
        if len(c) > 2:
            code = table[(c[:-2] << 10) | (c[1:-1] << 5) | c[2:]] + np.repeat(np.arange(b - a) * bins, np.diff(ends))[:-2]
            across = np.concatenate((ends[1:] - 2, ends[1:] - 1))  # trigrams that would run into the next text
            across = across[(across >= np.tile(ends[:-1], 2)) & (across < len(code))]
            code[across] = (b - a) * bins
            out[a:b] = np.bincount(code, minlength=(b - a) * bins + 1)[:-1].reshape(b - a, bins)
        a = b
    return out


def terms(spark: SparkSession, d: str) -> DataFrame:
    """(id, term, w): term frequency by log inverse document frequency."""
    tf = table(spark, d, "documents").select(F.col("doc_id").alias("id"), F.explode(_tokens()).alias("term")).groupBy("id", "term").agg(F.count("*").alias("tf"))
    df = tf.groupBy("term").agg(F.count("*").alias("df"))
    n = table(spark, d, "documents").agg(F.count("*").alias("n"))
    return tf.join(df, "term").crossJoin(F.broadcast(n)).select("id", "term", (F.col("tf") * F.log(F.col("n") / F.col("df"))).alias("w")).where("w > 0")


def tfidf(spark: SparkSession, d: str) -> DataFrame:
    """Sparse vectors; a term's number is its hash, so no vocabulary is gathered."""
    held = terms(spark, d).groupBy("id").agg(F.array_sort(F.collect_list(F.struct(F.xxhash64("term").alias("i"), "w"))).alias("e"))
    norm = F.sqrt(F.aggregate("e", F.lit(0.0), lambda a, t: a + t["w"] * t["w"]))
    return held.select("id", F.struct(F.transform("e", lambda t: t["i"]).alias("idx"), F.transform("e", lambda t: t["w"]).alias("val"), norm.alias("norm")).alias("x"))


_FEATURES = {
    "quantity": ("l_quantity / 50", "l_quantity / 50"),
    "price": ("l_extendedprice / 100000", "l_extendedprice / 100000"),
    "discount": ("l_discount * 10", "l_discount * 10"),
    "tax": ("l_tax * 10", "l_tax * 10"),
    "day": ("unix_timestamp(l_shipdate) / 86400 / 10000", "epoch(l_shipdate)::BIGINT / 86400 / 10000"),
    "flag": ("CASE l_returnflag WHEN 'A' THEN 0.0D WHEN 'N' THEN 0.5D ELSE 1.0D END", "CASE l_returnflag WHEN 'A' THEN 0.0 WHEN 'N' THEN 0.5 ELSE 1.0 END::DOUBLE"),
    "status": ("CASE l_linestatus WHEN 'F' THEN 0.0D ELSE 1.0D END", "CASE l_linestatus WHEN 'F' THEN 0.0 ELSE 1.0 END::DOUBLE"),
}


def signatures(spark: SparkSession, d: str, by: str = "l_suppkey") -> DataFrame:
    """An object's rows as at most 20 clusters on a grid of quantity and discount: centroid and share."""
    rows = table(spark, d, "lineitem").selectExpr(f"{by} AS id", *[f"cast({e[0]} AS double) AS {k}" for k, e in _FEATURES.items()], "cast(least(4, floor((l_quantity - 1) / 10)) AS int) * 4 + cast(least(3, floor(l_discount * 100 / 3 + 0.001)) AS int) AS cell")
    cells = rows.groupBy("id", "cell").agg(F.count("*").alias("n"), F.array(*[F.round(F.avg(k), 9) for k in _FEATURES]).alias("c"))
    held = cells.groupBy("id").agg(F.array_sort(F.collect_list(F.struct("cell", "c", "n"))).alias("e"), F.sum("n").alias("total"))
    return held.select("id", F.transform("e", lambda t: F.struct(t["c"].alias("c"), (t["n"] / F.col("total")).alias("w"))).alias("x"))


def line(spark: SparkSession, d: str) -> DataFrame:
    """Event values on the line, with 0, 1 and 40 (ids -1, -2 and -3)."""
    given = spark.createDataFrame([(-1, 0.0), (-2, 1.0), (-3, 40.0)], "id long, x double")
    return table(spark, d, "events").select(F.col("event_id").alias("id"), F.col("value").alias("x")).where("x IS NOT NULL").unionByName(given)


def lineitems(spark: SparkSession, d: str) -> DataFrame:
    """Seven scaled features of each row; the id is a hash of the whole row, as no key is unique."""
    rows = table(spark, d, "lineitem")
    id = F.conv(F.substring(F.md5(F.concat_ws("|", *[F.col(c).cast("string") for c in rows.columns]).cast("binary")), 1, 15), 16, 10).cast("long")
    return rows.select(id.alias("id"), F.array(*[F.expr(f"cast({e[0]} AS double)") for e in _FEATURES.values()]).alias("x"))


def user_mix(spark: SparkSession, d: str) -> DataFrame:
    """A user's share of each of five event types."""
    kinds = ["click", "view", "purchase", "signup", "logout"]
    counts = table(spark, d, "events").groupBy(F.col("user_id").alias("id")).agg(*[F.count(F.when(F.col("event_type") == k, 1)).alias(f"b{i}") for i, k in enumerate(kinds)], F.count("*").alias("n"))
    p = F.array(*[F.greatest(F.col(f"b{i}") / F.col("n"), F.lit(FLOOR)) for i in range(len(kinds))])
    return counts.select("id", p.alias("p")).select("id", F.struct("p", F.transform("p", lambda v: F.log(v)).alias("logp")).alias("x"))


def split(points: DataFrame, queries: int, number: int = 0) -> tuple[DataFrame, DataFrame]:
    """(points to index, queries): the queries are the first of a seeded order by id.

    The queries are few (a parameter), so the rest is found by a broadcast of their ids. They are kept, as
    every use of either part would choose them anew from all points.
    """
    from ..operators.graphs import cut

    asked = cut(points.orderBy(order_key(f"split{number}", "id"), "id").limit(queries))
    ids = F.broadcast(asked.select(F.col("id").alias("_q")))
    return points.join(ids, F.col("id") == F.col("_q"), "left_anti"), asked.select(F.col("id").alias("qid"), "x")


def _features_sql() -> str:
    return ", ".join(f"({e[1]})::DOUBLE AS {k}" for k, e in _FEATURES.items())


def _topics_sql(bins: int) -> str:
    shares = ", ".join(f"greatest(sum(CASE WHEN b = {k} THEN 1 ELSE 0 END) / count(*), {FLOOR!r})" for k in range(bins))
    return f"""SELECT id, {{'p': p, 'logp': list_transform(p, lambda v: ln(v))}} AS x FROM (
      SELECT id, [{shares}] AS p FROM (SELECT doc_id AS id, ('0x' || md5(t)[1:8])::BIGINT % {bins} AS b FROM (SELECT doc_id, unnest({_TOKENS_SQL}) AS t FROM documents)) GROUP BY id)"""


SQL = {
    "embeddings": "SELECT vec_id AS id, embedding::DOUBLE[] AS x FROM embeddings",
    "topics8": _topics_sql(8),
    "sequences": """SELECT doc_id AS id, translate(substring(regexp_replace(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^a-z]', '', 'g'), 1,
      greatest(1, floor(32.5 + 4 * ("""
    + " + ".join(["-6.0", *[f"('0x' || md5('len{i}:' || doc_id)[1:13])::BIGINT / 4503599627370496.0" for i in range(12)]])
    + """))::INT)), 'abcdefghijklmnopqrstuvwxyz', 'ACGTACGTACGTACGTACGTACGTAC') AS x FROM documents""",
    "signatures": f"""SELECT id, list_transform(e, lambda t: {{'c': t.c, 'w': t.n / total}}) AS x FROM (
      SELECT id, list({{'cell': cell, 'c': c, 'n': n}} ORDER BY cell) AS e, sum(n) AS total FROM (
      SELECT id, cell, count(*) AS n, [{", ".join(f"round(avg({k}), 9)" for k in _FEATURES)}] AS c FROM (
      SELECT l_suppkey AS id, {_features_sql()}, least(4, floor((l_quantity - 1) / 10))::INT * 4 + least(3, floor(l_discount * 100 / 3 + 0.001))::INT AS cell FROM lineitem) GROUP BY id, cell) GROUP BY id)""",
    "line": "SELECT event_id AS id, value AS x FROM events WHERE value IS NOT NULL UNION ALL (VALUES (-1, 0.0::DOUBLE), (-2, 1.0::DOUBLE), (-3, 40.0::DOUBLE))",
    "descriptors": None,
}


SQL["sequences_drawn"] = f"""SELECT id, translate(substring(s, 1 + floor({uniform_sql("'start:' || id")} * (greatest(0, length(s) - n) + 1))::INT, n), 'abcdefghijklmnopqrstuvwxyz', 'ACGTACGTACGTACGTACGTACGTAC') AS x FROM (
      SELECT doc_id AS id, regexp_replace(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^a-z]', '', 'g') AS s,
      greatest(1, floor(32.5 + 4 * ({" + ".join(["-6.0", *[uniform_sql(f"'len{i}:' || doc_id") for i in range(12)]])}))::INT) AS n FROM documents)"""


def _descriptors_sql(bins: int, normalise: bool) -> str:
    x = f"list_transform(range({bins}), lambda b: coalesce(m[b], 0)::DOUBLE{' / n' if normalise else ''})"
    return f"""SELECT id, {x} AS x FROM (SELECT id, map(list(b), list(c)) AS m, sum(c) AS n FROM (
      SELECT id, (s[i] * 961 + s[i + 1] * 31 + s[i + 2]) % {bins} AS b, count(*) AS c FROM (
      SELECT doc_id AS id, list_transform(string_split(regexp_replace(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^a-z]', '', 'g'), ''), lambda t: ascii(t)) AS s FROM documents), unnest(range(1, len(s) - 1)) r(i) GROUP BY ALL) GROUP BY id)"""


SQL["descriptors"] = _descriptors_sql(282, False)
SQL["descriptors_share"] = _descriptors_sql(282, True)


def split_sql(points: str, queries: int, number: int = 0) -> str:
    """CTEs all_pts, qs and pts over a builder of SQL."""
    return f"""all_pts AS MATERIALIZED ({SQL[points]}),
qs AS MATERIALIZED (SELECT id AS qid, x FROM all_pts ORDER BY md5('split{number}:' || id), id LIMIT {queries}),
pts AS MATERIALIZED (SELECT id, x FROM all_pts WHERE id NOT IN (SELECT qid FROM qs))"""


BUILDERS = {
    "embeddings": embeddings,
    "topics8": topics,
    "sequences": sequences,
    "sequences_drawn": sequences_drawn,
    "signatures": signatures,
    "line": line,
    "descriptors": descriptors,
    "descriptors_share": lambda spark, d: descriptors(spark, d, normalise=True),
    "tfidf": tfidf,
    "lineitems": lineitems,
    "user_mix": user_mix,
}


def topics_lda(spark: SparkSession, d: str, bins: int = 8, vocabulary: int = 4000, seed: int = 3) -> DataFrame:
    """Topic histograms by latent Dirichlet allocation, fitted on one half of the documents and applied to the other."""
    from pyspark.ml.clustering import LDA
    from pyspark.ml.feature import CountVectorizer
    from pyspark.ml.functions import vector_to_array

    docs = table(spark, d, "documents").select(F.col("doc_id").alias("id"), _tokens().alias("words"))
    half = F.pmod(F.xxhash64("id"), F.lit(2))
    counts = CountVectorizer(inputCol="words", outputCol="features", vocabSize=vocabulary, minDF=2).fit(docs.where(half == 0))
    model = LDA(k=bins, maxIter=10, seed=seed).fit(counts.transform(docs.where(half == 0)))
    shares = model.transform(counts.transform(docs.where(half == 1))).select("id", F.transform(vector_to_array("topicDistribution"), lambda v: F.greatest(v, F.lit(FLOOR))).alias("p"))
    return shares.select("id", F.struct("p", F.transform("p", lambda v: F.log(v)).alias("logp")).alias("x"))


def signatures_kmeans(spark: SparkSession, d: str, by: str = "l_partkey", clusters: int = 20, rounds: int = 10, sample: int = 10_000) -> DataFrame:
    """An object's rows as at most ``clusters`` centroids with shares, by k-means on a sample of its rows.

    The sample is the first ``sample`` of a hashed order within the object, so a group stays bounded.
    """
    import numpy as np
    import pandas as pd
    from pyspark.sql import Window

    rows = table(spark, d, "lineitem").selectExpr(f"{by} AS id", "xxhash64(*) AS h", f"array({', '.join(f'cast({e[0]} AS double)' for e in _FEATURES.values())}) AS v")
    w = Window.partitionBy("id").orderBy("h")
    few = rows.withColumn("r", F.row_number().over(w)).where(F.col("r") <= sample).select("id", "r", "v")

    def group(frame: pd.DataFrame) -> pd.DataFrame:
        x = np.stack(frame.sort_values("r")["v"].to_numpy())
        centres = np.unique(x, axis=0)[:: max(1, len(np.unique(x, axis=0)) // clusters)][:clusters]
        for _ in range(rounds):
            own = ((x[:, None] - centres[None]) ** 2).sum(-1).argmin(1)
            centres = np.stack([x[own == i].mean(0) if (own == i).any() else c for i, c in enumerate(centres)])
        own = ((x[:, None] - centres[None]) ** 2).sum(-1).argmin(1)
        kept = [{"c": centres[i].tolist(), "w": float((own == i).mean())} for i in np.unique(own)]
        return pd.DataFrame({"id": [frame["id"].iloc[0]], "x": [kept]})

    return few.groupBy("id").applyInPandas(group, "id long, x array<struct<c: array<double>, w: double>>")

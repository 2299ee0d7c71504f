"""The queries of this subpackage over the given tables, with their SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from .session import table


def op1_substring_dedup(spark, sf_dir):
    from .substring_dedup import remove_repeats

    out = remove_repeats(table(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_words", "n_removed", F.sha2(F.col("kept").cast("binary"), 256).alias("kept_sha256"))


OP1_SQL = r"""
WITH w AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS ws FROM documents),
win AS (SELECT doc_id, p, md5(array_to_string(ws[p:p + 49], ' ')) AS h FROM w, unnest(range(1, len(ws) - 48)) t(p)),
early AS (SELECT h, min(doc_id) AS d FROM win GROUP BY h),
gone AS (SELECT DISTINCT doc_id, p + o AS i FROM win JOIN early USING (h), range(50) t(o) WHERE early.d < doc_id),
word AS (SELECT doc_id, unnest(ws) AS word, generate_subscripts(ws, 1) AS i FROM w),
kept AS (SELECT doc_id, string_agg(word, ' ' ORDER BY i) AS k, count(*) AS n FROM word ANTI JOIN gone USING (doc_id, i) GROUP BY doc_id)
SELECT w.doc_id, len(ws)::BIGINT AS n_words, (len(ws) - coalesce(n, 0))::BIGINT AS n_removed, sha256(coalesce(k, '')) AS kept_sha256
FROM w LEFT JOIN kept USING (doc_id)
"""

def op2_sharding(spark, sf_dir):
    from .sharding import shuffle_into_shards

    out = shuffle_into_shards(table(spark, sf_dir, "documents").select("doc_id", "text"), shards=8)
    text = F.coalesce("text", F.lit(""))
    return out.select(
        "doc_id",
        (F.octet_length(text) + 1).cast("long").alias("size"),
        F.crc32(text.cast("binary")).alias("text_crc32"),
        F.lit("rows").alias("law"),
        "shard",
        F.col("slot").cast("long").alias("slot"),
        F.lit(None).cast("int").alias("grown_shard"),
    )


def op3_quality(spark, sf_dir):
    from . import quality
    from .sampling import fold

    docs = table(spark, sf_dir, "documents")
    model = quality.fit(docs, table(spark, sf_dir, "labels"), usable=fold() != 0)
    scored = docs.select("doc_id", model.column("text").alias("score"))
    return scored.select("doc_id", F.coalesce(fold() == 0, F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))


def op4_near_dup(spark, sf_dir):
    from .near_dup import classes

    return classes(table(spark, sf_dir, "documents"))


def op5_license_scan(spark, sf_dir):
    from .license_scan import scan

    out = scan(table(spark, sf_dir, "documents").select("doc_id", "text"))
    places, hits = F.col("found.places"), F.col("found.hits")
    base = F.array_sort(F.array_distinct(F.transform(places, lambda p: p["label"])))
    method = F.transform(hits, lambda h: F.substring_index(h["label"], "-notice", 1))
    n_base = F.size(places)
    return out.select(
        "doc_id",
        F.col("found.n_words").cast("long").alias("n_words"),
        n_base.cast("long").alias("n_base"),
        F.array_min(F.transform(places, lambda p: p["first_word"])).cast("long").alias("first_word"),
        F.array_max(F.transform(places, lambda p: p["first_word"])).cast("long").alias("last_word"),
        F.array_join(base, ",").alias("base_labels"),
        F.array_join(F.array_sort(F.array_distinct(F.concat(base, method))), ",").alias("labels"),
        F.when(n_base > 0, F.lit(1.0)).otherwise(F.coalesce(F.array_max(F.transform(hits, lambda h: h["containment"])), F.lit(0.0))).alias("score"),
    )


def _op5_sql():
    import math

    from .license_scan import DISTINGUISHING, PHRASES, TEMPLATES, THRESHOLD

    rows = []
    for label, text in TEMPLATES.items():
        own = sorted(set(text.split()))
        told = ", ".join(f"'{w}'" for w in DISTINGUISHING.get(label, "").split())
        rows.append(f"('{label.removesuffix('-notice')}', {own}, [{told}]::VARCHAR[], {len(text.split())}, {math.ceil(THRESHOLD * len(own) - 1e-9)})")
    phrases = []
    for phrase, label in PHRASES.items():
        parts = phrase.split()
        same = " AND ".join(f"ws[i + {j + 1}] = '{w}'" for j, w in enumerate(parts))
        phrases.append(f"SELECT doc_id, '{label}' AS label, i FROM w, unnest(range(0, len(ws) - {len(parts) - 1})) t(i) WHERE {same}")
    return rf"""
WITH w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM documents),
place AS ({" UNION ALL ".join(phrases)}),
base AS (SELECT doc_id, count(*) AS n, min(i) AS lo, max(i) AS hi, list_sort(list_distinct(list(label))) AS labels FROM place GROUP BY doc_id),
template(label, own, told, stride, need) AS (VALUES {", ".join(rows)}),
block AS (SELECT doc_id, label, need, len(own) AS m, len(list_intersect(list_distinct(ws[b * stride + 1:b * stride + 2 * stride]), own)) AS c,
                 list_has_all(ws[b * stride + 1:b * stride + 2 * stride], told) AS known
          FROM w, template, unnest(range(0, (len(ws) + stride - 1) // stride)) t(b)),
hit AS (SELECT doc_id, max(c / m) AS best, list(DISTINCT label) AS labels FROM block WHERE c >= need AND known GROUP BY doc_id)
SELECT w.doc_id, len(ws)::BIGINT AS n_words, coalesce(n, 0)::BIGINT AS n_base, lo::BIGINT AS first_word, hi::BIGINT AS last_word,
       coalesce(array_to_string(base.labels, ','), '') AS base_labels,
       coalesce(array_to_string(list_sort(list_distinct(list_concat(coalesce(base.labels, []), coalesce(hit.labels, [])))), ','), '') AS labels,
       CASE WHEN n > 0 THEN 1.0 ELSE coalesce(best, 0.0) END::DOUBLE AS score
FROM w LEFT JOIN base USING (doc_id) LEFT JOIN hit USING (doc_id)
"""


def sentence_pieces(path: str | None = None):
    """The encoder of a model file; where no path is given, of the public 32k model."""
    from .sentencepieces import SentencePieces

    if path is None:
        import public_tokenizers

        path = public_tokenizers.path("piece_bpe_32k.model")
    with open(path, "rb") as f:
        return SentencePieces(f.read())


def op6_sentencepiece(spark, sf_dir):
    held = sentence_pieces().encode_documents(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return held.select("doc_id", F.size("ids").cast("long").alias("n_tokens"), F.xxhash64("ids").alias("ids_hash"), "parity", "round_trip")


def byte_tokenizer(path: str | None = None) -> str:
    """The content of a tokenizer file; without a path, of the public 50k one."""
    import public_tokenizers

    with open(path or public_tokenizers.path("byte_bpe_50k.json"), encoding="utf-8") as f:
        return f.read()


def op7_token_files(spark, sf_dir):
    from uuid import uuid4

    from .session import shared_folder
    from .token_files import read_files, write_files

    folder = f"{shared_folder(spark)}/token-files-{uuid4()}"
    write_files(table(spark, sf_dir, "documents"), folder, byte_tokenizer(), end_id=0)
    return read_files(spark, folder).select("doc_id", "start", "n_tokens", F.crc32("ids").alias("ids_crc32"))


def op8_language(spark, sf_dir):
    from . import language
    from .sampling import fold

    docs = table(spark, sf_dir, "documents")
    model = language.fit(docs, usable=fold() != 0)
    found = docs.select("doc_id", model.column("text").alias("found"))
    return found.select("doc_id", F.coalesce(fold() == 0, F.lit(False)).alias("held_out"), F.col("found.lang").alias("lang_pred"), F.col("found.score").alias("score"))


def op9_decontaminate(spark, sf_dir):
    from .decontaminate import leaks

    out = leaks(table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "benchmark"))
    return out.select("doc_id", F.inline("leaks"))


def op10_nearest(spark, sf_dir):
    from .hnsw import index, nearest

    points = table(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("long").alias("id"), F.col("embedding").alias("v"))
    out = nearest(index(points), points.where(F.col("id") % 20 == 0), 20)
    return out.select("query_id", "rank", F.col("id").alias("vec_id"), "score")


def pipeline(spark, sf_dir):
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


_QUERIES = [op1_substring_dedup, op2_sharding, op3_quality, op4_near_dup, op5_license_scan, op6_sentencepiece, op7_token_files, op8_language, op9_decontaminate, op10_nearest, pipeline]
_SQL = {"op1_substring_dedup": OP1_SQL, "op5_license_scan": _op5_sql()}


def queries():
    return {f.__name__: f for f in _QUERIES}


def oracle_sql():
    return dict(_SQL)

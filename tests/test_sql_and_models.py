"""SQL functions, the table function, learned topics, clustered signatures, and the library's hashing."""

from conftest import MIDDLE, SMALL
from pyspark.sql import functions as F

from pivotrank.functions import distances as D
from pivotrank.functions import sqlfunctions
from pivotrank.operators import measures as M
from pivotrank.operators import projections
from pivotrank.operators import search as S
from pivotrank.operators.permutation_indexes import SharedPivots
from pivotrank.sources import workloads as W


def test_functions_and_views(spark):
    names = sqlfunctions.register(spark)
    assert "rank_rho" in names
    points, queries = W.split(W.embeddings(spark, SMALL), 5)
    sqlfunctions.register_views(SharedPivots(points, "l2", 16, mi=4))
    queries.createOrReplaceTempView("asked")
    got = spark.sql("SELECT qid, id, l2_distance(p.x, q.x) AS dist FROM pivot_points p CROSS JOIN asked q")
    assert S.ranked(got, 3).select("qid", "id").exceptAll(S.exact_knn(points, queries, "l2", 3).select("qid", "id")).count() == 0
    r = spark.sql("SELECT rank_rho(array(1S, 2S), array(2S, 1S)) AS rho, rank_footrule(array(1S, 2S), array(2S, 1S)) AS foot, bits_hamming(array(5L), array(6L)) AS ham, norm_levenshtein('ab', 'b') AS lev, kl_divergence(array(0.5D, 0.5D), array(0.5D, 0.5D)) AS kl, js_divergence(array(0.5D, 0.5D), array(0.5D, 0.5D)) AS js, l1_distance(array(1D), array(3D)) AS l1").first()
    assert (r.rho, r.foot, r.ham, r.lev, r.kl, r.l1) == (2, 2, 2, 0.5, 0.0, 2.0) and abs(r.js) < 1e-12


def test_table_function(spark):
    points, queries = W.split(W.embeddings(spark, SMALL), 3)
    sqlfunctions.register_search(spark, points)
    queries.createOrReplaceTempView("asked")
    got = spark.sql("SELECT qid, s.id, s.rnk FROM asked, LATERAL knn_search(asked.x, 4) s")
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, S.exact_knn(points, queries, "l2", 4).select("qid", "id", "rnk").collect()))


def test_learned_topics_and_signatures(spark):
    x = W.topics_lda(spark, SMALL, 4).first()["x"]
    assert len(x["p"]) == 4 and abs(sum(x["p"]) - 1) < 1e-3
    signs = W.signatures_kmeans(spark, SMALL, "l_suppkey", 5)
    held = signs.select(F.size("x").alias("n"), F.aggregate("x", F.lit(0.0), lambda s, c: s + c["w"]).alias("w")).collect()
    assert all(1 <= r.n <= 5 and abs(r.w - 1) < 1e-9 for r in held)
    few = signs.limit(2).select("x")
    a = few.crossJoin(few.withColumnRenamed("x", "y")).select(D.sqfd(F.col("x"), F.col("y")).alias("d")).collect()
    assert min(r.d for r in a) < 1e-6


def test_library_hashing(spark):
    points, queries = W.split(W.embeddings(spark, MIDDLE), 10)
    assert M.recall(projections.spark_lsh(points, queries, 10, 2.0, 10), S.exact_knn(points, queries, "l2")).first()["recall"] > 0.5

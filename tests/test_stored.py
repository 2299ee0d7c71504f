"""The stored index, running bests, distances of objects, tuning, and streams."""

import numpy as np
import pytest
from conftest import MIDDLE
from pyspark.sql import functions as F

from pivotrank.functions import distances as D
from pivotrank.operators import ball_tree as B
from pivotrank.operators import measures as M
from pivotrank.operators import permutation_indexes as P
from pivotrank.operators import planner, projections, search, stored
from pivotrank.operators.pivots import select_pivots
from pivotrank.sources import tables
from pivotrank.sources import workloads as W
from pivotrank.streaming import incremental


def cloud(spark, n, dim=6, seed=1):
    rng = np.random.default_rng(seed)
    return spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(rng.random((n, dim)))], "id long, x array<double>")


def asked(points, n):
    return points.where(F.col("id") < n).select(F.col("id").alias("qid"), "x")


def test_kept_equals_sorting():
    rng = np.random.default_rng(2)
    keys, ids = rng.integers(0, 6, (7, 200)), rng.permutation(200)
    kept = search.Kept(7, 9)
    for a, b in ((0, 3), (3, 90), (90, 91), (91, 200)):
        for q, r in ((0, 4), (4, 7)):
            kept.add(q, keys[q:r, a:b], ids[a:b])
    got = sorted(zip(kept.q.tolist(), kept.key.tolist(), kept.id.tolist(), strict=True))
    assert got == sorted((q, int(k), int(i)) for q in range(7) for k, i in sorted(zip(keys[q], ids, strict=True))[:9])


def test_tasks_shuffle_their_own_best_only(spark, monkeypatch):
    held = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "50")  # many blocks a task
    try:
        pts = cloud(spark, 2000).repartition(2).persist()
        qs = asked(pts, 5)
        for score in ("hamming", "rho", "footrule", "pivot_l2"):
            index = P.ExhaustivePermutations(pts, "l2", 70, score=score)
            assert sorted(index.best(qs, gamma=30).collect()) == sorted(index.candidates(qs, gamma=30).collect())
        assert search.exact_knn(pts, qs, "l2", 3000).count() == 5 * 2000
        monkeypatch.setattr(search, "BLOCK_PAIRS", 100)  # tiles of two queries
        full = {(r.qid, r.rnk): r.id for r in search.exact_knn(pts, qs, "l2", 10).collect()}
        assert full == {(r.qid, r.rnk): r.id for r in search.exact_knn(pts.coalesce(1), qs, "l2", 10).collect()}
        monkeypatch.setattr(search, "ranked", lambda frame, k: frame)
        monkeypatch.setattr(P, "top_gamma", lambda frame, *_: frame)
        assert search.exact_knn(pts, qs, "l2", 10).count() == 2 * 5 * 10  # tasks, queries, k
        assert index.best(qs, gamma=30).count() == 2 * 5 * 30
    finally:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", held)


@pytest.mark.parametrize("dist", ["l2", "l1", "cosine"])
def test_stored_index(spark, tmp_path, dist):
    pts = cloud(spark, 3000)
    qs = asked(pts, 20)
    plain = P.SharedPivots(pts, dist, 64, mi=16)
    built = stored.build(pts, dist, 64, f"{tmp_path}/i", mi=16, chunk=500)
    assert spark.read.parquet(f"{tmp_path}/i/chunks").count() >= 3
    opened = stored.StoredSharedPivots(spark, f"{tmp_path}/i")
    for t in (1, 6, 16):
        assert sorted(opened.candidates(qs, t).collect()) == sorted(plain.candidates(qs, t=t).collect())
        got = {(r.qid, r.rnk): (r.id, round(r.dist, 9)) for r in built.search(qs, 10, t).collect()}
        assert got == {(r.qid, r.rnk): (r.id, round(r.dist, 9)) for r in plain.search(qs, 10, t=t).collect()}
    with pytest.raises(ValueError):
        opened.search(qs, 10, t=17)
    assert opened.search(qs.limit(0), 10).count() == 0
    assert M.index_bytes(spark, f"{tmp_path}/i") > 3000 * 40  # random payloads of 48 bytes hardly compress


def test_kullback_leibler_table_needs_a_mu(spark):
    pts = W.topics(spark, MIDDLE)
    with pytest.raises(ValueError, match="mu"):
        P.PivotTable(pts, "kl", 8)
    P.PivotTable(pts, "kl", 8, mu=2.0)


def test_object_distances_equal_column_ones(spark):
    for name, frame in (("norm_lev", W.sequences_drawn(spark, MIDDLE).limit(30)), ("sqfd", W.signatures(spark, MIDDLE).limit(12))):
        held = frame.orderBy("id").collect()
        d = D.distance(name)
        x = B.payloads([r.x for r in held], d.payload)
        got = d.between(x, x)
        pairs = frame.crossJoin(frame.select(F.col("id").alias("j"), F.col("x").alias("y"))).select("id", "j", d(F.col("x"), F.col("y")).alias("v")).collect()
        place = {r.id: i for i, r in enumerate(held)}
        assert all(abs(got[place[r.id], place[r.j]] - r.v) < 1e-6 for r in pairs)


def test_strings_without_letters():
    assert D.np_norm_lev(B.payloads(["", "ab", "abc"], "text"), B.payloads(["", "ab"], "text")).round(6).tolist() == [[0, 1], [1, 0], [1, round(1 / 3, 6)]]


def test_sparse_cosine_fills_up(spark):
    terms = spark.createDataFrame([(1, "a", 1.0), (2, "b", 1.0), (3, "c", 2.0), (4, "c", 1.0)], "id long, term string, w double")
    got = search.exact_sparse_cosine(terms, spark.createDataFrame([(9, "a", 1.0)], "qid long, term string, w double"), 3).orderBy("rnk").collect()
    assert [(r.id, r.dist) for r in got] == [(1, 0.0), (2, 1.0), (3, 1.0)]


def test_tuning_on_small_sets(spark):
    pts = cloud(spark, 400, 4)
    qs = asked(cloud(spark, 10, 4, seed=8), 10)
    m, found = planner.tune_m(pts, qs, "l2", (8, 32), gamma=60)
    assert m in (8, 32) and found > 0.8
    assert planner.in_window(0.9) and not planner.in_window(0.99)
    size, decay, held = planner.tune_graph(pts, "l2", grid=(10,), decays=(0.9,))
    assert (size, decay) == (10, 0.9) and held > 0.6
    truth = search.exact_knn(pts, qs, "l2").persist()
    tree = B.BallTree.build(pts, "l2", 40)
    alpha = B.tune_pruner(tree, qs, truth, target=0.9, rounds=1)
    assert M.recall(tree.search(qs, 10, alpha), truth).first()["recall"] >= 0.9
    tied = truth.where("rnk <= 10").withColumn("id", F.col("id") + 1000)
    assert M.recall(tied, truth, ties=True).first()["recall"] == 1.0 and M.recall(tied, truth).first()["recall"] == 0.0


def test_bucketed_table_joins_without_shuffle(spark):
    a = tables.write_bucketed(cloud(spark, 100).select("id"), "bucketed_points", ["id"], 4)
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        plan = a.join(a.withColumnRenamed("id", "j"), F.col("id") == F.col("j"))._jdf.queryExecution().executedPlan().toString()
        assert "Exchange" not in plan
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
        spark.sql("DROP TABLE bucketed_points")


def test_points_and_queries_arrive_by_stream(spark, tmp_path):
    pts = cloud(spark, 300)
    pts.where("id < 150").write.parquet(f"{tmp_path}/in/a")
    pivots = select_pivots(pts, 16)
    source = lambda where: spark.readStream.schema("id long, x array<double>").option("recursiveFileLookup", True).parquet(where)
    run = lambda: incremental.append_stream(spark, source(f"{tmp_path}/in"), pivots, "l2", 4, f"{tmp_path}/postings", f"{tmp_path}/state").awaitTermination()
    run()
    pts.where("id >= 150").write.parquet(f"{tmp_path}/in/b")
    run()
    held = spark.read.parquet(f"{tmp_path}/postings").select("pid", "id")
    expected = P.SharedPivots(pts, "l2", 16, mi=4, pivots=pivots).postings.select(F.col("pid").cast("int"), "id")
    assert sorted(held.selectExpr("cast(pid AS int) pid", "id").collect()) == sorted(expected.collect())
    incremental.compact(held, pts.where("id % 2 = 0").select("id"), f"{tmp_path}/live")
    assert spark.read.parquet(f"{tmp_path}/live").where("id % 2 = 0").isEmpty() and spark.read.parquet(f"{tmp_path}/live").count() == 150 * 4

    index = stored.build(pts, "l2", 16, f"{tmp_path}/index", mi=4)
    asked(pts, 7).write.parquet(f"{tmp_path}/asked")
    stream = spark.readStream.schema("qid long, x array<double>").parquet(f"{tmp_path}/asked")
    incremental.search_stream(stream, index, 3, f"{tmp_path}/answers", f"{tmp_path}/state2", t=1).awaitTermination()
    got = spark.read.parquet(f"{tmp_path}/answers").select("qid", "id", "rnk")
    assert sorted(got.collect()) == sorted(index.search(asked(pts, 7), 3).select("qid", "id", "rnk").collect())


def test_stateful_streams(spark, tmp_path):
    events = spark.createDataFrame(
        [(1, "2024-01-01 10:00:00", 5, "view"), (1, "2024-01-01 10:00:00", 5, "view"), (2, "2024-01-01 10:30:00", 5, "purchase"), (3, "2024-01-01 12:00:00", 6, "view"), (4, "2024-01-01 14:30:00", 6, "purchase")],
        "event_id long, t string, user_id long, event_type string",
    ).select("event_id", F.col("t").cast("timestamp").alias("ts"), "user_id", "event_type")
    events.write.parquet(f"{tmp_path}/events")
    stream = lambda: spark.readStream.schema(events.schema).parquet(f"{tmp_path}/events")
    assert sorted(r.event_id for r in incremental.drain(incremental.first_seen(stream()), "first_seen").collect()) == [1, 2, 3, 4]
    got = incremental.drain(incremental.running_mix(stream()), "running", "update").collect()
    assert sorted((r.user_id, r.n, r["view"], r.purchase) for r in got) == [(5, 3, 2, 1), (6, 2, 1, 1)]
    met = incremental.drain(incremental.views_before_purchases(stream()), "bought").collect()
    assert {(r.view_id, r.buy_id) for r in met} == {(1, 2)}

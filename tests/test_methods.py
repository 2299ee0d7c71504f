"""Worked example, equivalences, accuracy by shape, plans, and refusals."""

import numpy as np
import pytest
from conftest import MIDDLE
from pyspark.sql import functions as F

from pivotrank.functions import distances as D
from pivotrank.operators import graphs as G
from pivotrank.operators import measures as M
from pivotrank.operators import permutation_indexes as P
from pivotrank.operators import planner, projections
from pivotrank.operators import search as S
from pivotrank.operators.ball_tree import BallTree
from pivotrank.operators.pivots import see, select_pivots
from pivotrank.sources import tables
from pivotrank.sources import workloads as W


@pytest.fixture(scope="module")
def world(spark):
    points, queries = W.split(W.embeddings(spark, MIDDLE), 40)
    points, queries = points.persist(), queries.persist()
    return points, queries, S.exact_knn(points, queries, "l2").persist()


def rows(frame):
    return sorted(tuple(r) for r in frame.collect())


def test_worked_example(spark):
    ranks = {"a": [1, 2, 3, 4], "b": [1, 2, 4, 3], "c": [2, 3, 1, 4], "d": [3, 2, 4, 1]}
    pts = spark.createDataFrame(list(ranks.items()), "p string, rank array<int>")
    bits = {r.p: r.b for r in pts.select("p", D.pack_bits(F.col("rank"), 4, 3)[0].alias("b")).collect()}
    assert bits == {"a": 0b1100, "b": 0b1100, "c": 0b1010, "d": 0b0101}  # pivot 1 is the lowest bit


def test_distances_agree_with_numpy(spark):
    rng = np.random.default_rng(0)
    x, y = rng.random((6, 5)), rng.random((4, 5))
    x[0] = y[0]
    payload = lambda v: v.tolist()
    hist = lambda v: (v.tolist(), np.log(v).tolist())
    for name, make, kind in (("l2", payload, "array<double>"), ("l1", payload, "array<double>"), ("cosine", payload, "array<double>"), ("kl", hist, "struct<p: array<double>, logp: array<double>>"), ("js", hist, "struct<p: array<double>, logp: array<double>>")):
        a = spark.createDataFrame([(i, make(v)) for i, v in enumerate(x)], f"i int, a {kind}")
        b = spark.createDataFrame([(i, make(v)) for i, v in enumerate(y)], f"j int, b {kind}")
        for side in ("left", "right"):
            d = D.distance(name)
            got = {(r.i, r.j): r.d for r in a.crossJoin(b).select("i", "j", d(F.col("a"), F.col("b"), side).alias("d")).collect()}
            expected = d.between(x, y, side)
            assert all(abs(got[i, j] - expected[i, j]) < 1e-9 for i in range(6) for j in range(4)), (name, side)


def test_text_and_zero_distances(spark):
    r = spark.range(1).select(D.norm_levenshtein(F.lit(""), F.lit("")).alias("e"), D.norm_levenshtein(F.lit("ab"), F.lit("")).alias("f"), D.cosine_dense(F.array(F.lit(0.0)), F.array(F.lit(1.0))).alias("z"), D.cosine_dense(F.array(F.lit(0.0)), F.array(F.lit(0.0))).alias("zz")).first()
    assert (r.e, r.f, r.z, r.zz) == (0.0, 1.0, 1.0, 0.0)


def test_permutations_are_bijections(world):
    points, _, _ = world
    seen = see(points, select_pivots(points, 16), "l2").limit(50).collect()
    for r in seen:
        assert sorted(r.rank) == list(range(1, 17)) and sorted(r.ord) == list(range(1, 17))
        assert all(r.rank[p - 1] == i + 1 for i, p in enumerate(r.ord))


def test_heap_equals_counting_and_scan(world):
    points, queries, _ = world
    index = P.ExhaustivePermutations(points, "l2", 32, score="hamming")
    a, b, c = (rows(x.select("qid", "id")) for x in (index.candidates(queries, 60, "heap"), index.candidates(queries, 60, "counting"), index.best(queries, 60)))
    assert a == b == c and len(a) == 60 * 40


def test_merges_agree(world):
    points, queries, _ = world
    found = [rows(P.SharedPivots(points, "l2", 64, mi=16, chunks=n).candidates(queries, t=5, merge=m).select("qid", "id")) for n, m in ((1, "scancount"), (4, "scancount"), (1, "forward"), (1, "scan"))]
    assert all(f == found[0] for f in found)


def test_whole_postings_are_exact(world):
    points, queries, _ = world
    pivots = select_pivots(points, 16)
    for score in ("rho", "footrule"):
        a = rows(P.RankPostings(points, "l2", 16, mi=16, pivots=pivots).scores(queries, 16, score))
        b = rows(P.ExhaustivePermutations(points, "l2", 16, pivots=pivots, score=score).scores(queries).select("qid", "id", "score"))
        assert a == b


def test_all_candidates_give_the_exact_answer(world):
    points, queries, truth = world
    assert rows(P.ExhaustivePermutations(points, "l2", 8).search(queries, 10, gamma=1.0).select("qid", "id", "rnk")) == rows(truth.select("qid", "id", "rnk"))
    assert rows(P.PrefixIndex(points, "l2", 8, 4).search(queries, 10, gamma=1.0).select("qid", "id", "rnk")) == rows(truth.select("qid", "id", "rnk"))


def test_recall_moves_as_reported(world):
    points, queries, truth = world
    pivots = select_pivots(points, 64)
    at = lambda score, gamma: M.recall(P.ExhaustivePermutations(points, "l2", 64, score=score, pivots=pivots).search(queries, 10, gamma=gamma), truth).first()["recall"]
    rho, foot, ham = (at(s, 100) for s in ("rho", "footrule", "hamming"))
    assert at("rho", 25) <= at("rho", 50) <= rho and rho >= foot - 0.02 and foot >= ham - 0.02 and rho > 0.7


def test_tree_prunes_exactly_and_polynomials_trade(world):
    points, queries, truth = world
    tree = BallTree.build(points, "l2", 20)
    assert rows(tree.search(queries, 10).select("qid", "id")) == rows(truth.select("qid", "id"))
    harsh = M.recall(tree.search(queries, 10, alpha=(8.0, 8.0)), truth).first()["recall"]
    assert harsh <= 1.0 and tree.read_points(queries, 10, (8.0, 8.0)) < tree.read_points(queries, 10)


def test_graphs_find_neighbours(world):
    points, queries, truth = world
    exact = G.exact_graph(points, "l2", 8)
    built = G.nn_descent(points, "l2", 8, max_iter=6)
    hit = built.select("src", "dst").join(exact.select("src", "dst"), ["src", "dst"]).count() / exact.count()
    assert hit > 0.6
    both = exact.unionByName(exact.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "dist")).distinct()
    beam = M.recall(G.graph_search(both, points, queries, "l2", 10, 5, 40), truth).first()["recall"]
    assert beam > 0.9


def test_probes_add_recall(world):
    points, queries, truth = world
    tool = projections.MultiProbe(points, 64, 6, 4, 2.0, 4096)
    few, many = (M.recall(tool.search(queries, 10, n), truth).first()["recall"] for n in (0, 8))
    assert few <= many


def test_tuning(world):
    points, queries, truth = world
    index = P.SharedPivots(points, "l2", 64, mi=16)
    t, _ = planner.tune_t(index, queries, truth, 0.9)
    assert M.recall(index.search(queries, 10, t=t), truth).first()["recall"] >= 0.9
    gamma = planner.tune_gamma(P.ExhaustivePermutations(points, "l2", 64), queries, truth, 0.9)
    assert M.recall(P.ExhaustivePermutations(points, "l2", 64).search(queries, 10, gamma=gamma), truth).first()["recall"] >= 0.85
    assert planner.choose(10**9, 1, 64, 100, True).method == "shared_pivots" and planner.choose(10**9, 1, 4, 100, True).method == "ball_tree"


def test_refusals_and_edges(spark, world):
    points, queries, _ = world
    with pytest.raises(ValueError):
        select_pivots(points, 4000)
    with pytest.raises(ValueError):
        P.SharedPivots(points, "l2", 8, mi=9)
    with pytest.raises(ValueError):
        P.SharedPivots(points, "l2", 16, mi=8).candidates(queries, t=9)
    with pytest.raises(ValueError):
        D.distance("nothing")
    with pytest.raises(ValueError):
        BallTree.build(points, "l2", 1)
    assert S.exact_knn(points.limit(3), queries.limit(1), "l2", 10).count() == 3  # k above the points
    assert S.exact_knn(points, queries.limit(0), "l2", 10).count() == 0
    assert S.exact_knn(points.limit(0), queries, "l2", 10).count() == 0


def test_plans_keep_points_in_place(world):
    points, queries, _ = world
    plan = lambda f: f._jdf.queryExecution().executedPlan().toString()
    seen = see(points, select_pivots(points, 8), "l2")
    assert "Exchange hash" not in plan(seen) and "Exchange Single" not in plan(seen)
    assert "Exchange hash" not in plan(P.SharedPivots(points, "l2", 32, mi=8).scan(queries, 2))


def test_files_round_trip(spark, world, tmp_path):
    points, _, _ = world
    index = P.SharedPivots(points, "l2", 16, mi=4)
    tables.write_index(index.postings.select("pid", "id"), str(tmp_path / "i"), ["pid"], m=16, mi=4)
    back, manifest = tables.read_index(spark, str(tmp_path / "i"))
    assert manifest == {"m": 16, "mi": 4} and rows(back.select("pid", "id")) == rows(index.postings.select("pid", "id"))
    for kind in ("json", "orc", "parquet"):
        tables.write_points(points.limit(5), str(tmp_path / kind), kind)
        assert tables.read_points(spark, str(tmp_path / kind), kind, "id long, x array<double>").count() == 5
    tables.write_points(points.limit(5), str(tmp_path / "csv"), "csv")
    assert tables.read_points(spark, str(tmp_path / "csv"), "csv", "id long, x string").select(F.from_json("x", "array<double>").alias("x")).first()["x"]

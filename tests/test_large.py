"""What the queries do on larger tables, at small sizes: the ways for many points give what the ways for few give."""

import pytest
from conftest import MIDDLE, SMALL
from pyspark.sql import functions as F

from pivotrank.operators import graphs as G
from pivotrank.operators import search as S
from pivotrank.sources import workloads as W


def rows(frame, *columns):
    return sorted(tuple(round(v, 6) if isinstance(v, float) else v for v in r) for r in frame.select(*columns).collect())


@pytest.fixture(scope="module")
def world(spark):
    return W.split(W.embeddings(spark, SMALL), 20)


@pytest.mark.parametrize("dist", ["l2", "l1"])
def test_exact_graph_has_more_points_than_a_search_takes_queries(world, dist, monkeypatch):
    points, _ = world
    asked = points.select(F.col("id").alias("qid"), "x")
    truth = rows(S.exact_knn(points, asked, dist, 6).where("qid <> id"), "qid", "id", "dist")
    monkeypatch.setattr(S, "MOST_QUERIES", 100)
    found = G.exact_graph(points, dist, 5)
    assert rows(found, "src", "dst", "dist") == truth and found.count() == 5 * points.count()


def test_exact_graph_with_repeated_ids_and_few_points(spark):
    points = spark.createDataFrame([(1, [0.0]), (1, [1.0]), (2, [1.0]), (3, [5.0])], "id long, x array<double>")
    assert rows(G.exact_graph(points, "l2", 3), "src", "dst", "dist") == [(1, 2, 0.0), (1, 2, 1.0), (1, 3, 4.0), (2, 1, 0.0), (2, 1, 1.0), (2, 3, 4.0), (3, 1, 4.0), (3, 1, 5.0), (3, 2, 4.0)]
    assert G.exact_graph(points.where("id = 3"), "l2", 3).count() == 0 == G.exact_graph(points.where("id > 3"), "l2", 3).count()


def test_walks_and_descent_in_tasks_equal_those_by_joins(world, monkeypatch):
    points, queries = world
    edges = G.exact_graph(points, "l2", 6)
    both = edges.unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "dist")).distinct()
    made = lambda: [rows(G.graph_search(both, points, queries, "l2", 5, 3, ef), "qid", "id", "rnk", "dist") for ef in (1, 8)] + [rows(G.nn_descent(points, "l2", 6, max_iter=3), "src", "dst", "dist")]
    here = made()
    monkeypatch.setattr(G, "GATHERED", 0)
    assert here == made()


def test_exact_graph_is_computed_once_and_both_ways_agree(world, monkeypatch):
    points, _ = world
    found = G.exact_graph(points, "l2", 6)
    assert "MapInArrow" not in found._jdf.queryExecution().executedPlan().toString()
    monkeypatch.setattr(G, "GATHERED", 0)
    by_cells = G.exact_graph(points, "l2", 6)
    assert "MapInArrow" not in by_cells._jdf.queryExecution().executedPlan().toString()
    assert rows(by_cells, "src", "dst", "dist") == rows(found, "src", "dst", "dist")


def test_descent_hands_pairs_on_in_bounded_batches(world, spark, monkeypatch):
    points, _ = world
    d = G.distance("l2")
    sent = spark.sparkContext.broadcast(G._gathered(points, d))
    ids = sent.value[0].tolist()
    near = spark.createDataFrame([(v, u, True) for v in ids[:80] for u in ids[:40]], "v long, u long, fresh boolean").coalesce(1)
    edges = spark.createDataFrame([(ids[0], ids[-1], 1e9)], "src long, dst long, dist double")
    made = lambda: G._joined_here(near, edges, sent, d, 1)
    whole = rows(made(), "src", "dst", "dist")
    monkeypatch.setattr(G, "PAIRS", 100)
    assert rows(made(), "src", "dst", "dist") == whole and len(whole) == 40 * 39


def test_a_batch_of_the_small_world_is_one_pass(world, spark):
    points, _ = world
    tracker = spark.sparkContext.statusTracker()
    spark.sparkContext.setJobGroup("small world", "small world")
    edges = G.small_world(points, "l2", 5, first=64)
    jobs = len(tracker.getJobIdsForGroup("small world"))
    spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    assert edges.select("src").distinct().count() == points.count() and jobs < 90


def test_trigram_counts_equal_a_plain_count():
    import random

    import pyarrow as pa

    draw = random.Random(5)
    texts = ["".join(draw.choice("abCDz éKK\n") for _ in range(draw.choice((0, 1, 2, 3, 5, 40, 700)))) for _ in range(60)] + [None, "", "ab", "abc", "x" * 9]
    expected = []
    for t in texts:
        s = [ord(c.lower()) for c in t or "" if c.isascii() and c.isalpha()]
        row = [0] * 282
        for i in range(len(s) - 2):
            row[(s[i] * 961 + s[i + 1] * 31 + s[i + 2]) % 282] += 1
        expected.append(row)
    for most in (1, 100, 1 << 20):
        assert W.trigram_counts(pa.array(texts), 282, most).tolist() == expected
    assert W.trigram_counts(pa.array(texts).slice(7, 30), 282).tolist() == expected[7:37]


def test_descriptors_make_no_row_for_a_trigram(spark):
    frame = W.descriptors(spark, SMALL, normalise=True)
    plan = frame._jdf.queryExecution().executedPlan().toString()
    assert "Generate" not in plan and "Exchange" not in plan


def test_descriptors_put_rows_of_one_id_together(spark, tmp_path):
    rows_ = [(1, "abcd"), (1, "Abc"), (2, "xyz"), (3, "no"), (4, None)]
    spark.createDataFrame(rows_, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = {r["id"]: r["x"] for r in W.descriptors(spark, str(tmp_path)).collect()}
    assert set(got) == {1, 2} and sum(got[1]) == 3.0 and max(got[1]) == 2.0
    shares = {r["id"]: r["x"] for r in W.descriptors(spark, str(tmp_path), normalise=True).collect()}
    assert abs(sum(shares[1]) - 1) < 1e-12 and max(shares[1]) == 2 / 3


def test_edit_distance_by_bits_equals_the_table():
    import random

    import numpy as np

    from pivotrank.functions.distances import np_norm_lev

    def plain(a, b):
        row = list(range(len(b) + 1))
        for i, c in enumerate(a, 1):
            new = [i]
            for j, e in enumerate(b, 1):
                new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (c != e)))
            row = new
        return row[-1] / max(1, len(a), len(b))

    draw = random.Random(3)
    some = lambda letters, sizes: "".join(draw.choice(letters) for _ in range(draw.choice(sizes)))
    for letters in ("ACGT", "aé中\U0001f600"):
        x = np.array(["", *[some(letters, range(90)) for _ in range(40)]], object)
        y = np.array(["", *[some(letters, (1, 5, 31, 63, 64, 65, 80)) for _ in range(20)]], object)
        assert np_norm_lev(x, y).tolist() == [[plain(a, b) for b in y] for a in x]


def test_tree_deals_its_points_once_and_measures_pivots_at_once(spark):
    from pivotrank.operators.ball_tree import BallTree

    points, queries = W.split(W.sequences_drawn(spark, SMALL), 5)
    tree = BallTree.build(points, "norm_lev", 10)
    assert tree.assigned() is tree.assigned()
    calls = []
    real = type(tree.dist).between
    try:
        type(tree.dist).between = lambda self, *a: calls.append(1) or real(self, *a)
        tree.visits(queries, 3)
    finally:
        type(tree.dist).between = real
    assert len(calls) <= len(tree.nodes) + 1  # home leaves, and one call for all pivots of all queries
    truth = S.exact_knn(points, queries, "norm_lev", 3)
    assert tree.search(queries, 3, alpha=(0.0, 0.0)).exceptAll(truth).isEmpty()


def test_worked_example_keeps_its_golden_values(spark):
    from pivotrank.functions import distances as D

    toy = {"a": [1, 2, 3, 4], "b": [1, 2, 4, 3], "c": [2, 3, 1, 4], "d": [3, 2, 4, 1]}
    frame, q = spark.createDataFrame(list(toy.items()), "point string, rank array<int>").where("point <> 'a'"), F.array(*[F.lit(v) for v in toy["a"]])
    made = frame.select("point", D.footrule(F.col("rank"), q), D.rho(F.col("rank"), q), D.hamming(D.pack_bits(F.col("rank"), 4, 3), D.pack_bits(q, 4, 3)))
    assert sorted(map(tuple, made.collect())) == [("b", 2, 2, 0), ("c", 4, 6, 2), ("d", 6, 14, 2)]
    posts = {p: {i: r for i, r in enumerate(rank) if r <= 2} for p, rank in toy.items()}
    score = {p: 8 - sum(4 - abs(r - posts["a"][i]) for i, r in own.items() if i in posts["a"]) for p, own in posts.items() if p != "a"}
    assert score == {"b": 0, "c": 5, "d": 4}


@pytest.mark.parametrize("name", ["perm_bytes", "postings_toy", "toy_example", "exact_levenshtein_drawn"])
def test_queries_read_a_table_and_equal_their_sql(spark, duck, name):
    from conftest import same

    from pivotrank.plans import registry

    frame = registry.queries()[name](spark, MIDDLE)
    assert any(p.endswith((".parquet", ".parquet/")) for p in frame.inputFiles())
    assert same(frame, duck.sql(registry.oracle_sql()[name]))

"""Reduced vectors, n-gram vectors, the grid of one join, and the comparison of all methods."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from knnvote.functions.vectors import normalize
from knnvote.operators import experiments as ex
from knnvote.operators import forest as fo
from knnvote.operators import measures as me
from knnvote.operators import reduction as rd
from knnvote.operators import search as se
from knnvote.plans.config import ForestParams
from knnvote.sources import tables as ta

P = ForestParams(trees=4, depth=3)


def test_singular_basis_agrees_with_numpy(spark):
    x = np.random.default_rng(1).standard_normal((60, 8)) * np.arange(1, 9)
    points = spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(x)], "id long, vec array<float>")
    basis = rd.singular_basis(points, 3)
    assert np.allclose(basis.values, np.linalg.svd(x)[1][:3], rtol=1e-4)
    near = {r.id: r.vec for r in basis.reduced(points, unit=False).collect()}
    assert all(np.allclose(near[i], x[i] @ basis.vectors, atol=1e-3) for i in range(60))


def test_singular_basis_of_less_rank_and_too_many_dimensions(spark):
    points = spark.createDataFrame([(1, [1.0, 0.0]), (2, [2.0, 0.0]), (3, [0.0, 0.0])], "id long, vec array<float>")
    basis = rd.singular_basis(points, 2)
    assert basis.vectors.shape == (2, 1)
    assert {r.id: list(r.vec) for r in basis.reduced(points).collect()} == {1: [1.0], 2: [1.0], 3: [0.0]}
    with pytest.raises(ValueError):
        rd.gram_matrix(points, rd.MAX_DIMS + 1)


def test_normalize_of_long_vectors(spark):
    r = spark.range(1).select(normalize(F.transform(F.sequence(F.lit(1), F.lit(5000)), lambda i: i.cast("double"))).alias("v")).first()
    want = np.arange(1, 5001) / np.linalg.norm(np.arange(1, 5001))
    assert np.allclose(r.v, want)


def test_character_ngrams(spark):
    texts = [(1, "abcABC"), (2, "a\U0001f600b\nc"), (3, "ab"), (4, ""), (5, None)]
    docs = spark.createDataFrame(texts, "id long, text string")
    wide = {r.id: np.array(r.vec) for r in ta.char_ngrams(docs, "id", "text", 4096).collect()}
    assert set(wide) == {1, 2} and all(abs((v * v).sum() - 1) < 1e-5 for v in wide.values())
    assert sorted(np.round(wide[1][wide[1] > 0] ** 2 * 6).astype(int)) == [1, 1, 4] and (wide[2] > 0).sum() == 3
    narrow = {r.id: np.array(r.vec) for r in ta.char_ngrams(docs, "id", "text", 64).collect()}
    assert set(narrow) == {1, 2}


def test_grid_equals_searches_one_by_one(spark):
    points, queries = ta.hold_out(fo.materialised(ta.gaussian_sphere(spark, 200, 12), "points"), 20)
    forest = fo.build_forest(points, P)
    truth = fo.materialised(se.brute_force_knn(points, queries, 5), "truth")
    for r in me.grid_recall(forest, queries, truth, 5, [2, 4], [2, 3], [1, 2]).collect():
        cands = fo.materialised(se.candidates(queries, forest.slice(r.trees, r.depth), r.votes), "c")
        hits = cands.join(truth, ["qid", "id"], "left_semi").count()
        assert (r.candidates, r.recall) == (cands.count(), round(hits / 100, 6))


def test_costs_rise_with_budgets_and_bounds_hold(spark):
    points, queries = ta.hold_out(fo.materialised(ta.gaussian_sphere(spark, 200, 12), "points"), 20)
    runs = ex.compare("sphere", points, queries, 5, P, {"trees": [2, 4], "depths": [2, 3], "votes": [1, 2]}, graph=False)
    rows = runs.collect()
    assert {r.method for r in rows} == {"dense_forest", "sparse_forest", "voting_forest", "kd_tree", "kd_forest", "kmeans_tree", "cross_polytope", "brute_force"}
    assert [r.recall for r in rows if r.setting == "eps=0.0"] == [1.0] and all(r.evals <= 180 * 20 for r in rows)
    leaves = sorted((int(r.setting.split("=")[-1]), r.evals, r.recall) for r in rows if r.method == "kmeans_tree")
    assert all(a[1] <= b[1] and a[2] <= b[2] for a, b in zip(leaves, leaves[1:], strict=False)) and leaves[-1][2] == 1.0
    best = {(r.method, r.level): r for r in ex.cost_to_recall(runs).collect()}
    assert best["brute_force", 0.99].speedup == 1.0 and best["kd_tree", 0.99].evals <= 3600


def test_kmeans_tree_of_double_vectors(spark):
    from knnvote.operators import baselines as ba

    points = spark.createDataFrame([(i, [float(i % 4), float(i)]) for i in range(40)], "id long, vec array<double>")
    queries = points.where("id < 3").select(F.col("id").alias("qid"), F.col("vec").alias("qvec"))
    assert {(r.qid, r.id) for r in ba.kmeans_tree(points, 2, 2).search(queries, 1, 4).collect()} == {(0, 0), (1, 1), (2, 2)}


def test_frontier_keeps_the_least_setting_of_equal_runs(spark):
    rows = [(8, 3, 2, 0.5, 10), (4, 4, 2, 0.5, 10), (4, 3, 8, 0.5, 10), (4, 3, 2, 0.5, 10), (4, 2, 1, 0.9, 30), (16, 2, 1, 0.9, 30), (8, 2, 1, 0.4, 20)]
    for order in (rows, rows[::-1], rows[2:] + rows[:2]):
        runs = spark.createDataFrame(order, "trees int, depth int, votes int, recall double, candidates long").coalesce(1)
        assert sorted(map(tuple, me.frontier(runs, "candidates").collect())) == [(4, 2, 1, 0.9, 30), (4, 3, 2, 0.5, 10)]


def test_letter_pairs_and_words_of_odd_texts(spark, tmp_path):
    rows = [(1, "abcABC"), (2, "a\U0001f600b\nc \u212aelvin"), (3, "a b"), (4, ""), (5, None), (6, "x" * 5000 + " the"), (6, "the the")]
    spark.createDataFrame(rows, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    place = lambda gram, d: ta._bucket_of(gram.encode(), d)
    got = {r.id: np.array(r.vec) for r in ta.letter_bigrams(spark, str(tmp_path)).collect()}
    assert set(got) == {1, 2, 6}
    want = np.zeros(784)
    for gram, n in (("ab", 2), ("bc", 2), ("ca", 1)):
        want[place(gram, 784)] += n
    assert np.allclose(got[1], want / 3)
    want = np.zeros(784)
    for gram, n in (("xx", 4999), ("th", 3), ("he", 3)):  # both rows of a document, and no pair across their ends
        want[place(gram, 784)] += n
    assert np.allclose(got[6], want / np.linalg.norm(want))
    docs = ta.load(spark, str(tmp_path), "documents")
    words = {r.id: np.array(r.vec) for r in ta.word_counts(docs, "doc_id", "text", 512, idf=False).collect()}
    assert set(words) == {1, 2, 3, 6} and np.isclose(words[6][place("the", 512)], 3 / np.sqrt(10))
    assert "Generate" not in ta.word_counts(docs, "doc_id", "text", 512)._jdf.queryExecution().executedPlan().toString()  # a row a text, not a row a word


def test_budgets_count_pairs_without_making_them(spark):
    from knnvote.operators import baselines as ba

    points, queries = ta.hold_out(fo.materialised(ta.gaussian_sphere(spark, 200, 12), "points"), 20)
    truth = fo.materialised(se.brute_force_knn(points, queries, 5), "truth")
    forest = ba.axis_forest(points, 3, 3, top_dims=5)
    visits = fo.materialised(forest.visits(queries, 8), "visits")
    for r in ex.budget_runs(visits, forest.codes, truth, 5, 20, [1, 4, 8]).collect():
        met = forest.cells.join(visits.where(F.col("nth") <= r.budget), ["part", "cell"]).select("qid", "id").distinct()
        assert (r.evals, r.recall) == (met.count(), round(met.join(truth, ["qid", "id"]).count() / 100, 6))


def test_tree_methods_split_and_build_alike_from_blocks(spark, monkeypatch):
    from knnvote.operators import baselines as ba
    from knnvote.operators.blocks import packed

    points = fo.materialised(ta.gaussian_sphere(spark, 300, 12).unionByName(ta.gaussian_sphere(spark, 40, 12).select((F.col("id") + 1000).alias("id"), "vec")), "points")
    held = packed(points)
    assert sum(len(ids) for ids, in held.table.selectExpr("unhex(hex(ids))").collect()) == 8 * 340
    one, two = fo.build_forest(points, P), fo.build_forest(points, P, held)
    assert np.allclose(one.splits, two.splits) and sorted(map(tuple, one.codes.collect())) == sorted(map(tuple, two.codes.collect()))
    small = ba.axis_forest(points, 2, 3, top_dims=5, held=held)
    monkeypatch.setattr(ba, "LOCAL_ROWS", 100)
    large = ba.axis_forest(points, 2, 3, top_dims=5, held=held)
    assert np.array_equal(small.axes, large.axes) and np.allclose(small.cuts, large.cuts)


def test_graph_lists_hold_the_nearest_that_were_tried(spark):
    from knnvote.operators import baselines as ba

    x = np.random.default_rng(3).integers(0, 3, (300, 24)).astype(float)  # many copies of values: packed by a byte a place
    points = fo.materialised(spark.createDataFrame([(7 * i - 50, v.tolist()) for i, v in enumerate(x)], "id long, vec array<double>"), "points")
    rows = ba.knn_graph(points, 10, delta=0.0).edges.collect()
    hits = 0
    for i in range(300):
        far = np.round(np.sqrt(((x - x[i]) ** 2).sum(1)), 6)
        own = [(r.distance, r.v) for r in rows if r.u == 7 * i - 50]
        assert len(own) == 10 and all(d == far[(v + 50) // 7] for d, v in own) and 7 * i - 50 not in [v for _, v in own]
        far[i] = np.inf
        hits += sum(d <= np.sort(far)[9] for d, _ in own)
    assert hits > 0.9 * 3000
    codes = [ba._squeezed(v) for v in x] + [ba._squeezed(np.arange(24.0))]
    assert len(codes[0]) < 24 * 8 and np.array_equal(ba._spread_out(codes, "<f8", 24), np.vstack([x, np.arange(24.0)]))


def test_weighted_words_equal_plain_counts(spark):
    rows = [(i, " ".join(w for j, w in enumerate(("ant", "bee", "cat", "dog", "eel")) for _ in range((i * j) % 4))) for i in range(12)]
    docs = spark.createDataFrame(rows, "id long, text string")
    got = {r.id: np.array(r.vec) for r in ta.word_counts(docs, "id", "text", 300).collect()}
    counts = {}
    for i, text in rows:
        for w in text.split():
            v = counts.setdefault(i, np.zeros(300))
            v[ta._bucket_of(w.encode(), 300)] += 1
    weight = np.log(12 / np.maximum(1, sum(v > 0 for v in counts.values())))
    assert set(got) == set(counts)
    for i, v in counts.items():
        want = v * weight
        assert np.allclose(got[i], want / (np.linalg.norm(want) or 1))

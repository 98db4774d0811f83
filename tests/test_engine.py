"""Invariants of forests, votes, searches and comparison methods on generated and given vectors."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from knnvote.operators import baselines as ba
from knnvote.operators import forest as fo
from knnvote.operators import measures as me
from knnvote.operators import search as se
from knnvote.operators.projection import directions
from knnvote.plans import published
from knnvote.plans.config import ForestParams, VectorSchemaError
from knnvote.sources import tables as ta

P = ForestParams(trees=6, depth=3)


@pytest.fixture(scope="module")
def setting(spark):
    pts = fo.materialised(ta.gaussian_sphere(spark, 300, 16), "points")
    points, queries = ta.hold_out(pts, 20)
    return fo.materialised(points, "points"), fo.materialised(queries, "queries")


@pytest.fixture(scope="module")
def forest(setting):
    return fo.build_forest(setting[0], P)


def answers(df):
    return {(r.qid, r.rank): (r.id, r.distance) for r in df.collect()}


def test_directions(spark):
    rows = directions(spark, ForestParams(trees=8, depth=4), 64).collect()
    w = np.array([r.weight for r in rows])
    assert abs(len(rows) / (8 * 4 * 64) - 1 / 8) < 0.03 and abs(w.mean()) < 0.15 and abs(w.std() - 1) < 0.15
    assert len({(r.tree, r.level) for r in rows}) == 32
    exact = directions(spark, ForestParams(trees=2, depth=2, nnz="exact"), 64).groupBy("tree", "level").count().collect()
    assert {r["count"] for r in exact} == {8}


def test_leaves_are_even_and_complete(forest):
    for r in me.leaf_balance(forest).collect():
        assert r.points == 280 and r.leaves == 8 and r.largest - r.smallest <= 1


def test_a_point_reaches_its_own_leaves(setting, forest):
    own = setting[0].limit(15).select(F.col("id").alias("qid"), F.col("vec").alias("qvec"))
    votes = {(r.qid, r.id): r.votes for r in se.candidates(own, forest, 1).collect()}
    assert all(votes[(r.qid, r.qid)] == P.trees for r in own.collect())


def test_votes_narrow_the_candidates(setting, forest):
    sets = [{(r.qid, r.id) for r in se.candidates(setting[1], forest, v).collect()} for v in (1, 2, 3)]
    assert sets[2] < sets[1] < sets[0] and len(sets[0]) <= 20 * 6 * 35
    assert se.candidates(setting[1], forest, P.trees + 1).count() == 0
    assert sets[1] == {(r.qid, r.id) for r in se.candidates(setting[1], forest, 2, "scan").collect()}


def test_strategies_agree(setting, forest):
    ways = [answers(se.approximate_knn(setting[1], forest, 5, 2, s)) for s in ("probe", "scan", "fused")]
    assert ways[0] == ways[1] == ways[2] and ways[0]


@pytest.mark.parametrize("build", ["level_exact", "sample"])
def test_builds_agree(setting, forest, build):
    assert np.array_equal(fo.build_forest(setting[0], P.but(build=build)).splits, forest.splits)


def test_depth_0_is_brute_force(setting):
    flat = fo.build_forest(setting[0], ForestParams(trees=1, depth=0, density=1.0))
    assert answers(se.approximate_knn(setting[1], flat, 5, 1)) == answers(se.brute_force_knn(*setting, 5)) == answers(se.brute_force_knn(*setting, 5, "arrow"))


def test_slices_are_smaller_forests(setting, forest):
    small = fo.build_forest(setting[0], P.but(trees=3, depth=2))
    part = forest.slice(3, 2)
    assert np.array_equal(small.splits, part.splits)
    assert sorted(map(tuple, small.postings().collect())) == sorted(map(tuple, part.postings().collect()))


def test_save_and_load(spark, setting, forest, tmp_path):
    forest.save(str(tmp_path / "f"))
    again = fo.Forest.load(spark, str(tmp_path / "f"))
    assert answers(se.approximate_knn(setting[1], again, 5, 2)) == answers(se.approximate_knn(setting[1], forest, 5, 2))


def test_comparison_methods(setting):
    points, queries = setting
    truth = answers(se.brute_force_knn(points, queries, 5))
    tree = ba.axis_forest(points, depth=3)
    assert answers(tree.search_bounded(queries, 5, 0.0)) == truth
    exact, loose = (tree.bounded_visits(queries, 5, eps).count() for eps in (0.0, 3.0))
    assert 20 <= loose < exact <= 160
    voted = ba.kmeans_votes(points, queries, 5, trees=3, votes=1, max_leaves=16)
    assert answers(voted) == truth
    assert answers(ba.axis_forest(points, 3, 3, 5).search(queries, 5, 100)) == truth
    means = ba.kmeans_tree(points, 3, 2)
    assert answers(means.search(queries, 5, 9)) == truth and means.sse[1] <= means.sse[0]
    hashed = ba.cross_polytope(points, 4)
    few, more = (me.mean_recall(me.recall(hashed.search(queries, 5, n), se.brute_force_knn(points, queries, 5), queries, 5)).first()[0] for n in (4, 40))
    assert few <= more
    graph = ba.knn_graph(points, 8)
    assert me.mean_recall(me.recall(graph.search(queries, 5, 60), se.brute_force_knn(points, queries, 5), queries, 5)).first()[0] >= 0.9


def test_recall_by_hand(spark):
    found = spark.createDataFrame([(1, 1, 10, 0.1), (1, 2, 11, 0.2)], "qid long, rank int, id long, distance double")
    truth = spark.createDataFrame([(1, 1, 10, 0.1), (1, 2, 12, 0.15), (2, 1, 3, 0.1), (2, 2, 4, 0.1)], "qid long, rank int, id long, distance double")
    queries = spark.createDataFrame([(1,), (2,)], "qid long")
    assert sorted(map(tuple, me.recall(found, truth, queries, 2).collect())) == [(1, 1, 0.5), (2, 0, 0.0)]


def test_published_counts(spark):
    wins = {r.method: r.wins for r in me.win_counts(published.times(spark), (0.90, 0.95, 0.99)).collect()}
    high = {r.method: r.wins for r in me.win_counts(published.times(spark), (0.95, 0.99)).collect()}
    assert (wins["voting_forest"], wins["knn_graph"], high["voting_forest"], high["knn_graph"]) == (14, 7, 10, 4)


def test_bad_input(spark):
    rows = spark.createDataFrame([(1, [1.0, 2.0]), (2, None), (3, [1.0]), (4, [float("nan"), 0.0])], "i long, v array<double>")
    with pytest.raises(VectorSchemaError):
        ta.to_points(rows, "i", "v")
    assert [r.id for r in ta.to_points(rows, "i", "v", on_invalid="drop").collect()] == [1]
    with pytest.raises(ValueError):
        ForestParams(depth=4).validate(n=15)


def test_points_are_numbered_without_gaps(spark):
    ids = [7 * i + 1_000_000 + i % 3 for i in range(500)]
    points = spark.createDataFrame([(i, [float(i % 13), float(i % 7)]) for i in ids], "id long, vec array<double>").repartition(7)
    assert [(r.id, r.at) for r in ba._numbered(points).orderBy("at").collect()] == [(x, k) for k, x in enumerate(sorted(ids))]
    counted = points.select("id", "vec")
    counted.count = lambda: 2_000_000  # as a large table would
    edges = ba.knn_graph(counted, 4, rounds=1).edges.groupBy("u").count().collect()
    assert {r.u for r in edges} == set(ids) and {r["count"] for r in edges} <= {1, 2, 3, 4}


def test_auto_takes_exact_medians_at_every_size(setting, forest, monkeypatch):
    monkeypatch.setattr(fo, "LOCAL_ROWS", 50)
    monkeypatch.setattr(fo, "SAMPLE_ROWS", 50)
    large = fo.build_forest(setting[0], P)
    assert np.array_equal(large.splits, forest.splits)
    assert sorted(map(str, large.codes.collect())) == sorted(map(str, forest.codes.collect()))


@pytest.mark.parametrize("functions", [1, 2])
def test_multi_probe_ranks_every_bucket(setting, functions):
    points, queries = setting
    hashed = ba.cross_polytope(points, 2, functions)
    seen = {}
    for r in hashed.visits(queries, 60).orderBy("qid", "nth").collect():
        seen.setdefault(r.qid, []).append((r.part, r.cell))
    for q in queries.collect():
        want = []
        for t in range(2):
            y = ba._rotated(hashed.signs, np.array([q.qvec]))[0, t]
            loss = np.concatenate([y, -y], 1).max(1, keepdims=True) - np.concatenate([y, -y], 1)
            total = loss[0] if functions == 1 else (loss[0][:, None] + loss[1]).ravel()
            want += [(x, t, b) for b, x in enumerate(total)]
        assert len(seen[q.qid]) == 60 == len(set(seen[q.qid])) and set(seen[q.qid]) == {(t, b) for _, t, b in sorted(want)[:60]}


def test_a_sample_fits_other_splits_than_all_points(setting, forest):
    part = fo.build_forest(setting[0], P.but(build="sample", sample=0.5))
    assert not np.array_equal(part.splits, forest.splits) and part.codes.count() == 280


def test_uneven_forests_are_grown_anew(spark, setting, forest):
    assert forest.maintained() is forest
    one = setting[0].orderBy("id").limit(1).select(F.explode(F.sequence(F.lit(10_000), F.lit(10_300))).alias("id"), "vec")
    worse = forest.insert(one)
    assert worse.maintained(1e9) is worse and worse.maintained() is not worse


def test_further_leaves_add_answers(setting, forest):
    truth = se.brute_force_knn(*setting, 5)
    few, more = (me.mean_recall(me.recall(se.priority_knn(setting[1], forest, 5, 1, extra), truth, setting[1], 5)).first()[0] for extra in (0, 2))
    assert few < more


def test_axes_are_those_of_numpy(setting):
    x = np.array([r.vec for r in setting[0].collect()])
    tree = ba.axis_forest(setting[0], depth=1)
    assert tree.axes[0, 0] == np.argmax(np.round(x.max(0) - x.min(0), 9)) and abs(tree.cuts[0, 0] - np.median(x[:, tree.axes[0, 0]])) < 1e-9
    drawn = ba.axis_forest(setting[0], 6, 1, top_dims=3).axes[:, 0]
    assert set(drawn) <= set(np.argsort(-x.var(0))[:3]) and len(set(drawn)) > 1


def test_rotations_keep_lengths_and_beams_of_several_widths_agree(setting):
    points, queries = setting
    x = np.random.default_rng(1).standard_normal((5, 12))
    y = ba._rotated(np.random.default_rng(2).choice([-1.0, 1.0], (2, 3, 3, 16)), x)
    assert y.shape == (5, 2, 3, 16) and np.allclose((y**2).sum(3), (x**2).sum(1)[:, None, None])
    graph = ba.knn_graph(points, 6, rounds=3)
    found, evals = graph.search_all(queries, 5, [10, 40])
    assert answers(found.where("search_cost = 10").drop("search_cost")) == answers(graph.search(queries, 5, 10)) and 0 < evals[10] <= evals[40]

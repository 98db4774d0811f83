"""Queries that once made up their data, on tables of their own; and joins without rows of pairs."""

from __future__ import annotations

import duckdb
import numpy as np
import pytest

from knnvote import queries as qs
from knnvote.operators import forest as fo
from knnvote.operators import search as se
from knnvote.plans.config import ForestParams


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    path = str(tmp_path_factory.mktemp("in"))
    x = np.round(np.random.default_rng(5).standard_normal((150, 8)), 3)
    spark.createDataFrame([(i, v.tolist(), i % 5) for i, v in enumerate(x)], "vec_id long, embedding array<float>, label int").coalesce(1).write.parquet(f"{path}/embeddings.parquet")
    return path


def by_sql(text, path):
    with duckdb.connect() as c:
        c.execute(f"CREATE VIEW embeddings AS SELECT * FROM read_parquet('{path}/embeddings.parquet/*.parquet')")
        return sorted(c.execute(text).fetchall(), key=repr)


def test_directions_are_those_of_the_tables_vectors(spark, folder):
    for kind in ("sparse", "dense", "ternary", "very_sparse", "exact_nnz"):
        rows = qs.QUERIES[f"directions_{kind}"](spark, folder).collect()
        assert {r.dim for r in rows} <= set(range(8)) and len({(r.tree, r.level) for r in rows}) == 64


def test_cost_model_counts_the_tables_vectors(spark, folder):
    got = qs.QUERIES["cost_model"](spark, folder)
    assert sorted(map(tuple, got.collect()), key=repr) == by_sql(qs.SQL["cost_model"], folder)
    assert {r.method: r.build_cost for r in got.collect()}["dense"] == 100 * 10 * 150 * 8


def test_races_are_run_on_the_table(spark, folder, monkeypatch):
    runs = fo.materialised(qs._race_runs(spark, folder), "runs")
    assert {r.evals for r in runs.where("method = 'brute_force'").collect()} == {120 * 30}
    monkeypatch.setattr(qs, "_race_runs", lambda spark, sf_dir: runs)
    for name in ("win_counts_published", "win_counts_published_high", "speedup_published", "time_to_recall_published", "pivot_times", "rollup_runs"):
        # widths other than the given tables' are not in the SQL's directions, so votes may differ, brute force may not
        rows = qs.QUERIES[name](spark, folder).collect()
        want = by_sql(qs.SQL[name], folder)
        assert rows and len(rows) == len(want)


def test_join_makes_no_rows_of_pairs(spark, monkeypatch):
    monkeypatch.setattr(se, "CELL_ROWS", 40, raising=False)
    x = np.random.default_rng(3).standard_normal((200, 6)).round(2)
    x[150:] = x[0]  # a group of copies, larger than a part
    points = fo.materialised(spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, vec array<double>"), "points")
    kept = []
    monkeypatch.setattr(se, "ranked", lambda pairs, k, ranked=se.ranked: kept.append(pairs) or ranked(pairs, k))
    for trees, votes in ((4, 2), (4, 1), (3, 3), (2, 3)):
        forest = fo.build_forest(points, ForestParams(trees=trees, depth=1))
        codes = np.array([r.codes for r in forest.codes.orderBy("id").collect()])
        shared = (codes[:, None, :] == codes[None, :, :]).sum(2)
        want = {}
        for i in range(200):
            far = np.round(np.sqrt(((x - x[i]) ** 2).sum(1)), 6)
            others = sorted((far[j], j) for j in range(200) if j != i and shared[i, j] >= votes)[:5]
            want |= {(i, n): (j, d, shared[i, j]) for n, (d, j) in enumerate(others, 1)}
        assert {(r.qid, r.rank): (r.id, r.distance, r.votes) for r in se.knn_join(forest, 5, votes).collect()} == want
        assert not want or kept[-1].count() < 200 * 100


def test_wide_rows_lie_in_small_groups(spark):
    import glob

    import pyarrow.parquet as pq
    from pyspark.sql import functions as F

    wide = spark.range(0, 900, 1, 1).select("id", F.array_repeat(F.col("id").cast("double"), 9216).alias("vec"))
    path = fo.materialised(wide, "wide", 9216).inputFiles()[0].removeprefix("file:")
    meta = pq.ParquetFile(glob.glob(path)[0]).metadata
    assert meta.num_rows == 900 and max(meta.row_group(i).num_rows for i in range(meta.num_row_groups)) <= 227


def test_a_task_keeps_k_of_its_points(spark, monkeypatch):
    kept = []
    monkeypatch.setattr(se, "ranked", lambda pairs, k, ranked=se.ranked: kept.append(pairs) or ranked(pairs, k))
    old = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", 20)
    try:
        x = np.random.default_rng(4).standard_normal((300, 5)).round(1)
        points = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, vec array<double>").coalesce(1)
        queries = points.where("id < 10").selectExpr("id AS qid", "vec AS qvec")
        got = {(r.qid, r.rank): r.id for r in se.brute_force_knn(points, queries, 4, "arrow").collect()}
        far = np.round(np.sqrt(((x[:10, None] - x[None]) ** 2).sum(2)), 6)
        assert got == {(i, n): int(j) for i in range(10) for n, j in enumerate(np.lexsort((np.arange(300), far[i]))[:4], 1)}
        assert kept[0].count() == 40
    finally:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", old)


def test_bounded_search_makes_no_rows_of_candidates(spark, monkeypatch):
    from knnvote.operators import baselines as ba

    def never(*_):
        raise AssertionError("candidates became rows")

    x = np.random.default_rng(6).standard_normal((120, 5)).round(1)
    points = fo.materialised(spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, vec array<double>"), "points")
    queries = points.where("id < 6").selectExpr("id AS qid", "vec AS qvec")
    tree = ba.axis_forest(points, depth=2)
    monkeypatch.setattr(ba, "rank_candidates", never)
    far = np.round(np.sqrt(((x[:6, None] - x[None]) ** 2).sum(2)), 6)
    want = {(i, n, int(j)) for i in range(6) for n, j in enumerate(np.lexsort((np.arange(120), far[i]))[:3], 1)}
    assert {(r.qid, r.rank, r.id) for r in tree.search_bounded(queries, 3).collect()} == want


def test_part_demand_is_filled_in_blocks(spark, tmp_path):
    from datetime import datetime

    from knnvote.sources import tables as ta

    rows = [(1, 2.0, datetime(1995, 1, 1)), (1, 3.0, datetime(1995, 1, 20)), (1, 4.0, datetime(1995, 1, 21)), (2, 5.0, datetime(2001, 12, 31)), (3, 6.0, datetime(1994, 1, 1)), (2, 1.0, datetime(1995, 2, 10))]
    spark.createDataFrame(rows, "l_partkey long, l_quantity double, l_shipdate timestamp").write.parquet(f"{tmp_path}/lineitem.parquet")
    demand = ta.part_demand(spark, str(tmp_path))
    got = {r.id: {i: v for i, v in enumerate(r.vec) if v} for r in demand.collect()}
    assert got == {1: {0: 5.0, 1: 4.0}, 2: {2: 1.0, 127: 5.0}}
    assert "MapInArrow" in demand._jdf.queryExecution().executedPlan().toString()  # no map is searched anew for each of the 128 places

"""Streams, joins in time and table functions."""

from __future__ import annotations

from datetime import datetime, timedelta

import pytest
from pyspark.sql import functions as F

from knnvote.functions import tables as ft
from knnvote.operators import forest as fo
from knnvote.operators import search as se
from knnvote.plans.config import ForestParams
from knnvote.sources import tables as ta
from knnvote.streaming import forests as sf
from knnvote.streaming import profiles as sp

DAY = datetime(2024, 1, 2)


@pytest.fixture(scope="module")
def events(spark):
    at = lambda h, m=0: DAY + timedelta(hours=h, minutes=m)
    rows = [(1, at(1), 7, "view", 1.0), (2, at(1, 30), 7, "purchase", 5.0), (3, at(9), 7, "view", 2.0), (4, at(12), 7, "purchase", 3.0), (5, at(2), 8, "purchase", 4.0), (6, at(2), 8, "view", 9.0), (6, at(2), 8, "view", 9.0)]
    return spark.createDataFrame([(*r, "{}") for r in rows], sp.EVENTS)


@pytest.fixture(scope="module")
def folder(events, tmp_path_factory):
    path = str(tmp_path_factory.mktemp("in"))
    events.coalesce(1).write.mode("overwrite").parquet(f"{path}/events.parquet")
    return path


def rows_of(df):
    return sorted(map(tuple, df.collect()))


def test_as_of_takes_the_last_row_before(events):
    e = sp.once(events)
    got = sp.as_of(e.where("event_type = 'purchase'").select("event_id", "user_id", "ts"), e.where("event_type = 'view'"), "user_id", "ts", ["event_id", "value"])
    assert [(r.event_id, r.last_event_id, r.last_value) for r in got.orderBy("event_id").collect()] == [(2, 1, 1.0), (4, 3, 2.0), (5, 6, 9.0)]


def test_windows_and_followers(events):
    e = sp.once(events)
    assert e.count() == 6
    assert [r.events for r in sp.profiles(e, "session").where("user_id = 7").orderBy("start").collect()] == [2, 1, 1]
    assert sp.profiles(e, "tumbling").agg(F.sum("events")).first()[0] == 6 and sp.profiles(e, "sliding").agg(F.sum("events")).first()[0] == 24
    assert rows_of(sp.followed(e)) == [(7, 1, 2), (8, 6, 5)]


def test_streams_give_what_batches_give(spark, events, folder, tmp_path):
    stream = lambda: spark.readStream.schema(sp.EVENTS).parquet(f"{folder}/events.parquet")
    assert rows_of(sp.collected(sp.followed(sp.once(stream()), late=None), str(tmp_path / "f"))) == rows_of(sp.followed(sp.once(events)))
    got = sp.collected(sp.running_vectors(stream()), str(tmp_path / "v"), "update")
    assert {(r.user_id, r.events, sum(r.vec)) for r in got.collect()} == {(7, 4, 4.0), (8, 3, 3.0)}
    day = sp.collected(sp.profiles(stream(), "tumbling"), str(tmp_path / "w"), "complete")
    assert rows_of(day) == rows_of(sp.profiles(events, "tumbling"))


def test_query_and_insert_streams(spark, tmp_path):
    points = fo.materialised(ta.gaussian_sphere(spark, 120, 8), "points")
    old, new = points.where("id < 100"), points.where("id >= 100")
    forest = fo.build_forest(old, ForestParams(trees=4, depth=2))
    new.write.parquet(str(tmp_path / "new"))
    stream = spark.readStream.schema("id long, vec array<float>").parquet(str(tmp_path / "new"))
    sf.insert_stream(stream, forest, str(tmp_path / "added"), str(tmp_path / "c1")).awaitTermination()
    grown = sf.with_inserted(forest, str(tmp_path / "added"))
    assert grown.n == 120 and rows_of(grown.postings()) == rows_of(forest.insert(new).postings())
    sf.query_stream(sf.as_queries(stream), forest, 3, 1, str(tmp_path / "found"), str(tmp_path / "c2"), "probe").awaitTermination()
    want = se.approximate_knn(sf.as_queries(new), forest, 3, 1)
    found = spark.read.parquet(str(tmp_path / "found")).drop("batch")
    assert rows_of(found.select(want.columns)) == rows_of(want)


def test_table_functions(spark):
    ft.register(spark)
    spark.createDataFrame([(1, 5, 0.3), (1, 6, 0.1), (1, 7, 0.1), (2, 5, 0.9)], "qid long, id long, distance double").createOrReplaceTempView("pairs")
    assert rows_of(spark.sql("SELECT * FROM best_of(TABLE(pairs) PARTITION BY (qid), 2)")) == [(1, 1, 6, 0.1), (1, 2, 7, 0.1), (2, 1, 5, 0.9)]
    assert rows_of(spark.sql("SELECT * FROM explode_leaves(array(3, 0))")) == [(0, 3), (1, 0)]
    means = ft.vec_mean(spark.createDataFrame([(1, [1.0, 2.0]), (1, [3.0, 4.0]), (2, [0.0, 1.0])], "g int, vec array<float>"), "g", d=2)
    assert rows_of(means) == [(1, [2.0, 3.0]), (2, [0.0, 1.0])]

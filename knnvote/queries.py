"""The driver's queries for the nearest-neighbour engine, and their DuckDB SQL."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions.vectors import METRICS
from .operators import baselines as ba
from .operators import experiments as ex
from .operators import forest as fo
from .operators import measures as me
from .operators import search as se
from .operators.projection import directions, packed, project
from .operators.reduction import singular_basis
from .plans import oracle as sql
from .plans import surface as su
from .plans.config import ForestParams
from .sources import tables as ta
from .sources.storage import work_folder
from .streaming import profiles as sp

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}

P = ForestParams(trees=16, depth=4, seed=42)
VOTES, K = 2, 10
DENSE = P.but(trees=8, depth=3, density=1.0)
D = 64


def query(text: str | None = None, name: str | None = None):
    """Registers a query, with its SQL where there is one."""
    def put(f):
        QUERIES[name or f.__name__] = f
        if text:
            SQL[name or f.__name__] = text
        return f

    return put


def setting(spark: SparkSession, sf_dir: str, p: ForestParams = P):
    """(points, queries, forest) of the standard workload: embeddings, a hundred held out."""
    points, queries = ta.hold_out(ta.embeddings(spark, sf_dir))
    return points, queries, fo.build_forest(points, p)


def _width(points: DataFrame) -> int:
    return points.agg(F.max(F.size("vec"))).first()[0]


# ---- directions and projections -------------------------------------------------------------

for _name, _p in {
    "directions_sparse": P, "directions_dense": P.but(density=1.0), "directions_ternary": P.but(components="ternary"),
    "directions_very_sparse": P.but(components="very_sparse"), "directions_exact_nnz": P.but(nnz="exact"),
}.items():
    query(sql.with_ctes(sql.directions(_p, D), "SELECT tree, level, dim, weight FROM dirs"), _name)(lambda spark, sf_dir, p=_p: directions(spark, p, _width(ta.embeddings(spark, sf_dir))).select("tree", "level", "dim", "weight"))

_PROJ_SQL = sql.with_ctes(sql.held_out(), sql.directions(P, D), sql.projections(P), "SELECT id, tree, level, value FROM proj")


@query(_PROJ_SQL)
def projection_matrix(spark, sf_dir, engine="native"):
    points, _ = ta.hold_out(ta.embeddings(spark, sf_dir))
    out = project(points, packed(directions(spark, P, D)), P, D, engine)
    return out.select("id", F.posexplode("proj").alias("at", "value")).select("id", F.expr(f"int(at div {P.depth})").alias("tree"), F.expr(f"int(at % {P.depth})").alias("level"), "value")


query(_PROJ_SQL, "projection_matrix_arrow")(lambda spark, sf_dir: projection_matrix(spark, sf_dir, "arrow"))
query(_PROJ_SQL, "projection_matrix_relational")(lambda spark, sf_dir: projection_matrix(spark, sf_dir, "relational"))

# ---- forests ---------------------------------------------------------------------------------

_SPLITS = sql.with_ctes(*sql.forest(P), sql.all_splits(P) + " SELECT tree, level, node, threshold FROM splits")


def _splits(spark, sf_dir, p):
    return setting(spark, sf_dir, p)[2].split_table()


_S = P.but(build="sample", sample=0.5)
query(sql.with_ctes(*sql.forest(_S), sql.all_splits(_S) + " SELECT tree, level, node, threshold FROM splits"), "splits_sampled")(lambda spark, sf_dir: _splits(spark, sf_dir, _S))
for _name, _b in {"splits_level": "level_exact", "splits_tree_local": "tree_local"}.items():
    query(_SPLITS, _name)(lambda spark, sf_dir, b=_b: _splits(spark, sf_dir, P.but(build=b)))
query(None, "splits_sketch")(lambda spark, sf_dir: _splits(spark, sf_dir, P.but(build="level_sketch")))

_CODES = "SELECT id, tree, node AS leaf FROM n%d" % P.depth


@query(sql.with_ctes(*sql.forest(P), _CODES))
def leaf_codes(spark, sf_dir):
    return setting(spark, sf_dir)[2].postings().select("id", "tree", "leaf")


@query(sql.with_ctes(*sql.forest(P), "SELECT tree, min(c) AS smallest, max(c) AS largest, count(*) AS leaves, sum(c)::BIGINT AS points FROM (SELECT tree, node, count(*) AS c FROM n4 GROUP BY ALL) GROUP BY tree"))
def leaf_balance(spark, sf_dir):
    return me.leaf_balance(setting(spark, sf_dir)[2])


_F = P.but(trees=4, split="fractile")


@query(sql.with_ctes(*sql.forest(_F), "SELECT id, tree, node AS leaf FROM n4"))
def splits_fractile(spark, sf_dir):
    return setting(spark, sf_dir, _F)[2].postings().select("id", "tree", "leaf")


_R = P.but(trees=4, depth=3, tie="rank")


@query(sql.with_ctes(*sql.forest(_R), "SELECT id, tree, node AS leaf FROM n3"))
def splits_rank_ties(spark, sf_dir):
    return setting(spark, sf_dir, _R)[2].postings().select("id", "tree", "leaf")


_N = P.but(trees=4, depth=2, density=1.0, direction_scope="node")


@query(sql.with_ctes(*sql.forest(_N), "SELECT id, tree, node AS leaf FROM n2"))
def per_node_forest(spark, sf_dir):
    return setting(spark, sf_dir, _N)[2].postings().select("id", "tree", "leaf")


# ---- votes and searches -------------------------------------------------------------------------

_VOTES = sql.votes(P)


@query(sql.with_ctes(*sql.forest(P), *sql.routes(P), "SELECT qid, tree, node AS leaf FROM q4"))
def route_queries(spark, sf_dir):
    _, queries, forest = setting(spark, sf_dir)
    return se.route(queries, forest)


@query(sql.with_ctes(*_VOTES, "SELECT qid, id, votes FROM votes"))
def vote_counts(spark, sf_dir):
    _, queries, forest = setting(spark, sf_dir)
    return se.candidates(queries, forest, 1)


query(sql.with_ctes(*_VOTES, "SELECT qid, id FROM votes"), "defeatist_candidates")(lambda spark, sf_dir: vote_counts(spark, sf_dir).select("qid", "id"))


@query(sql.with_ctes(*_VOTES, f"SELECT qid, id, votes FROM votes WHERE votes >= {VOTES + 2}"))
def vote_candidates(spark, sf_dir):
    _, queries, forest = setting(spark, sf_dir)
    return se.candidates(queries, forest, VOTES + 2)


query(SQL["vote_candidates"], "vote_candidates_scan")(lambda spark, sf_dir: (lambda s: se.candidates(s[1], s[2], VOTES + 2, "scan"))(setting(spark, sf_dir)))


def _search(p: ForestParams, votes: int, k: int = K, **options):
    def run(spark, sf_dir):
        _, queries, forest = setting(spark, sf_dir, p)
        return se.approximate_knn(queries, forest, k, votes, **options).select("qid", "rank", "id", "distance")

    return run


for _name, _p, _v, _o in (
    ("voting_knn", P, VOTES, {}), ("voting_knn_scan", P, VOTES, {"strategy": "scan"}), ("voting_knn_fused", P, VOTES, {"strategy": "fused"}),
    ("voting_knn_v4", P, 4, {}), ("voting_knn_sparse_v1", P, 1, {}), ("dense_forest_knn", DENSE, 1, {}), ("classic_forest_knn", _N, 1, {}),
    ("voting_knn_ternary", P.but(components="ternary"), VOTES, {}), ("voting_knn_very_sparse", P.but(components="very_sparse"), VOTES, {}),
):
    query(sql.with_ctes(*sql.knn(_p, _v, K), "SELECT qid, rank, id, distance FROM knn"), _name)(_search(_p, _v, **_o))

query(sql.with_ctes(*sql.knn(P, 6, K), sql.shortfall(K, 1)), "shortfall_lower_votes")(_search(P, 6, shortfall="lower_votes"))
query(sql.with_ctes(*sql.knn(P, 6, K), sql.shortfall(K, 0)), "shortfall_brute")(_search(P, 6, shortfall="brute"))


@query(sql.with_ctes(*sql.knn(P, VOTES, K, "id IN (SELECT vec_id FROM embeddings WHERE label < 3)"), "SELECT qid, rank, id, distance FROM knn"))
def filtered_knn(spark, sf_dir):
    _, queries, forest = setting(spark, sf_dir)
    some = ta.load(spark, sf_dir, "embeddings").where("label < 3").select(F.col("vec_id").alias("id"))
    forest.points = forest.points.join(some, "id", "left_semi")
    return se.approximate_knn(queries, forest, K, VOTES).select("qid", "rank", "id", "distance")


@query(sql.with_ctes(*sql.self_join(P.but(trees=4), 2, 5), "SELECT qid, rank, id, distance FROM knn"))
def knn_join(spark, sf_dir):
    return se.knn_join(setting(spark, sf_dir, P.but(trees=4))[2], 5, 2).select("qid", "rank", "id", "distance")


@query(sql.with_ctes(*sql.forest(P), *sql.routes(P), f"SELECT id, tree, node AS leaf FROM n{P.depth} UNION ALL SELECT qid, tree, node FROM q{P.depth}"))
def insert_points(spark, sf_dir):
    _, queries, forest = setting(spark, sf_dir)
    return forest.insert(queries.select(F.col("qid").alias("id"), F.col("qvec").alias("vec"))).postings().select("id", "tree", "leaf")


@query()
def priority_leaves(spark, sf_dir):
    _, queries, forest = setting(spark, sf_dir)
    return se.route_with_neighbours(queries, forest, 2)


@query()
def priority_knn(spark, sf_dir):
    _, queries, forest = setting(spark, sf_dir)
    return se.priority_knn(queries, forest, K, VOTES, 2).select("qid", "rank", "id", "distance")


for _k in (1, 10, 25, 100):
    query(sql.with_ctes(*sql.brute(_k), "SELECT qid, rank, id, distance FROM truth"), f"brute_force_knn_{_k}")(lambda spark, sf_dir, k=_k: se.brute_force_knn(*ta.hold_out(ta.embeddings(spark, sf_dir)), k, engine="arrow"))
query(SQL["brute_force_knn_10"], "brute_force_knn_native")(lambda spark, sf_dir: se.brute_force_knn(*ta.hold_out(ta.embeddings(spark, sf_dir)), 10))

for _m in ("l1", "linf", "cosine"):
    query(sql.with_ctes(*sql.brute(5, _m), "SELECT qid, rank, id, distance FROM truth"), f"brute_force_{_m}")(lambda spark, sf_dir, m=_m: se.brute_force_knn(*ta.hold_out(ta.embeddings(spark, sf_dir)), 5, metric=m))
assert set(METRICS) >= {"l1", "linf", "cosine"}


@query(sql.with_ctes(*sql.brute(10**9), "SELECT qid, id, distance FROM truth WHERE distance <= 1.2"))
def within_radius(spark, sf_dir):
    return se.within_radius(*ta.hold_out(ta.embeddings(spark, sf_dir)), 1.2)


# ---- measures ----------------------------------------------------------------------------------

_V4 = 4
_BOTH = (*sql.knn(P, _V4, K), sql.truth(K))


def _compared(spark, sf_dir, k=K):
    points, queries, forest = setting(spark, sf_dir)
    found = fo.materialised(se.approximate_knn(queries, forest, k, _V4), "found")
    return found, fo.materialised(se.brute_force_knn(points, queries, k, "arrow"), "truth"), queries, forest


_RECALL = "rec AS (SELECT h.id AS qid, coalesce(c.hits, 0)::BIGINT AS hits, round(coalesce(c.hits, 0) / 10.0, 6) AS recall FROM held h LEFT JOIN (SELECT qid, count(*) AS hits FROM knn SEMI JOIN truth USING (qid, id) GROUP BY qid) c ON c.qid = h.id)"


@query(sql.with_ctes(*_BOTH, _RECALL, "SELECT qid, hits, recall FROM rec"))
def recall_by_query(spark, sf_dir):
    found, truth, queries, _ = _compared(spark, sf_dir)
    return me.recall(found, truth, queries, K)


query(sql.with_ctes(*_BOTH, _RECALL, "SELECT round(avg(recall), 6) AS recall FROM rec"), "recall_mean")(lambda spark, sf_dir: me.mean_recall(recall_by_query(spark, sf_dir)))


@query(sql.with_ctes(*_BOTH, "last AS (SELECT qid, max(distance) AS last FROM truth GROUP BY qid)", "SELECT h.id AS qid, coalesce(c.hits, 0)::BIGINT AS hits, round(coalesce(c.hits, 0) / 10.0, 6) AS recall FROM held h LEFT JOIN (SELECT qid, count(*) AS hits FROM knn JOIN last USING (qid) WHERE distance <= last GROUP BY qid) c ON c.qid = h.id"))
def recall_ties(spark, sf_dir):
    found, truth, queries, _ = _compared(spark, sf_dir)
    return me.recall(found, truth, queries, K, "distance")


@query(sql.with_ctes(*_BOTH, "SELECT qid, round(sum(k.distance) / sum(t.distance), 6) AS ratio FROM knn k JOIN truth t USING (qid, rank) GROUP BY qid"))
def distance_ratio(spark, sf_dir):
    found, truth, _, _ = _compared(spark, sf_dir)
    return me.distance_ratio(found, truth)


@query(sql.with_ctes(*_BOTH, "SELECT round(avg(CASE WHEN k.id IS NULL THEN 0 ELSE 1 END), 6) AS hit_rate FROM (SELECT * FROM truth WHERE rank = 1) t LEFT JOIN knn k USING (qid, id)"))
def hit_rate(spark, sf_dir):
    found, truth, queries, _ = _compared(spark, sf_dir)
    return me.hit_rate(found, truth, queries)


@query(sql.with_ctes(*_VOTES, f"SELECT h.id AS qid, coalesce(c, 0)::BIGINT AS candidates, round(coalesce(c, 0) / (SELECT count(*) FROM pts)::DOUBLE, 6) AS fraction FROM held h LEFT JOIN (SELECT qid, count(*) AS c FROM votes WHERE votes >= {_V4} GROUP BY qid) v ON v.qid = h.id"))
def candidate_stats(spark, sf_dir):
    _, queries, forest = setting(spark, sf_dir)
    return me.candidate_stats(se.candidates(queries, forest, _V4), queries, forest.n)


@query(sql.with_ctes(*_VOTES, f"SELECT count(*) AS distance_evals FROM votes WHERE votes >= {_V4}"))
def distance_evals(spark, sf_dir):
    _, queries, forest = setting(spark, sf_dir)
    return me.distance_evals(se.candidates(queries, forest, _V4))


@query(sql.with_ctes(*_VOTES, sql.truth(K), "SELECT rank, round(avg(coalesce(votes, 0)), 6) AS mean_votes FROM truth LEFT JOIN votes USING (qid, id) GROUP BY rank"))
def vote_profile(spark, sf_dir):
    points, queries, forest = setting(spark, sf_dir)
    return me.vote_profile(se.candidates(queries, forest, 1), se.brute_force_knn(points, queries, K, "arrow"))


@query(sql.with_ctes(sql.held_out(), sql.directions(P, D), f"SELECT 'ids' AS part, {P.trees} * count(*) AS entries, {8 * P.trees} * count(*) AS bytes FROM pts UNION ALL SELECT 'splits', {P.trees * 15}, {P.trees * 15 * 8} UNION ALL SELECT 'directions', count(*), 12 * count(*) FROM dirs"))
def index_size(spark, sf_dir):
    return me.index_size(setting(spark, sf_dir)[2])


@query(sql.cost_model(P.but(trees=100, depth=10)))
def cost_model(spark, sf_dir):
    return me.cost_model(ta.embeddings(spark, sf_dir), P.but(trees=100, depth=10))


_GRID = ([4, 8, 16], [2, 3, 4], [1, 2, 4, 8])


@query(sql.grid(P, K, *_GRID))
def grid_recall(spark, sf_dir):
    points, queries, forest = setting(spark, sf_dir)
    truth = fo.materialised(se.brute_force_knn(points, queries, K, "arrow"), "truth")
    return me.grid_recall(forest, queries, truth, K, *_GRID)


@query(f"WITH runs AS ({sql.grid(P, K, *_GRID)}) SELECT trees, depth, votes, recall, candidates FROM (SELECT *, max(recall) OVER (ORDER BY candidates, recall DESC, trees, depth, votes ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS best FROM runs) WHERE best IS NULL OR recall > best")
def frontier_by_candidates(spark, sf_dir):
    return me.frontier(fo.materialised(grid_recall(spark, sf_dir), "grid"), "candidates")


# ---- races, as in the published table, on the embeddings ---------------------------------------------

_RACE_KS, _RACE_GRID, _RACE_VOTES = (1, 10, 25, 100), ([4, 8, 16], [2, 3, 4]), [1, 2, 3, 4, 6, 8]
_RACERS = ("dense_forest", "sparse_forest", "voting_forest", "brute_force")


def _race_runs(spark, sf_dir):
    """(dataset, method, recall, evals): a data set is the embeddings with a number of neighbours asked for, the cost exact distances for all queries."""
    points, queries = _held(spark, sf_dir)
    truth = fo.materialised(se.brute_force_knn(points, queries, max(_RACE_KS), "arrow"), "truth")
    parts = []
    for p, votes in ((P.but(density=1.0), [1]), (P, _RACE_VOTES)):
        forest = fo.build_forest(points, p)
        parts += [me.grid_recall(forest, queries, truth, k, *_RACE_GRID, votes).select(F.lit(f"k={k}").alias("dataset"), F.lit("dense_forest" if p.density == 1.0 else "voting_forest").alias("method"), "votes", "recall", F.col("candidates").alias("evals")) for k in _RACE_KS]
    runs = fo.materialised(_union(parts), "runs")
    plain = runs.where("method = 'voting_forest' and votes = 1").withColumn("method", F.lit("sparse_forest"))
    brute = spark.createDataFrame([(f"k={k}", "brute_force", 1.0, points.count() * queries.count()) for k in _RACE_KS], "dataset string, method string, recall double, evals long")
    return runs.unionByName(plain).drop("votes").unionByName(brute)


def _race_times(spark, sf_dir):
    return me.time_to_recall(_race_runs(spark, sf_dir), cost="evals")


def _races(last: str, levels: tuple[float, ...] = me.LEVELS) -> str:
    return sql.races(P.but(density=1.0), P, _RACE_KS, *_RACE_GRID, _RACE_VOTES, last, levels)


for _name, _levels in {"win_counts_published": (0.90, 0.95, 0.99), "win_counts_published_high": (0.95, 0.99)}.items():
    query(_races("SELECT method, wins, races FROM w", _levels), _name)(lambda spark, sf_dir, levels=_levels: me.win_counts(_race_times(spark, sf_dir), levels, "evals"))
query(_races("SELECT dataset, level, method, round(base / evals, 6) AS speedup FROM t JOIN (SELECT dataset, level, evals AS base FROM t WHERE method = 'brute_force') USING (dataset, level) WHERE method <> 'brute_force'"), "speedup_published")(lambda spark, sf_dir: me.speedup(_race_times(spark, sf_dir), "brute_force", "evals"))
query(_races("SELECT dataset, method, level, evals FROM t"), "time_to_recall_published")(_race_times)


@query(_races("SELECT dataset, level, " + ", ".join(f"max(evals) FILTER (method = '{m}') AS {m}" for m in _RACERS) + " FROM t GROUP BY dataset, level"))
def pivot_times(spark, sf_dir):
    return _race_times(spark, sf_dir).groupBy("dataset", "level").pivot("method", list(_RACERS)).agg(F.first("evals"))


# ---- workloads -----------------------------------------------------------------------------------

for _name, _f, _t in (("user_profiles", ta.user_profiles, sql.USER_PROFILES), ("part_demand", ta.part_demand, sql.PART_DEMAND), ("customer_brand", ta.customer_brand, sql.CUSTOMER_BRAND), ("doc_bigrams", ta.letter_bigrams, sql.DOC_BIGRAMS), ("page_features", ta.page_features, sql.PAGE_FEATURES)):
    query(_t, _name)(lambda spark, sf_dir, f=_f: f(spark, sf_dir).select("id", F.transform("vec", lambda x: F.round(x, 4)).alias("vec")))

_W = P.but(trees=16, depth=3)


def _workload(f, k=K, votes=2, width=1):
    def run(spark, sf_dir):
        points = fo.materialised(f(spark, sf_dir), "vectors", width)
        points, queries = ta.hold_out(points)
        forest = fo.build_forest(points, _W)
        found = fo.materialised(se.approximate_knn(queries, forest, k, votes, "auto"), "found")
        rec = me.recall(found, se.brute_force_knn(points, queries, k, "arrow"), queries, k, "distance")
        return rec.agg(F.count("*").alias("queries"), F.round(F.avg("recall"), 4).alias("recall"))

    return run


for _name, _f in {"users": ta.user_profiles, "parts": ta.part_demand, "customers": ta.customer_brand, "bigrams": ta.letter_bigrams, "pages": ta.page_features}.items():
    query(None, f"voting_knn_{_name}")(_workload(_f))
query(None, "voting_knn_words")(_workload(lambda spark, sf_dir: ta.word_counts(ta.load(spark, sf_dir, "documents"), "doc_id", "text", 256)))

# ---- comparison methods ------------------------------------------------------------------------------


def _held(spark, sf_dir):
    points, queries = ta.hold_out(ta.embeddings(spark, sf_dir))
    return fo.materialised(points, "points"), fo.materialised(queries, "queries")


def _neighbours(df: DataFrame) -> DataFrame:
    return df.select("qid", "rank", "id", "distance")


@query(SQL["brute_force_knn_10"])
def kd_tree_knn(spark, sf_dir):
    points, queries = _held(spark, sf_dir)
    return _neighbours(ba.axis_forest(points, depth=4).search_bounded(queries, K, 0.0))


@query()
def kd_tree_knn_eps(spark, sf_dir):
    points, queries = _held(spark, sf_dir)
    return _neighbours(ba.axis_forest(points, depth=4).search_bounded(queries, K, 1.0))


@query()
def kd_forest_knn(spark, sf_dir):
    points, queries = _held(spark, sf_dir)
    return _neighbours(ba.axis_forest(points, 4, 4, top_dims=5).search(queries, K, 16))


@query()
def kd_forest_voting_knn(spark, sf_dir):
    points, queries = _held(spark, sf_dir)
    return _neighbours(ba.axis_forest(points, 4, 4, top_dims=5).search(queries, K, 24, votes=2))


@query()
def kmeans_tree_knn(spark, sf_dir):
    points, queries = _held(spark, sf_dir)
    return _neighbours(ba.kmeans_tree(points, 4, 2).search(queries, K, 6))


@query()
def kmeans_voting_knn(spark, sf_dir):
    points, queries = _held(spark, sf_dir)
    return _neighbours(ba.kmeans_votes(points, queries, K))


@query()
def cross_polytope_voting_knn(spark, sf_dir):
    points, queries = _held(spark, sf_dir)
    return _neighbours(ba.cross_polytope(points, 10).search(queries, K, 100, votes=2))


@query()
def cross_polytope_knn(spark, sf_dir):
    points, queries = _held(spark, sf_dir)
    return _neighbours(ba.cross_polytope(points, 10).search(queries, K, 50))


@query()
def cross_polytope_single_probe(spark, sf_dir):
    points, queries = _held(spark, sf_dir)
    return _neighbours(ba.cross_polytope(points, 10).search(queries, K))


@query()
def knn_graph_build(spark, sf_dir):
    return ba.knn_graph(_held(spark, sf_dir)[0], 10).edges


@query()
def knn_graph_search(spark, sf_dir):
    points, queries = _held(spark, sf_dir)
    return _neighbours(ba.knn_graph(points, 10).search(queries, K, 50))


@query()
def ml_lsh_knn(spark, sf_dir):
    points, queries = _held(spark, sf_dir)
    return ba.ml_lsh(points, queries, K, 1.4)


# ---- experiments -----------------------------------------------------------------------------------------

_WORDS, _TOPICS = 512, 100


def _document_words(spark, sf_dir):
    return fo.materialised(ta.word_counts(ta.load(spark, sf_dir, "documents"), "doc_id", "text", _WORDS), "words")


def reduced_words(spark, sf_dir):
    """Documents as weighted word counts on their leading singular vectors."""
    words = _document_words(spark, sf_dir)
    return singular_basis(words, _TOPICS).reduced(words)


def _trigrams(table: str, key: str, text: str, d: int):
    return lambda spark, sf_dir: ta.char_ngrams(ta.load(spark, sf_dir, table).select(key, text), key, text, d)


for _name, _f, _d in (("reduced_words", reduced_words, _TOPICS), ("page_trigrams", _trigrams("pages", "page_id", "html", 4096), 4096), ("document_trigrams", _trigrams("documents", "doc_id", "text", 9216), 9216)):
    query(None, f"voting_knn_{_name}")(_workload(_f, width=_d))


@query()
def singular_values(spark, sf_dir):
    values = singular_basis(_document_words(spark, sf_dir), _TOPICS).values
    return spark.createDataFrame([(i + 1, round(float(x), 4)) for i, x in enumerate(values)], "nth int, value double")


def _look_up(table: str, key: str):
    """Texts from another table against the documents, all in the space of the documents; repeated keys are one query."""
    def run(spark, sf_dir):
        docs = ta.load(spark, sf_dir, "documents").select(F.col("doc_id").alias("k"), "text")
        asked = ta.load(spark, sf_dir, table).groupBy(F.col(key).alias("k")).agg(F.concat_ws(" ", F.array_sort(F.collect_list("text"))).alias("text"))
        words = _document_words(spark, sf_dir)
        basis = singular_basis(words, _TOPICS)
        forest = fo.build_forest(fo.materialised(basis.reduced(words), "vectors"), _W)
        queries = ta.word_counts(asked, "k", "text", _WORDS, base=docs)
        queries = fo.materialised(basis.reduced(queries).select(F.col("id").alias("qid"), F.col("vec").alias("qvec")), "queries")
        found = fo.materialised(se.approximate_knn(queries, forest, K, 2, "auto"), "found")
        rec = me.recall(found, se.brute_force_knn(forest.points, queries, K, "arrow"), queries, K, "distance")
        return rec.agg(F.count("*").alias("queries"), F.round(F.avg("recall"), 4).alias("recall"))

    return run


query(None, "look_up_benchmark")(_look_up("benchmark", "item_id"))
query(None, "look_up_conversations")(_look_up("conversations", "conv_id"))

_TREES, _DEPTHS, _LEVELS = [4, 8, 16], [2, 3, 4], [1, 2, 3, 4, 6, 8]
_ROW = "trees, depth, votes, recall, candidates"


def _grid(spark, sf_dir, p: ForestParams, k: int, votes: list[int]) -> DataFrame:
    points, queries, forest = setting(spark, sf_dir, p)
    truth = fo.materialised(se.brute_force_knn(points, queries, k, "arrow"), "truth")
    return me.grid_recall(forest, queries, truth, k, _TREES, _DEPTHS, votes)


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for x in parts[1:]:
        out = out.unionByName(x)
    return out


def _sql_union(kind: str, grids: dict[object, str]) -> str:
    return " UNION ALL ".join(f"SELECT {v} AS {kind}, {_ROW} FROM ({g})" for v, g in grids.items())


_KS = (1, 10, 25, 100)
query(_sql_union("k", {k: sql.grid(P, k, _TREES, _DEPTHS, _LEVELS) for k in _KS}), "k_sweep")(lambda spark, sf_dir: _union([_grid(spark, sf_dir, P, k, _LEVELS).withColumn("k", F.lit(k)) for k in _KS]))

_SHARES = {f"{x}::DOUBLE": P.but(density=x) for x in (round(1 / D, 6), 0.1, 0.125, round(1 / 3, 6), 1.0)}
query(_sql_union("density", {x: sql.grid(p, K, _TREES, _DEPTHS, _LEVELS) for x, p in _SHARES.items()}), "density_study")(lambda spark, sf_dir: _union([_grid(spark, sf_dir, p, K, _LEVELS).withColumn("density", F.lit(p.density)) for p in _SHARES.values()]))

_STEPS = {"dense_forest": (P.but(density=1.0), [1]), "sparse_forest": (P, [1]), "voting_forest": (P, _LEVELS)}
_ABLATION = _sql_union("method", {f"'{m}'": sql.grid(p, K, _TREES, _DEPTHS, v) for m, (p, v) in _STEPS.items()})


def _ablation(spark, sf_dir):
    return _union([_grid(spark, sf_dir, p, K, v).withColumn("method", F.lit(m)) for m, (p, v) in _STEPS.items()])


query(_ABLATION, "ablation")(_ablation)


@query(f"WITH r AS ({_ABLATION}), t AS (SELECT l AS level, min(candidates) FILTER (method = 'dense_forest' AND recall >= l) AS d, min(candidates) FILTER (method = 'sparse_forest' AND recall >= l) AS s, min(candidates) FILTER (method = 'voting_forest' AND recall >= l) AS v FROM r, (SELECT unnest([0.80, 0.90, 0.95, 0.99]::DOUBLE[]) AS l) GROUP BY l) SELECT 'sphere' AS dataset, level, round(d / s, 4) AS sparsity_gain, round(s / v, 4) AS voting_gain FROM t")
def ablation_gains(spark, sf_dir):
    return ex.gains(_ablation(spark, sf_dir).select(F.lit("sphere").alias("dataset"), "method", "recall", F.col("candidates").alias("evals")))


_WORKLOADS = {"sphere": ta.embeddings, "bigrams": ta.letter_bigrams, "reduced_words": reduced_words, "parts": ta.part_demand}
_WIDTHS = {"bigrams": 784}


def _compare(name: str):
    def run(spark, sf_dir):
        points, queries = ta.hold_out(fo.materialised(_WORKLOADS[name](spark, sf_dir), "vectors", _WIDTHS.get(name, 1)))
        return ex.cost_to_recall(ex.compare(name, points, queries, K, P))

    return run


for _name in _WORKLOADS:
    query(None, f"cost_to_recall_{_name}")(_compare(_name))

_LABELS = "SELECT vec_id AS id, label FROM embeddings"


@query(sql.with_ctes(*sql.knn(P, VOTES, K), f"c AS (SELECT qid, label, count(*) AS n FROM knn JOIN ({_LABELS}) USING (id) GROUP BY ALL)", "SELECT qid, label, share FROM (SELECT qid, label, round(n / sum(n) OVER (PARTITION BY qid), 6) AS share, row_number() OVER (PARTITION BY qid ORDER BY n DESC, label) AS nth FROM c) WHERE nth = 1"))
def classify_by_neighbours(spark, sf_dir):
    _, queries, forest = setting(spark, sf_dir)
    return se.classify(se.approximate_knn(queries, forest, K, VOTES), ta.load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), "label"))


@query(sql.with_ctes(*sql.knn(P, VOTES, K), f"c AS (SELECT qid, label AS item, round(sum(1 / (1 + distance)), 6) AS score FROM knn JOIN ({_LABELS}) USING (id) GROUP BY ALL)", "SELECT qid, rank, item, score FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY score DESC, item) AS rank FROM c) WHERE rank <= 3"))
def recommend_by_neighbours(spark, sf_dir):
    _, queries, forest = setting(spark, sf_dir)
    items = ta.load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("label").alias("item"), F.lit(1.0).alias("weight"))
    return se.recommend(se.approximate_knn(queries, forest, K, VOTES), items, 3)


# ---- events, runs and streams --------------------------------------------------------------------------


def _events(spark, sf_dir):
    return ta.load(spark, sf_dir, "events")


query(su.TUMBLING, "tumbling_profiles")(lambda spark, sf_dir: sp.profiles(_events(spark, sf_dir), "tumbling"))
query(su.SLIDING, "sliding_profiles")(lambda spark, sf_dir: sp.profiles(_events(spark, sf_dir), "sliding", "event_type"))
query(su.SESSION, "session_profiles")(lambda spark, sf_dir: sp.profiles(_events(spark, sf_dir), "session"))
query(su.FOLLOWED, "interval_join")(lambda spark, sf_dir: sp.followed(_events(spark, sf_dir)))


@query(su.AS_OF)
def asof_profile(spark, sf_dir):
    e = _events(spark, sf_dir)
    return sp.as_of(e.where("event_type = 'purchase'").select("event_id", "user_id", "ts"), e.where("event_type = 'view'"), "user_id", "ts", ["event_id", "value"]).drop("ts")


@query(su.JSON)
def json_props(spark, sf_dir):
    k = F.get_json_object("props", "$.k").cast("long")
    return _events(spark, sf_dir).groupBy("event_type").agg(F.sum(k).alias("total"), F.count(k).alias("known"))


@query(_races("SELECT dataset, method, count(evals) AS reached, sum(evals)::BIGINT AS evals FROM t GROUP BY ROLLUP (dataset, method)"))
def rollup_runs(spark, sf_dir):
    return _race_times(spark, sf_dir).rollup("dataset", "method").agg(F.count("evals").alias("reached"), F.sum("evals").alias("evals"))


@query(sql.with_ctes(*_BOTH, su.SETS.format(both="")))
def set_ops_recall(spark, sf_dir):
    found, truth, _, _ = _compared(spark, sf_dir)
    a, t = found.select("qid", "id"), truth.select("qid", "id")
    return a.intersect(t).select(F.lit("found").alias("kind"), "qid", "id").unionByName(t.subtract(a).select(F.lit("missed").alias("kind"), "qid", "id"))


def _stream_folder(spark):
    return f"{work_folder(spark)}/streams/{uuid.uuid4().hex}"


query(su.FOLLOWED, "stream_interval_join")(lambda spark, sf_dir: sp.collected(sp.followed(sp.event_stream(spark, sf_dir)), _stream_folder(spark)))
query(su.TUMBLING, "stream_tumbling_profiles")(lambda spark, sf_dir: sp.collected(sp.profiles(sp.event_stream(spark, sf_dir), "tumbling"), _stream_folder(spark), "complete"))
query(None, "stream_running_vectors")(lambda spark, sf_dir: sp.collected(sp.running_vectors(sp.event_stream(spark, sf_dir)), _stream_folder(spark), "update"))

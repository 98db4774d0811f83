"""DuckDB SQL that restates the engine's results on the given tables, built from the same parameters."""

from __future__ import annotations

from .config import ForestParams


def with_ctes(*parts: str) -> str:
    """Common table expressions and the query over them, which comes last (and may bring expressions of its own)."""
    *ctes, last = parts
    return "WITH " + ", ".join(ctes) + (", " if last.startswith("splits AS") else " ") + last


def u(*parts: str) -> str:
    return f"(('0x' || substr(md5(concat_ws(':', {', '.join(parts)})), 1, 8))::BIGINT / 4294967296.0::DOUBLE)"


def directions(p: ForestParams, d: int) -> str:
    inner = p.direction_scope == "node"
    key = [str(p.seed), "tree", "level", *(["node"] if inner else []), "dim"]
    nodes = ", (SELECT l AS level, unnest(range(1 << l)) AS node FROM range(%d) r(l)) n" % p.depth if inner else ", (SELECT range AS level, NULL::INTEGER AS node FROM range(%d)) n" % p.depth
    kept = f"nth <= {p.nonzeros(d)}" if p.nnz == "exact" else f"u < {p.share(d)}::DOUBLE OR nth = 1"
    if p.components == "gaussian":
        weight = f"round(sqrt(-2 * ln({u(*key, repr('a'))} + 1 / 4294967296.0::DOUBLE)) * cos(2 * pi() * {u(*key, repr('b'))}), 6)"
    else:
        weight = f"CASE WHEN {u(*key, repr('a'))} < 0.5 THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END"
    grid = f"(SELECT t.range::INTEGER AS tree, n.level::INTEGER AS level, n.node::INTEGER AS node, m.range::INTEGER AS dim FROM range({p.trees}) t{nodes}, range({d}) m)"
    hashed = f"(SELECT *, {u(*key, repr('u'))} AS u FROM {grid})"
    return f"dirs AS (SELECT tree, level, node, dim, {weight} AS weight FROM (SELECT *, row_number() OVER (PARTITION BY tree, level, node ORDER BY u, dim) AS nth FROM {hashed}) WHERE {kept})"


def held_out(queries: int = 100) -> str:
    return f"ids AS (SELECT vec_id, row_number() OVER (ORDER BY md5('q:' || vec_id), vec_id) AS nth, count(*) OVER () AS n FROM embeddings), held AS (SELECT vec_id AS id, embedding AS vec FROM embeddings SEMI JOIN (SELECT vec_id FROM ids WHERE nth <= least({queries}, n // 5)) USING (vec_id)), pts AS (SELECT vec_id AS id, embedding AS vec FROM embeddings ANTI JOIN (SELECT id AS vec_id FROM held) USING (vec_id))"


def projections(p: ForestParams, points: str = "pts", name: str = "proj") -> str:
    return f"{name} AS (SELECT id, tree, level, node, round(sum(vec[dim + 1]::DOUBLE * weight), 9) AS value FROM {points}, dirs GROUP BY ALL)"


def _step(p: ForestParams, j: int) -> str:
    """Split values of a level and the nodes below it."""
    on = "p.id = x.id AND p.tree = x.tree AND p.level = %d" % j + (" AND p.node = x.node" if p.direction_scope == "node" else "")
    here = f"v{j} AS (SELECT x.id, x.tree, x.node, p.value FROM n{j} x JOIN proj p ON {on})"
    if p.tie == "rank":
        split = f"s{j} AS (SELECT tree, node, median(value) AS cut FROM v{j} GROUP BY ALL)"
        return f"{here}, {split}, n{j + 1} AS (SELECT id, tree, node * 2 + CASE WHEN nth > ceil(m / 2.0) THEN 1 ELSE 0 END AS node FROM (SELECT *, row_number() OVER (PARTITION BY tree, node ORDER BY value, id) AS nth, count(*) OVER (PARTITION BY tree, node) AS m FROM v{j}))"
    if p.split == "fractile":
        f = f"0.25 + 0.5 * {u(str(p.seed), 'tree', str(j), 'node', repr('f'))}"
        split = f"s{j} AS (SELECT tree, node, value AS cut FROM (SELECT *, row_number() OVER (PARTITION BY tree, node ORDER BY value, id) AS nth, count(*) OVER (PARTITION BY tree, node) AS m FROM v{j}) WHERE nth = ceil(({f}) * m))"
    else:
        split = f"s{j} AS (SELECT tree, node, median(value) AS cut FROM v{j} GROUP BY ALL)"
    return f"{here}, {split}, n{j + 1} AS (SELECT id, tree, node * 2 + CASE WHEN value > cut THEN 1 ELSE 0 END AS node FROM v{j} JOIN s{j} USING (tree, node))"


def forest(p: ForestParams, d: int = 64) -> list[str]:
    some = f" WHERE {u(str(p.seed), 'id', repr('sample'))} < {p.sample}::DOUBLE" if p.sample else ""
    start = f"n0 AS (SELECT id, range::INTEGER AS tree, 0 AS node FROM pts, range({p.trees}){some})"
    return [held_out(), directions(p, d), projections(p), start, *(_step(p, j) for j in range(p.depth))]


def all_splits(p: ForestParams) -> str:
    return "splits AS (" + " UNION ALL ".join(f"SELECT tree, {j} AS level, node, cut AS threshold FROM s{j}" for j in range(p.depth)) + ")"


def routes(p: ForestParams) -> list[str]:
    out = [projections(p, "held", "qproj"), f"q0 AS (SELECT id AS qid, range::INTEGER AS tree, 0 AS node FROM held, range({p.trees}))"]
    same = " AND p.node = x.node" if p.direction_scope == "node" else ""
    out += [f"q{j + 1} AS (SELECT x.qid, x.tree, x.node * 2 + CASE WHEN p.value > s.cut THEN 1 ELSE 0 END AS node FROM q{j} x JOIN qproj p ON p.id = x.qid AND p.tree = x.tree AND p.level = {j}{same} JOIN s{j} s ON s.tree = x.tree AND s.node = x.node)" for j in range(p.depth)]
    return out


def votes(p: ForestParams) -> list[str]:
    return [*forest(p), *routes(p), f"votes AS (SELECT qid, id, count(*)::INTEGER AS votes FROM n{p.depth} JOIN q{p.depth} USING (tree, node) GROUP BY ALL)"]


_L2 = "round(sqrt(list_sum([(a[i]::DOUBLE - b[i]) * (a[i]::DOUBLE - b[i]) FOR i IN range(1, len(a) + 1)])), 6)"
_METRIC = {
    "l2": _L2,
    "l1": "round(list_sum([abs(a[i]::DOUBLE - b[i]) FOR i IN range(1, len(a) + 1)]), 6)",
    "linf": "round(list_max([abs(a[i]::DOUBLE - b[i]) FOR i IN range(1, len(a) + 1)]), 6)",
    "cosine": "round(1 - list_sum([a[i]::DOUBLE * b[i] FOR i IN range(1, len(a) + 1)]) / (sqrt(list_sum([x::DOUBLE * x FOR x IN a])) * sqrt(list_sum([x::DOUBLE * x FOR x IN b]))), 6)",
}


def _ranked(name: str, pairs: str, k: int, metric: str = "l2") -> str:
    return f"{name} AS (SELECT qid, nth::INTEGER AS rank, id, distance FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY distance, id) AS nth FROM (SELECT qid, id, {_METRIC[metric]} AS distance FROM ({pairs}))) WHERE nth <= {k})"


def knn(p: ForestParams, least: int, k: int, where: str = "TRUE") -> list[str]:
    return [*votes(p), _ranked("knn", f"SELECT v.qid, v.id, h.vec AS a, x.vec AS b FROM votes v JOIN held h ON h.id = v.qid JOIN pts x ON x.id = v.id WHERE votes >= {least} AND v.{where}" if where != "TRUE" else f"SELECT v.qid, v.id, h.vec AS a, x.vec AS b FROM votes v JOIN held h ON h.id = v.qid JOIN pts x ON x.id = v.id WHERE votes >= {least}", k)]


def truth(k: int, metric: str = "l2") -> str:
    return _ranked("truth", "SELECT h.id AS qid, x.id, h.vec AS a, x.vec AS b FROM held h, pts x", k, metric)


def brute(k: int, metric: str = "l2") -> list[str]:
    return [held_out(), truth(k, metric)]


def self_join(p: ForestParams, least: int, k: int) -> list[str]:
    pairs = f"SELECT v.qid, v.id, h.vec AS a, x.vec AS b FROM (SELECT q.id AS qid, n.id, count(*) AS votes FROM n{p.depth} n JOIN n{p.depth} q USING (tree, node) WHERE q.id <> n.id GROUP BY ALL) v JOIN pts h ON h.id = v.qid JOIN pts x ON x.id = v.id WHERE votes >= {least}"
    return [*forest(p), _ranked("knn", pairs, k)]


def shortfall(k: int, least: int) -> str:
    pairs = "SELECT h.id AS qid, x.id, h.vec AS a, x.vec AS b FROM held h, pts x" if not least else f"SELECT v.qid, v.id, h.vec AS a, x.vec AS b FROM votes v JOIN held h ON h.id = v.qid JOIN pts x ON x.id = v.id WHERE votes >= {least}"
    return f"SELECT qid, rank, id, distance FROM knn WHERE qid IN (SELECT qid FROM knn GROUP BY qid HAVING count(*) >= {k}) UNION ALL SELECT qid, rank, id, distance FROM (WITH {_ranked('other', pairs, k)} SELECT * FROM other) WHERE qid NOT IN (SELECT qid FROM knn GROUP BY qid HAVING count(*) >= {k})"


def grid(p: ForestParams, k: int, trees: list[int], depths: list[int], votes_: list[int]) -> str:
    cells = f"c AS (SELECT t AS trees, l AS depth, qid, id, count(*) AS f FROM n{p.depth} n JOIN q{p.depth} q USING (tree), (SELECT unnest({trees}) AS t), (SELECT unnest({depths}) AS l) WHERE tree < t AND n.node >> ({p.depth} - l) = q.node >> ({p.depth} - l) GROUP BY ALL)"
    return with_ctes(*forest(p), *routes(p), truth(k), cells, f"SELECT trees::INTEGER AS trees, depth::INTEGER AS depth, v::INTEGER AS votes, round(count(t.id) / ({k}.0 * (SELECT count(*) FROM held)), 6) AS recall, count(*) AS candidates FROM c JOIN (SELECT unnest({votes_}) AS v) ON f >= v LEFT JOIN truth t USING (qid, id) GROUP BY ALL")


def _forest_runs(p: ForestParams, ks: tuple[int, ...], trees: list[int], depths: list[int], votes_: list[int]) -> str:
    """The grid of a forest for several k: candidates are counted once by votes and true rank."""
    cells = f"c AS (SELECT t AS trees, l AS depth, qid, id, count(*) AS f FROM n{p.depth} n JOIN q{p.depth} q USING (tree), (SELECT unnest({trees}) AS t), (SELECT unnest({depths}) AS l) WHERE tree < t AND n.node >> ({p.depth} - l) = q.node >> ({p.depth} - l) GROUP BY ALL)"
    counts = "g AS (SELECT trees, depth, f, rank, count(*) AS n FROM c LEFT JOIN truth USING (qid, id) GROUP BY ALL)"
    return with_ctes(*forest(p), *routes(p), truth(max(ks)), cells, counts, f"SELECT k, v AS votes, round(coalesce(sum(n) FILTER (rank <= k), 0) / (k::DOUBLE * (SELECT count(*) FROM held)), 6) AS recall, sum(n)::BIGINT AS evals FROM g, (SELECT unnest({list(ks)}) AS k), (SELECT unnest({votes_}) AS v) WHERE f >= v GROUP BY k, v, trees, depth")


def races(dense: ForestParams, sparse: ForestParams, ks: tuple[int, ...], trees: list[int], depths: list[int], votes_: list[int], last: str, levels: tuple[float, ...]) -> str:
    """Runs of forests and of brute force on the embeddings as runs, their least distances to each recall level as t, wins at some levels as w, and a query over them."""
    some = ", ".join(map(str, levels))
    return with_ctes(
        held_out(), f"thin AS ({_forest_runs(sparse, ks, trees, depths, votes_)})", f"full_ AS ({_forest_runs(dense, ks, trees, depths, [1])})",
        f"runs AS (SELECT 'k=' || k AS dataset, 'dense_forest' AS method, recall, evals FROM full_ UNION ALL SELECT 'k=' || k, 'sparse_forest', recall, evals FROM thin WHERE votes = 1 UNION ALL SELECT 'k=' || k, 'voting_forest', recall, evals FROM thin UNION ALL SELECT 'k=' || k, 'brute_force', 1.0::DOUBLE, (SELECT count(*) FROM pts) * (SELECT count(*) FROM held) FROM (SELECT unnest({list(ks)}) AS k))",
        "t AS (SELECT dataset, level, method, min(evals) FILTER (recall >= level) AS evals FROM runs, (SELECT unnest([0.80, 0.90, 0.95, 0.99]::DOUBLE[]) AS level) GROUP BY ALL)",
        f"w AS (SELECT method, sum(CASE WHEN nth = 1 THEN 1 ELSE 0 END)::BIGINT AS wins, count(*) AS races FROM (SELECT *, rank() OVER (PARTITION BY dataset, level ORDER BY evals) AS nth FROM t WHERE level IN ({some}) AND evals IS NOT NULL) GROUP BY method)",
        last,
    )


def cost_model(p: ForestParams) -> str:
    t, depth = p.trees, p.depth
    return (
        f"WITH m AS (SELECT n, d, round(1 / sqrt(d), 9) AS a FROM (SELECT count(*)::DOUBLE AS n, max(len(embedding))::DOUBLE AS d FROM embeddings)) "
        f"SELECT 'dense' AS method, round({t} * d * ({depth} + n / (1 << {depth})), 6) AS query_cost, round({t} * {depth} * n * d, 6) AS build_cost, round({t} * (d * ((1 << {depth}) - 1) + n), 6) AS memory FROM m "
        f"UNION ALL SELECT 'sparse', round({t} * ({depth} * a * d + n / (1 << {depth}) * d), 6), round({t} * {depth} * n * a * d, 6), round({t} * (a * d * {depth} + (1 << {depth}) - 1 + n), 6) FROM m"
    )


def _histogram(rows: str, d: int, digits: int = 4) -> str:
    return f"WITH r AS ({rows}), s AS (SELECT k, b, sum(v) AS v FROM r GROUP BY ALL), m AS (SELECT k, map_from_entries(list((b, v))) AS m FROM s GROUP BY k) SELECT k AS id, [round(coalesce(m[i], 0.0), {digits})::DOUBLE FOR i IN range({d})] AS vec FROM m"


USER_PROFILES = _histogram("SELECT user_id AS k, (dense_rank() OVER (ORDER BY event_type) - 1) * 24 + hour(ts) AS b, 1.0::DOUBLE AS v FROM events", 120)
PART_DEMAND = _histogram("SELECT l_partkey AS k, date_diff('day', DATE '1995-01-01', l_shipdate::DATE) // 20 AS b, l_quantity AS v FROM lineitem WHERE date_diff('day', DATE '1995-01-01', l_shipdate::DATE) BETWEEN 0 AND 2559", 128)
CUSTOMER_BRAND = _histogram("SELECT o_custkey AS k, b, l_extendedprice * (1 - l_discount) AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON c_custkey = o_custkey JOIN (SELECT p_partkey, dense_rank() OVER (ORDER BY p_brand) - 1 AS b FROM part) ON p_partkey = l_partkey", 25)


def _hashed_counts(rows: str, d: int, digits: int = 4) -> str:
    """Counts of tokens g of keys k in d buckets, at length 1."""
    return f"WITH r AS ({rows}), s AS (SELECT k, (('0x' || substr(md5(g), 1, 8))::BIGINT % {d})::INTEGER AS b, count(*)::DOUBLE AS v FROM r GROUP BY ALL), m AS (SELECT k, map_from_entries(list((b, v))) AS m, 1.0::DOUBLE / sqrt(sum(v * v)) AS f FROM s GROUP BY k) SELECT k AS id, [round(coalesce(m[i], 0.0) * f, {digits})::DOUBLE FOR i IN range({d})] AS vec FROM m"


DOC_BIGRAMS = _hashed_counts("SELECT k, g FROM (SELECT k, substr(t, p, 2) AS g FROM (SELECT doc_id AS k, lower(text) AS t, unnest(range(1, length(text) + 1)) AS p FROM documents)) WHERE regexp_full_match(g, '[a-z]{2}')", 784)
PAGE_FEATURES = _hashed_counts("SELECT page_id AS k, unnest(regexp_extract_all(lower(regexp_replace(html, '<[^>]*>', ' ', 'g')), '[a-z]+')) AS g FROM pages", 960)

"""The driver's queries for the training-data operators, and their SQL where there is one."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import langid, licenses, mih, mixing, sharding, simhash, tokenstore, toxicity, urltree, winnowing
from .common import crc_mod, literal_rows, table, work_folder

Query = Callable[[SparkSession, str], DataFrame]


#: Target weights of the mix: level (0 domain, 1 language, 2 source), name, weight. Others weigh 1.
MIX_WEIGHTS = ((0, "d0", 3), (0, "d1", 2), (1, "en", 4), (1, "de", 2), (1, "fr", 2), (2, "src0", 2))
MIX_SHARE, MIX_EPOCHS, MIX_SEED = 0.5, 2, 42


def domain_of(source: str = "source"):
    """A document's domain: one of four, by its source."""
    return F.concat(F.lit("d"), F.crc32(F.coalesce(F.col(source), F.lit("")).cast("binary")) % 4)


def op1_hierarchical_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    weights = literal_rows(spark, MIX_WEIGHTS, "level int, name string, weight long")
    return mixing.mix(table(spark, sf_dir, "documents"), domain_of(), MIX_SHARE, MIX_EPOCHS, weights, MIX_SEED)


def op3_bounded_load_ring(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = sharding.assign_rows(sharding.measured(table(spark, sf_dir, "documents")), tie=["size", "text_crc32"])
    return rows.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def op5_license_compression(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan_documents(table(spark, sf_dir, "documents")).drop("spans")


def op6_multi_index_hashing(spark: SparkSession, sf_dir: str) -> DataFrame:
    points = mih.with_code(table(spark, sf_dir, "embeddings"))
    asked = points.where("id % 100 = 0").select(F.col("id").alias("qid"), F.col("code").alias("qcode"))
    return mih.nearest(points, asked).select(F.col("qid").alias("query_id"), "rank", F.col("id").alias("vec_id"), "distance")


def op10_path_template_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urltree.judge(table(spark, sf_dir, "pages"))


def op2_simhash_vantage_trees(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.near_duplicates(table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op4_winnowing_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = winnowing.measured(winnowing.shared_spans(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark")))
    return found.select("doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated")


def op7_naive_bayes_ngram_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = toxicity.train(docs, table(spark, sf_dir, "labels"), where=toxicity.learnable())
    scored = toxicity.score(docs, model)
    return scored.select("doc_id", (crc_mod("doc_id", 3) == 1).alias("held_out"), "score", (F.col("score") >= toxicity.THRESHOLD).cast("int").alias("predicted"))


def op8_content_addressed_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = f"{work_folder(spark)}/tokens-{uuid.uuid4().hex}"
    tokenstore.write_store(table(spark, sf_dir, "documents"), path)
    return tokenstore.read_digests(spark, path).select("doc_id", "start", "n_tokens", "ids_crc32", "verified")


def op9_rank_order_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    profiles = langid.train(docs, where=langid.learnable())
    return langid.identify(docs, profiles).select("doc_id", (crc_mod("doc_id", 5) == 0).alias("held_out"), "lang_pred", "score")


#: Words of whole texts as the decontamination contract takes them, in DuckDB.
_WORDS = "regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[0-9a-z\\x{80}-\\x{10FFFF}]+')"

OP4_SQL = f"""
WITH d AS (SELECT doc_id, {_WORDS} AS w FROM documents),
i AS (SELECT item_id, w, least(13, len(w)) AS n FROM (SELECT item_id, {_WORDS} AS w FROM benchmark) WHERE len(w) > 0),
iw AS (SELECT DISTINCT item_id, n, array_to_string(w[p:p + n - 1], ' ') AS g
       FROM (SELECT item_id, w, n, unnest(range(1, len(w) - n + 2)) AS p FROM i)),
dw AS (SELECT doc_id, n, p, array_to_string(w[p:p + n - 1], ' ') AS g
       FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS p FROM d, (SELECT DISTINCT n FROM i) WHERE len(w) >= n)),
hits AS (SELECT doc_id, n, p, item_id FROM dw JOIN iw USING (n, g)),
words_hit AS (SELECT doc_id, count(DISTINCT q) AS n_hit FROM (SELECT doc_id, unnest(range(p, p + n)) AS q FROM (SELECT DISTINCT doc_id, n, p FROM hits)) GROUP BY 1),
items AS (SELECT doc_id, count(*) AS n_items, string_agg(s, ',' ORDER BY s) AS list FROM (SELECT DISTINCT doc_id, item_id::VARCHAR AS s FROM hits) GROUP BY 1)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
       sha256(coalesce(list, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated
FROM d LEFT JOIN words_hit USING (doc_id) LEFT JOIN items USING (doc_id)
"""

QUERIES: dict[str, Query] = {
    f.__name__: f
    for f in (
        op1_hierarchical_mix,
        op2_simhash_vantage_trees,
        op3_bounded_load_ring,
        op4_winnowing_decontamination,
        op5_license_compression,
        op6_multi_index_hashing,
        op7_naive_bayes_ngram_toxicity,
        op8_content_addressed_tokens,
        op9_rank_order_language,
        op10_path_template_filter,
    )
}
OP6_SQL = """
WITH q AS (SELECT vec_id AS query_id, embedding AS e FROM embeddings WHERE vec_id % 100 = 0),
d AS (SELECT query_id, vec_id, list_sum([CASE WHEN (q.e[i] > 0) <> (p.embedding[i] > 0) THEN 1 ELSE 0 END FOR i IN range(1, 65)])::INTEGER AS distance FROM q, embeddings p),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY distance, vec_id)::INTEGER AS rank FROM d)
SELECT query_id, rank, vec_id, distance FROM r WHERE rank <= 10
"""

SQL: dict[str, str] = {"op4_winnowing_decontamination": OP4_SQL, "op6_multi_index_hashing": OP6_SQL}

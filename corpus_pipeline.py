"""The corpus pipeline: toxicity, near-duplicates, decontamination, mixing, token output."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from knnvote.llm import mixing, simhash, tokenstore, toxicity, winnowing
from knnvote.llm.common import give_back, literal_rows, table, work_folder
from knnvote.llm.queries import MIX_WEIGHTS, domain_of


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejects documents that score 0.7 or more; the classifier learns from all labelled documents."""
    give_back(spark)
    model = toxicity.train(docs, table(spark, sf_dir, "labels"))
    give_back(spark)
    return toxicity.without_toxic(docs, model)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the document of the least id of each group: SimHash links over five-word shingles, and links of similarity 0.8 or more."""
    give_back(spark)
    return simhash.one_of_each(docs, shingle=5, radius=simhash.RADIUS, similarity=0.8)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejects documents of which benchmark passages make up a twentieth of the words or more."""
    give_back(spark)
    return winnowing.without_contaminated(docs, table(spark, sf_dir, "benchmark"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps three quarters of the words, dealt to domains, languages and sources by weight; each document once at most."""
    give_back(spark)
    weights = literal_rows(spark, MIX_WEIGHTS, "level int, name string, weight long")
    return mixing.mixed_rows(docs, domain_of(), 0.75, weights)


def write_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Writes the documents' token ids into a content-addressed store and reads it back."""
    give_back(spark)
    path = f"{work_folder(spark)}/tokens-{uuid.uuid4().hex}"
    tokenstore.write_store(docs, path)
    give_back(spark)
    return tokenstore.read_digests(spark, path)


STAGES = [
    ("toxicity", drop_toxic),
    ("near_dedup", drop_near_copies),
    ("decontamination", drop_contaminated),
    ("mixing", mix_sources),
    ("token_output", write_tokens),
]

#: Fingerprint groups, a fitted classifier and tokenisation are beyond SQL.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over `documents`; each one's rows are written as Parquet and read again for the next."""
    docs = table(spark, sf_dir, "documents")
    folder = f"{work_folder(spark)}/pipeline-{uuid.uuid4().hex}"
    for k, (name, stage) in enumerate(STAGES):
        out = stage(spark, docs, sf_dir)
        if k + 1 == len(STAGES):
            return out
        out.write.parquet(f"{folder}/{k}-{name}")
        docs = spark.read.schema(out.schema).parquet(f"{folder}/{k}-{name}")
    return docs

"""The stages of corpus_pipeline.py: each takes (spark, docs, sf_dir) and returns what it keeps, with the columns of documents; the last packs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from contactscope.llm import decontaminate, exact_dedup, language, packing, simhash
from contactscope.llm.common import table, without_ids

#: Documents whose best language holds a smaller share of the positions are rejected.
LEAST_SHARE = 0.3


def keep_known_languages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return language.accepted(docs, language.fit(docs), LEAST_SHARE)


def keep_first_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return without_ids(docs, exact_dedup.duplicates(docs).where("not kept").select("doc_id"), rows=docs.count())


def keep_one_of_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return without_ids(docs, simhash.near_duplicates(docs).where("doc_id <> component_id").select("doc_id"), rows=docs.count())


def drop_benchmark_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.drop_contaminated(docs, table(spark, sf_dir, "benchmark"))


def pack_mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack(docs)

"""Corpus pipeline: language ID, exact dedup, SimHash near-dedup, benchmark decontamination, packing.

Every stage's result is written as Parquet to the shared folder and read again as the documents of the next one, so a lost
executor costs at most one stage's tasks, and each stage sees all rows its predecessor kept.

Defined results: documents with null, empty or letterless text are rejected by the first stage; null lang, source or doc_id don't matter to any stage's decision, but rows with a null
doc_id are never dropped as copies; rows that repeat a doc_id share its fate as copies; of exact copies the longest original text stays, then the smallest doc_id, of a near-duplicate group the smallest doc_id; further columns,
whatever their names, pass through to the last stage, which reads doc_id, text and source alone; an empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from contactscope.llm import pipeline_stages as stages
from contactscope.llm.common import stored, table

STAGES = [
    ("language_id", stages.keep_known_languages),
    ("exact_dedup", stages.keep_first_copies),
    ("simhash_dedup", stages.keep_one_of_near_copies),
    ("decontamination", stages.drop_benchmark_documents),
    ("packing", stages.pack_mixture),
]

#: Trained networks and XXH64 fingerprints can't be expressed in DuckDB SQL; tests compare with a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = stored(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)

"""From raw documents to packed sequences: toxicity, near duplicates, shared passages, secrets, packing."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from variety.llm.common import table, written
from variety.llm.near_duplicates import keep_one_of_each
from variety.llm.packing import pack_sequences
from variety.llm.passages import cut_shared_passages
from variety.llm.secrets import redact_secrets
from variety.llm.toxicity import drop_toxic

#: Each stage takes (spark, docs, sf_dir); all but the last return the columns of documents.
STAGES = [
    ("toxicity", drop_toxic),
    ("near_duplicates", keep_one_of_each),
    ("substring_dedup", cut_shared_passages),
    ("secret_scan", redact_secrets),
    ("best_fit_packing", pack_sequences),
]

#: No stage but the joins can be said in SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)

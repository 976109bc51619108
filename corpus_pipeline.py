"""A corpus pipeline of five stages over ``documents``.

Toxic documents go; of each group of near duplicates the document of the least id stays; documents that
overlap a benchmark item go; secrets are replaced in place; what is left is packed into
token sequences.  Each stage reads what the one before it wrote, whole, and all but the last
return the columns of ``documents``.

Every stage keeps rows with null ids or null texts (they are not toxic, not near duplicates, overlap nothing and
have no secrets); such a text packs as the closing id alone.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from rangeann.llm import decontamination, jaccard, packing, secrets, toxicity
from rangeann.llm.common import staged, table
from rangeann.llm.queries import VOCABULARY

#: Of a packing worker: after the join executors have less memory left than where packing runs alone.
CACHE_ENTRIES = 400_000


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return toxicity.keep_clean(docs, toxicity.fit_on(docs, table(spark, sf_dir, "labels")), threshold=0.7)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return jaccard.keep_first(docs)


def drop_benchmark_overlaps(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontamination.keep_clean(docs, table(spark, sf_dir, "benchmark"))


def replace_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return secrets.redact(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack(docs, public_tokenizers.path(VOCABULARY), capacity=4096, end_id=1, cache_entries=CACHE_ENTRIES)


STAGES = [
    ("toxicity", drop_toxic),
    ("n-gram Jaccard join", drop_near_duplicates),
    ("benchmark decontamination", drop_benchmark_overlaps),
    ("secret scans", replace_secrets),
    ("best-fit packing", pack),
]

ORACLE_SQL = None  # learnt scores, fingerprints and token ids are beyond SQL; tests hold the stages against plain versions


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = staged(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)

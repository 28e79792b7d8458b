"""A corpus in five stages: classify, drop near copies, redact secrets, mix sources, pack sequences.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame that is written as Parquet and read again
as the next one's docs. All but the last return the columns of documents.

What each stage decides: rows below the quality threshold go; of each group of near copies one row stays;
secrets in the texts give way to their kind in brackets; each row comes as often as the mix takes it whole, and
once more cut to the words of the blocks that the last pass draws; every piece of a text gets its place in a sequence.

Defined cases: a null or empty text is a text without words, scored like any other; of near copies the row of the smallest doc_id stays
(null last), of rows alike in doc_id and text one; repeated rows that differ in doc_id are copies; the mix takes nothing of texts without words; texts of any length
stay whole; empty tables, and no labels, give an empty table or keep all; columns beside those of documents, of whatever name, come back as they were
from all stages but the last.

ORACLE_SQL is None: no SQL engine expresses the classifier, the fingerprints or the tokens. The stages are
held against brute-force versions in tests/llm.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from balclust.llm import common, mixing, packing, quality, secrets, simhash

ORACLE_SQL = None


def classify(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality.keep_good(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return simhash.keep_one(docs)


def redact_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return secrets.redact(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.apply(docs)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack(packing.pieces(docs))


STAGES = [
    ("quality_classifier", classify),
    ("simhash_near_dedup", drop_near_copies),
    ("secret_scans", redact_secrets),
    ("source_mix", mix_sources),
    ("sequence_packing", pack_sequences),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.documents(spark, sf_dir)
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = common.stage(docs)
    return docs

"""A corpus pipeline: each stage reads what its predecessor kept, and writes it for the next.

language: documents without letters, or in no language that was learned (junk, other languages and scripts), go.
dedup:    of each group linked by 4-word shingles (Jaccard 0.85 or more), one row stays, that of the smallest doc_id.
decontam: documents in which a benchmark item is found go.
secrets:  found secrets are replaced by a mark.
packing:  documents are packed into token sequences.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from caseloom.llm import decontam, jaccard, kernels, language, packing, secrets


def language_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return language.keep_identified(docs, language.fit(language.sample(docs)))


def dedup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return jaccard.distinct(docs)


def decontam_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontam.clean(docs, kernels.table(spark, sf_dir, "benchmark"))


def secrets_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return secrets.redact(docs, secrets.fit(docs))


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return packing.pack(packing.pieces(docs, public_tokenizers.path("word_bpe_49k.json")))


STAGES = [("language_id", language_stage), ("jaccard_join", dedup_stage), ("decontamination", decontam_stage), ("secret_scan", secrets_stage), ("best_fit_packing", packing_stage)]

#: Models and similarity components are beyond SQL; a brute-force version is in tests/llm.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; what a stage returns is written as Parquet in the shared folder and read again."""
    kernels.ready(spark)
    root = f"{spark.sparkContext._jsc.sc().getCheckpointDir().get()}/pipeline-{uuid.uuid4().hex}"
    docs = kernels.table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        stage(spark, docs, sf_dir).write.parquet(f"{root}/{k}")
        docs = spark.read.parquet(f"{root}/{k}")
    return docs

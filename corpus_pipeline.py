"""A corpus pipeline of five stages, each over all that its predecessor kept.

Language ID drops documents without a language, SimHash near-dedup keeps one document of each
group, decontamination drops documents that hold a benchmark item, PII spans are replaced by their
kind, and BPE gives ids and digests. Every stage but the last returns the columns it was given.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from serieslake.llm import bpe, decontam, langid, pii, simhash
from serieslake.llm.common import shared_folder, table, tuned


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    tuned(spark)
    return langid.keep_identified(docs)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    tuned(spark)
    return simhash.one_of_each(docs)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    tuned(spark)
    return decontam.clean(docs, table(spark, sf_dir, "benchmark"))


def redact_personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    tuned(spark)
    return pii.redact(docs)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    tuned(spark)
    return bpe.encode_decode(docs, with_text=False)


STAGES = [("language_id", identify_language), ("simhash_near_dedup", drop_near_duplicates), ("benchmark_decontamination", drop_contaminated), ("pii", redact_personal_data), ("bpe", encode)]

#: SQL can't express piece sums, SimHash groups or BPE; tests/llm holds run() against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages in order; each is written to the shared folder and read again, so none is run twice. What a
    stage has read is deleted once its own output stands; only the last stage's input stays."""
    docs, folder, before = table(spark, sf_dir, "documents"), f"{shared_folder(spark)}/pipeline-{uuid.uuid4()}", None
    at = spark._jvm.org.apache.hadoop.fs.Path
    files = at(folder).getFileSystem(spark._jsc.hadoopConfiguration())
    for name, stage in STAGES[:-1]:
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
        if before:
            files.delete(at(f"{folder}/{before}"), True)
        before = name
    return STAGES[-1][1](spark, docs, sf_dir)

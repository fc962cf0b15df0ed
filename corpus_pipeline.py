"""A training corpus from `documents`: toxic texts out, exact and near copies out, sources mixed to target weights, texts encoded."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from studymap.llm.base import remove, table, work_folder
from studymap.llm.exact_dedup import without_exact_duplicates
from studymap.llm.mixing import mixed_documents
from studymap.llm.near_dedup import without_near_duplicates
from studymap.llm.sentencepiece_viterbi import encode
from studymap.llm.toxic_crf import without_toxic

#: SQL has no twin of the chain field or of the segmentation; tests hold each stage against a brute-force version.
ORACLE_SQL = None


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the chain field, fitted on labels.toxic of the stage's own documents, rejects go."""
    return without_toxic(docs, table(spark, sf_dir, "labels"))


def exact_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts the largest doc_id stays."""
    return without_exact_duplicates(docs)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of linked texts (five-word shingles, similarity 0.75 or more) the smallest doc_id stays."""
    return without_near_duplicates(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sources take their shares of the words, better documents first; documents of small sources repeat, those beyond a large source's share go."""
    return mixed_documents(docs, table(spark, sf_dir, "labels").select("doc_id", "quality"))


def tokenise(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, ids, n_tokens, n_byte_tokens and round_trip of every document that is left."""
    return encode(docs)


STAGES = [("toxicity", toxicity), ("exact_dedup", exact_dedup), ("near_dedup", near_dedup), ("mix_sources", mix_sources), ("tokenise", tokenise)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents, each written as Parquet in the shared folder and read again by the next; a stage's files go once the next one is written."""
    folder = f"{work_folder(spark)}/pipeline-{uuid.uuid4().hex}"
    docs, before = table(spark, sf_dir, "documents"), None
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            at = f"{folder}/{k}-{name}"
            docs.write.parquet(at)
            docs = spark.read.parquet(at)
            if before:
                remove(spark, before)
            before = at
    return docs

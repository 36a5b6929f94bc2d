"""Documents to packed training sequences, in five stages; each is written as Parquet and read again by the next."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from zspan.llm import jaccard, langid, linededup, packing, secret_scan
from zspan.llm.common import is_held_out, written

VOCABULARY = public_tokenizers.path("byte_bpe_50k.json")


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents without a letter and those that no mixture of the learned languages explains."""
    model = langid.learn(docs.where(~is_held_out(F.col("doc_id"))).select("doc_id", "text", "lang"))
    return langid.accepted(spark, docs, model)


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str, passages: bool = False) -> DataFrame:
    """Removes repeated chunks of lines, with ``passages`` all repeated passages too, and documents that held nothing else."""
    found = linededup.clean(docs, passages=passages)
    left = (F.col("n_dropped") == 0) | (F.length(F.trim("text")) > 0)
    return found.where(left).withColumn("n_chars", F.when(F.col("n_dropped") > 0, F.length("text")).otherwise(F.col("n_chars")).cast(docs.schema["n_chars"].dataType)).select(docs.columns)


def whole_line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Removes repeated runs of lines, and documents that held nothing else."""
    return line_dedup(spark, docs, sf_dir, passages=True)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the document with the least doc_id of each class of near duplicates."""
    return jaccard.keep_one(docs)


def secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Masks the secrets in the texts."""
    return secret_scan.redact(docs, secret_scan.train(VOCABULARY), VOCABULARY)


def best_fit_packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Packs the tokenised documents into sequences."""
    return packing.pack(docs, VOCABULARY)


STAGES = [
    ("language ID", language_id),
    ("line dedup", whole_line_dedup),
    ("n-gram Jaccard join", near_duplicates),
    ("secret scans", secrets),
    ("best-fit packing", best_fit_packing),
]

#: Language mixtures, chosen paths, forests and tokenizers are beyond SQL; tests hold every stage against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The last stage's rows over the documents of ``sf_dir``."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)

"""The corpus pipeline: five filters and transforms over documents, each written and read again as the next one's input.

Rules of the stages, all with the operators' production parameters:

* language_id drops documents without any letter (`und`) and those whose best language has less than MIN_LANG_SCORE;
* toxicity drops documents that the machine calls toxic (score of at least 0.5); it learns from `labels`;
* near_duplicates keeps the smallest doc_id of each component, and every document without words;
* pii replaces personal data in texts by its kind, and sets n_chars anew;
* packing packs what is left; its rows are those of the packing operator.

Before each stage executors give back the memory that the one before no longer needs.

All stages but the last return the columns of documents. Extra columns pass through; rows that repeat
a doc_id are one document and stay together.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ctxrelease.llm import langid, ngram_join, packing, pii, toxicity
from ctxrelease.llm.common import append_columns, fresh
from ctxrelease.plans.runtime import relax, shared_dir

Stage = Callable[[SparkSession, DataFrame, str], DataFrame]

#: A clean document in a learned language scores far higher; see the README for the distribution.
MIN_LANG_SCORE = 0.3


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps documents with a letter and a language score of at least MIN_LANG_SCORE; null and empty texts go.

    It learns from the documents' own `lang`; without any, every document is unknown and goes. Columns of any name pass.
    """
    lang, score = fresh(docs, "__lang"), fresh(docs, "__score")
    judged = langid.identify(docs, langid.train(docs), names=(lang, score))
    return judged.where((F.col(lang) != langid.UNKNOWN) & (F.col(score) >= MIN_LANG_SCORE)).select(*docs.columns)


def toxicity_filter(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps documents whose toxicity score is under 0.5; a null or empty text has the intercept's score and stays."""
    name = fresh(docs, "__toxic")
    machine = toxicity.train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return toxicity.score(docs, machine, name=name).where(F.col(name) < 0.5).select(*docs.columns)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the smallest doc_id of each component, and every document without words or without a doc_id."""
    gone = ngram_join.near_duplicates(docs).where(F.col("n_shingles") > 0).where("doc_id <> component_id").select("doc_id").distinct()
    return docs.join(gone, "doc_id", "left_anti").select(*docs.columns)


def pii_redaction(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Replaces personal data by its kind in every text and sets n_chars anew; null texts stay null."""
    name = fresh(docs, "__clean")
    clean = append_columns(docs, "text", [T.StructField(name, T.StringType())], lambda: lambda texts: [[pii.redact(t) for t in texts]], owner="pii")
    out = clean.withColumn("text", F.col(name))
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.col("text").isNotNull(), F.char_length("text")).cast(docs.schema["n_chars"].dataType))
    return out.select(*docs.columns)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Packs all documents; rows are those of the packing operator. A null or empty text is one end mark."""
    return packing.pack_documents(docs)


def _relaxed(stage: Stage) -> Stage:
    def run_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        relax(spark)
        return stage(spark, docs, sf_dir)

    return run_stage


STAGES: list[tuple[str, Stage]] = [
    (name, _relaxed(stage))
    for name, stage in (("language_id", language_id), ("toxicity", toxicity_filter), ("near_duplicates", near_duplicates), ("pii", pii_redaction), ("packing", pack))
]

#: Trained models and the tokenizer have no SQL; tests compare the stages with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Applies the stages to documents; each result is a written table in the shared folder."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    folder = f"{shared_dir(spark)}/pipeline-{uuid.uuid4().hex}"
    for name, stage in STAGES:
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
    return docs

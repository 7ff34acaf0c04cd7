"""Documents to token files in five stages, each calling one of the corpus operators."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from docspj.llm.common import read_table, scratch
from docspj.llm.decontaminate import keep_clean
from docspj.llm.language import keep_identified, train_language_model
from docspj.llm.minhash import near_duplicates
from docspj.llm.mixture import mixed_rows
from docspj.llm.token_files import tokenise


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents stay unless the language model, trained on their own labels, rejects them."""
    return keep_identified(docs, train_language_model(docs))


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate group, the one of least id, stays; rows without an id stay."""
    name = "kept_id"
    while name in docs.columns:
        name += "_"
    kept = near_duplicates(docs).where("kept").select(F.col("doc_id").alias(name)).distinct()
    return docs.join(kept, F.col("doc_id").eqNullSafe(F.col(name)), "left_semi")


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in which a benchmark item is found go."""
    return keep_clean(docs, read_table(spark, sf_dir, "benchmark"))


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mix of sources; a document that two epochs take is two rows."""
    return mixed_rows(docs)


def token_files(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token files of the mix, and what they hold of each row."""
    return tokenise(docs, public_tokenizers.path("byte_bpe_50k.json"), remembered=100_000)


STAGES = [("language_id", language_id), ("near_dedup", near_dedup), ("decontaminate", decontaminate), ("mix", mix), ("token_files", token_files)]

#: Language models, minima and tokenizers are beyond SQL; tests hold each stage against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages; each one's rows are written to the shared folder before the next reads them, so no stage is computed twice."""
    docs = read_table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        done = stage(spark, docs, sf_dir)
        docs = done if name == STAGES[-1][0] else scratch(done, name)
    return docs

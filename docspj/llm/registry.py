"""The corpus operators' queries for the driver, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from docspj.llm.common import held_out, read_table
from docspj.llm.decontaminate import contaminated
from docspj.llm.exact import exact_duplicates
from docspj.llm.language import identify, train_language_model
from docspj.llm.licences import scan_licences
from docspj.llm.line_templates import drop_recurring_lines
from docspj.llm.minhash import near_duplicates
from docspj.llm.mixture import mix_sources
from docspj.llm.quality import score_quality, train_quality_model
from docspj.llm.secrets import KINDS, labelled_samples, scan_secrets, span_text, train_markov
from docspj.llm.token_files import tokenise


def op1_mixture(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix_sources(read_table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken", "source", "copies")


def op2_licence_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_licences(read_table(spark, sf_dir, "documents"))


def op3_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    found = scan_secrets(docs, train_markov(labelled_samples(docs)))
    # A lambda's second argument, a default one too, would be given a span's place.
    count = lambda kind: F.size(F.filter("base", lambda s: s["kind"] == kind)).cast("long")
    counts = [count(k).alias(f"n_{name}") for k, name in enumerate(KINDS)]
    everything = F.array_sort(F.concat("base", "added"))
    return found.select("doc_id", *counts, F.sha2(span_text(F.col("base")).cast("binary"), 256).alias("base_sha256"), span_text(everything).alias("spans"))


def op4_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokenise(read_table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json")).select("doc_id", "start", "n_tokens", "ids_crc32")


def op5_minhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(read_table(spark, sf_dir, "documents"))


def op6_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_duplicates(read_table(spark, sf_dir, "documents"))


OP6_SQL = r"""
with t as (
  select doc_id, coalesce(length(text), 0) as points,
         sha256(regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]', '', 'g')) as text_sha256
  from documents)
select doc_id,
       first_value(doc_id) over (partition by text_sha256 order by points desc, doc_id nulls last) as keep_id,
       count(*) over (partition by text_sha256) as group_size,
       doc_id is not distinct from first_value(doc_id) over (partition by text_sha256 order by points desc, doc_id nulls last) as kept,
       text_sha256
from t"""


def op7_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    scored = score_quality(docs, train_quality_model(docs, read_table(spark, sf_dir, "labels")))
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", "predicted")


def op8_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    found = identify(docs, train_language_model(docs))
    return found.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score", "rejected")


def op9_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return drop_recurring_lines(read_table(spark, sf_dir, "documents"))


def op10_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contaminated(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "benchmark"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found = (op1_mixture, op2_licence_scan, op3_secret_scan, op4_token_files, op5_minhash_dedup, op6_exact_dedup, op7_quality, op8_language_id, op9_line_dedup, op10_decontamination)
    return {f.__name__: f for f in found}


def oracle_sql() -> dict[str, str]:
    return {"op6_exact_dedup": OP6_SQL}

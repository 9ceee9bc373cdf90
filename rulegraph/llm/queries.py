"""The registered queries over the given tables: each applies one operator to its whole table."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rulegraph.llm import html_text, language_id, language_model, line_dedup, media, mixing, packing, quality, simhash, suffix_dedup
from rulegraph.llm.attention import ModelShape
from rulegraph.llm.common import crc_mod, ship

TOKENIZER = public_tokenizers.path("word_bpe_49k.json")


def _docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def op1_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _docs(spark, sf_dir).select("doc_id", "text", "lang")
    held_out = F.coalesce(crc_mod("doc_id", 4) == 2, F.lit(False))
    found = language_id.identify_language(docs, held_out=held_out, keep=["doc_id"])
    return found.select("doc_id", held_out.alias("held_out"), "lang_pred", "score", "margin")


def op2_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.near_duplicates(_docs(spark, sf_dir).select("doc_id", "text"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op3_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    return html_text.extract_main_text(spark.read.parquet(f"{sf_dir}/pages.parquet"), keep=["page_id", "url"])


def op4_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(_docs(spark, sf_dir))


def op5_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_dedup.dedup_lines(_docs(spark, sf_dir).select("doc_id", "text"))


def op6_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.quality_signals(_docs(spark, sf_dir).select("doc_id", "text")).drop("text", "clean_text")


def op7_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = suffix_dedup.remove_repeats(_docs(spark, sf_dir).select("doc_id", "text"), with_bytes=False)
    return found.select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "n_passages", "n_passage_words")


def op8_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(_docs(spark, sf_dir).select("doc_id", "text"), tokenizer=TOKENIZER)


def op9_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language_model.lm_scores(_docs(spark, sf_dir).select("doc_id", "text"), tokenizer=TOKENIZER, held_out=crc_mod("doc_id", 10) == 0, shape=ModelShape(classes=32, inner=True, most=36))


def op10_media_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media.media_columns(_docs(spark, sf_dir).select("doc_id", "text"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f for f in (op1_language_id, op2_simhash_near_dedup, op3_html_extraction, op4_source_mixing, op5_line_dedup, op6_quality_rules, op7_suffix_dedup, op8_packing, op9_lm_scoring, op10_media_columns)
}

#: DuckDB SQL of those that SQL can express.
ORACLES: dict[str, str] = {"op4_source_mixing": mixing.mixing_sql(), "op6_quality_rules": quality.QUALITY_SQL}

"""One query for each corpus operator: production parameters, whole tables, results as the contracts fix them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from tallgram.llm import oracles
from tallgram.llm.common import table
from tallgram.llm.decontaminate import contamination
from tallgram.llm.html_text import extract_main_text
from tallgram.llm.language import identify
from tallgram.llm.language_model import scores
from tallgram.llm.media import media_digests
from tallgram.llm.near_dups import near_duplicates
from tallgram.llm.packing import pack_documents
from tallgram.llm.sharding import shard_documents
from tallgram.llm.token_store import token_digests
from tallgram.llm.toxicity import toxicity


def op1_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract_main_text(table(spark, sf_dir, "pages"))


def op2_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return identify(table(spark, sf_dir, "documents"))


def op3_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media_digests(table(spark, sf_dir, "documents"))


def op4_token_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_digests(table(spark, sf_dir, "documents"))


def op5_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(table(spark, sf_dir, "documents"))


def op6_lm_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scores(table(spark, sf_dir, "documents"))


def op7_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark")).drop("low", "high")


def op8_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shard_documents(table(spark, sf_dir, "documents"))


def op9_near_dups(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))


def op10_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_main_text, op2_language, op3_media, op4_token_store, op5_packing, op6_lm_scores, op7_decontamination, op8_shards, op9_near_dups, op10_toxicity)}


def oracle_sql() -> dict[str, str]:
    """The others have no SQL form: tests hold them against brute force, round trips or held-out accuracy."""
    return {"op7_decontamination": oracles.CONTAMINATION, "op9_near_dups": oracles.CLASSES}

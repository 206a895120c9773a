"""The registered queries of this package: each applies one operator to its whole table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from . import oracles
from .common import table
from .html import extract_main_text
from .line_dedup import line_report
from .merkle import edited_report
from .mixing import mix_report
from .ngram_join import link_report
from .packing import pack
from .quality import quality_report
from .secrets import scan_secrets
from .tokens import token_files
from .urls import judge_urls


def tokenizer_file() -> str:
    """The vocabulary file of the token queries; operators take its path as a parameter."""
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def op1_secret_ownership(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_secrets(table(spark, sf_dir, "documents"))


def op2_quality_divergence(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_report(table(spark, sf_dir, "documents"))


def op3_url_ngrams(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge_urls(table(spark, sf_dir, "pages"))


def op4_html_blocks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract_main_text(table(spark, sf_dir, "pages"))


def op5_token_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_files(table(spark, sf_dir, "documents"), tokenizer_file())


def op6_mix_curriculum(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix_report(table(spark, sf_dir, "documents"))


def op7_jaccard_partition(spark: SparkSession, sf_dir: str) -> DataFrame:
    return link_report(table(spark, sf_dir, "documents"))


def op8_line_chunks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_report(table(spark, sf_dir, "documents"), runs=True)


def op9_merkle_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return edited_report(table(spark, sf_dir, "documents"))


def op10_harmonic_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents"), tokenizer_file())


def queries() -> dict:
    found = {k: f for k, f in globals().items() if k.startswith("op") and callable(f)}
    return dict(sorted(found.items(), key=lambda x: int(x[0][2:].split("_")[0])))


def oracle_sql() -> dict[str, str]:
    return {"op1_secret_ownership": oracles.secrets_sql(), "op2_quality_divergence": oracles.quality_sql(), "op6_mix_curriculum": oracles.mix_sql(), "op9_merkle_fingerprints": oracles.merkle_sql()}

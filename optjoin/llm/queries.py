"""The registered queries of this subpackage: each applies its operator to the whole of its table."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .html_text import extract_pages
from .jpeg import media_columns
from .lm import score_documents
from .oracles import ORACLES
from .packing import pack
from .pieces import encode_documents
from .quality import quality
from .session import shared_dir
from .simhash import near_duplicates
from .substring_dedup import remove_repeated_windows
from .suffix_dedup import remove_repeats
from .warc import read_warc, write_warc


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    base = shared_dir(spark)
    folder = f"{base if ':' in base else 'file://' + base}/warc-{uuid.uuid4().hex}"
    manifest = write_warc(table(spark, sf_dir, "pages"), folder)
    return read_warc(manifest, folder).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def suffix_array(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = remove_repeats(table(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256).alias("kept_sha256"))


def simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))


def substring(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = remove_repeated_windows(table(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_words", "n_removed", F.sha2(F.encode("kept", "UTF-8"), 256).alias("kept_sha256"))


def lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = score_documents(table(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_words", F.round("log_score", 4).alias("log_score"), F.round("perplexity", 2).alias("perplexity"))


def media(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = media_columns(table(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature")


def quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = quality(table(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode_documents(table(spark, sf_dir, "documents"), pieces=False).drop("pieces")


def html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract_pages(table(spark, sf_dir, "pages"))


def packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_warc": warc,
    "op2_suffix_array_dedup": suffix_array,
    "op3_simhash": simhash,
    "op4_substring_dedup": substring,
    "op5_lm_scoring": lm_scoring,
    "op6_media_jpeg": media,
    "op7_quality_rules": quality_rules,
    "op8_sentencepiece": sentencepiece,
    "op9_html_extraction": html_extraction,
    "op10_packing": packing,
}

__all__ = ["ORACLES", "QUERIES"]

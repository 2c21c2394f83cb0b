"""A corpus pipeline of four stages over `documents`: quality rules, near-duplicates, repeated substrings, packing.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; all but the last return the columns of
documents, with n_chars made anew where a text changes. Every stage works on all that the one before
it kept.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from optjoin.llm.near_text import distinct_documents
from optjoin.llm.packing import pack
from optjoin.llm.quality import quality
from optjoin.llm.session import cut
from optjoin.llm.suffix_dedup import remove_repeats

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops the documents that the threshold table rejects."""
    return quality(docs, keep=COLUMNS).filter("kept").select(*COLUMNS)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the document with the smallest id of each group of near-duplicates, by fingerprints and by texts."""
    return distinct_documents(docs, keep=COLUMNS[2:]).select(*COLUMNS)


def repeated_substrings(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Removes the characters of passages that start in a smaller document, also those that a passage cuts."""
    out = remove_repeats(docs, keep=("lang", "source"), characters=True)
    text = F.make_valid_utf8(out["kept"].cast("string"))
    return out.select("doc_id", text.alias("text"), "lang", "source").filter(F.length("text") > 0).select("doc_id", "text", "lang", "source", F.length("text").cast("long").alias("n_chars"))


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Packs the documents that are left into sequences."""
    return pack(docs)


STAGES = [("quality rules", quality_rules), ("near-duplicates", near_duplicates), ("repeated substrings", repeated_substrings), ("packing", packing)]

#: SQL can't express the near-duplicate and tokenising stages; tests hold them against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; each stage's rows are cut from their lineage in the shared folder."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for _, stage in STAGES[:-1]:
        docs = cut(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)

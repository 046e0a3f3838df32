"""The corpus pipeline: quality rules, line templates, near duplicates, source mixing, BPE.

Each stage takes ``(spark, docs, sf_dir)`` and returns a DataFrame that is written as Parquet and read again as the next
stage's ``docs``.  All but the last return the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from treeloom.llm.bpe import encode_documents
from treeloom.llm.lines import drop_recurring_lines
from treeloom.llm.mixing import mix_sources
from treeloom.llm.near import drop_near_duplicates
from treeloom.llm.quality import keep_good
from treeloom.llm.queries import MIX_REPETITION, VOCABULARY
from treeloom.llm.store import saved

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the base test and every rule of the cascade keep."""
    return keep_good(docs.select(*COLUMNS))


def line_templates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without their recurring lines; one that had lines and has none left goes, as its text stays elsewhere."""
    kept = drop_recurring_lines(docs.select(*COLUMNS)).filter("n_dropped = 0 or text rlike '[^\\\\x20\\\\x09-\\\\x0D]'")
    return kept.withColumn("n_chars", F.length("text").cast("long")).select(*COLUMNS)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group that five-word shingles tie at a similarity of 0.8 or more."""
    return drop_near_duplicates(docs.select(*COLUMNS))


def source_mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document once, those of small sources up to twice, towards the tempered weights."""
    return mix_sources(docs.select(*COLUMNS), max_repetition=MIX_REPETITION).select(*COLUMNS)


def bpe_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token count, digest of the ids and digest of the decoded text of each document."""
    return encode_documents(docs, VOCABULARY)


STAGES = [
    ("quality_rules", quality_rules),
    ("line_templates", line_templates),
    ("near_duplicates", near_duplicates),
    ("source_mixing", source_mixing),
    ("bpe_tokens", bpe_tokens),
]
#: BPE is beyond SQL; the tests hold each stage against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = saved(stage(spark, docs, sf_dir), name)
    return docs

"""The corpus pipeline: five stages, each one operator over all that the stage before kept.

A stage takes (spark, docs, sf_dir) and returns a DataFrame; it is written as Parquet
and read again as the next stage's docs.  All but the last return the columns of documents, also
those it doesn't know, whatever their names; text and n_chars are the only ones that change.

All stages take nulls in any column, texts of any length, repeated rows and empty tables: an empty
table gives an empty one, and a row's fate hangs on its id and text alone, but for near duplicates, where
one row of a group stays.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from patchflow.llm.bpe import token_digests
from patchflow.llm.common import Scratch, read_table
from patchflow.llm.decontam import drop_contaminated
from patchflow.llm.jaccard import keep_one
from patchflow.llm.pii import mask_personal_data
from patchflow.llm.rules import filter_quality


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the rules reject go, so do null and empty texts; boilerplate lines leave the rest.  Repeated rows share one fate."""
    return filter_quality(docs)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate group stays: that of the least id (a null id only where there is no other), of ties that of the least text hash.

    SimHash blocks give the first links; as four bits see few pairs at a similarity of 0.8, an exact join
    on five-word shingles finds the rest.  Null and empty texts are one group.
    """
    return keep_one(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a window of a benchmark item go; null and empty texts hold none.  An empty benchmark lets all stay."""
    return drop_contaminated(docs, read_table(spark, sf_dir, "benchmark"))


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Spans of personal data become their kind in brackets, the first of overlapping ones; a null text stays null."""
    return mask_personal_data(docs)


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token counts and digests of ids and decoded bytes, one row a document; a null text has no tokens."""
    return token_digests(docs.select("doc_id", "text")).select("doc_id", "n_tokens", "ids_sha256", "decoded_sha256")


STAGES = [
    ("quality_rules", quality_rules),
    ("simhash_near_dedup", near_dedup),
    ("benchmark_decontamination", decontamination),
    ("personal_data", personal_data),
    ("byte_bpe", tokens),
]

#: No SQL expresses the fingerprint groups and the merges; tests hold the stages against plain versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents."""
    scratch = Scratch(spark, "pipeline")
    docs = read_table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = scratch.save(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)

"""Corpus pipeline: quality filter, near-duplicates, decontamination, pseudonyms, encoding."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stablegrammar.llm import bpe, decontamination, near_dedup, pii, quality
from stablegrammar.llm.common import settled, small_or_shuffled, table, unused


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows that the rule ensemble, fitted on labelled rows of this stage's input, doesn't reject.

    Null and empty texts are judged by an empty text's statistics; long texts whole; equal rows stay or go together; rows with a null id are
    judged like others; other columns, whatever their names, stay as they are; an empty table stays empty.
    """
    model = quality.train(docs, table(spark, sf_dir, "labels"))
    score = unused(docs.columns, "_score")
    return quality.with_score(docs, model, score).where(F.col(score) >= 0.3).select(*docs.columns)


def _without(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """Rows whose doc_id isn't among ids; rows with a null id stay."""
    return docs.join(small_or_shuffled(settled(ids.distinct())), "doc_id", "left_anti").select(*docs.columns)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each component of near-duplicates stays, the one with the smallest id: five-word shingles, similarity 0.8 or more.

    Null and empty texts and rows with a null id stay; rows that share an id are one document and stay or go together, so repeated rows
    stay repeated; texts of any length are compared whole; other columns stay as they are; an empty table stays empty.
    """
    return _without(docs, near_dedup.near_duplicates(docs, percent=80).where("not kept").select("doc_id"))


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark item, as it is or with other values, go.

    Null and empty texts and rows with a null id stay; rows that share an id are one document and go together if one of them holds an
    item; texts of any length are searched whole; other columns stay as they are; an empty table stays empty.
    """
    return _without(docs, decontamination.contamination(docs, table(spark, sf_dir, "benchmark")).select("doc_id"))


def replace_private(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Validated numbers, dates and addresses become pseudonyms, under the key in the session's settings.

    Every row stays; null texts stay null, with a null n_chars; equal texts stay equal; other columns stay as they are.
    """
    return pii.pseudonymise(docs, key=pii.key_of(spark)).withColumn("n_chars", F.length("text").cast("long"))


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every text, with digests of the ids and of the bytes that they decode to.

    Every row stays; null texts count as empty and have no tokens; long texts are encoded whole; equal texts get equal ids; columns of the
    input other than doc_id aren't returned; an empty table stays empty.
    """
    return bpe.bpe_round_trip(docs, keep=("ids",))


STAGES = [("quality", keep_quality), ("near_dedup", drop_near_duplicates), ("decontamination", drop_contaminated), ("pii", replace_private), ("encode", encode)]

ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents table."""
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES:
        docs = stage(spark, docs, sf_dir)
    return docs

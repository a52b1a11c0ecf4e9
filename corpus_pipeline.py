"""Corpus pipeline: toxicity, quality rules, near-duplicates, mixing, tokens.

Every stage takes (spark, docs, sf_dir) and works on all that the one before kept. The first four return
the columns of documents; the last returns each row's token count and digests of ids and decoded text.
Labels are read from sf_dir. Between stages, documents are written to the session's shared folder, so a
lost executor never costs more than one stage; what a stage has read is deleted once its result stands.

Nulls and odd input are those of the operators: a null text is empty, a null doc_id takes part in every
stage, equal rows are near-duplicates of each other, an empty table gives an empty result, further columns
pass up to the last stage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from meshprofile.llm.bpe import token_digests
from meshprofile.llm.common import clear_shared, materialise, shared_tables, table
from meshprofile.llm.mixing import mixed_documents
from meshprofile.llm.quality_rules import quality_survivors
from meshprofile.llm.simhash_dedup import simhash_survivors
from meshprofile.llm.toxicity import drop_toxic


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents scored below 0.5 stay."""
    return drop_toxic(docs, table(spark, sf_dir, "labels"))


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that neither the base rules nor a risk-controlled cutoff rejects stay."""
    return quality_survivors(docs, table(spark, sf_dir, "labels"))


def simhash(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate group stays, the one with the smallest id."""
    return simhash_survivors(docs)


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row for each copy the mix takes, in training order."""
    return mixed_documents(docs)


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return token_digests(docs)


STAGES = [("toxicity", toxicity), ("quality rules", quality_rules), ("simhash near-dedup", simhash), ("mixing", mixing), ("bpe", tokens)]

#: Recurrent scores and SimHash components are not for SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, before = table(spark, sf_dir, "documents"), shared_tables()
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), f"stage-{name.replace(' ', '-')}")
        clear_shared(spark, since=before, keep=1)
    return STAGES[-1][1](spark, docs, sf_dir)

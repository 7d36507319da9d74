"""Corpus pipeline over ``documents``: toxicity, near duplicates, benchmark leaks, mixture, shards."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from shardgraph.llm import decontaminate, jaccard_join, mixing, sharding, toxicity
from shardgraph.llm.common import Workspace, free_name, table

#: Share of all tokens that the mixture keeps.
BUDGET_SHARE = 0.9
FEW_IDS = 2_000_000


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the ordinal model finds not toxic; learned from the labelled ones among them.

    Null and empty texts, null ids and repeated rows are judged by their text alone. All columns stay.
    """
    name = free_name(docs, "_toxicity")
    model = toxicity.train(docs, table(spark, sf_dir, "labels"))
    return toxicity.severity(docs, model, out=name).where(~toxicity.rejects(out=name)).drop(name)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each component of similar shingle sets: the one with the smallest id.

    Texts without words and null ids link with nothing and stay; rows that repeat an id stay or go together.
    """
    found = jaccard_join.similar_components(docs)
    gone = Workspace(spark, "gone").write(found.where("doc_id <> component_id").select("doc_id"), "gone")
    return docs.join(F.broadcast(gone) if gone.count() <= FEW_IDS else gone, "doc_id", "left_anti").select(docs.columns)


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that cover less than half of every benchmark item; null and empty texts cover none and stay."""
    name = free_name(docs, "_overlap")
    return decontaminate.covered_by(docs, table(spark, sf_dir, "benchmark"), name=name).where(~decontaminate.contaminated(name=name)).drop(name)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in the first epoch of the mixture: of each leaf those before its cut in a seeded order of ids.

    Null lang and source are nodes of their own; rows that repeat an id go together; an empty table gives none.
    """
    return mixing.in_mix(docs, BUDGET_SHARE)


def deal_shards(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A row per document with its shard and slot; equal texts are neighbours, null texts count as empty, null ids come first."""
    return sharding.assign_shards(docs, n_shards=8)


STAGES = [
    ("toxicity", drop_toxic),
    ("near_duplicates", drop_near_duplicates),
    ("decontamination", drop_leaks),
    ("mixing", mix_sources),
    ("sharding", deal_shards),
]

#: The learned and iterative stages have no SQL form; the tests hold run() against its stages and these against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    ws = Workspace(spark, "pipeline")
    docs = table(spark, sf_dir, "documents")
    for i, (name, stage) in enumerate(STAGES):
        docs = ws.write(stage(spark, docs, sf_dir), name)
        if i:
            ws.drop(STAGES[i - 1][0])  # read for the last time
    return docs

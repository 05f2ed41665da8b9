"""Corpus pipeline: five of the training-data operators, each stage on what the one before it kept.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; all but the last
return the columns of ``documents``.  Decisions are by id: rows with a null id are
one document, and so are rows that repeat an id.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from stablecf.llm import decontaminate, exact_dedup, jaccard, packing, toxicity
from stablecf.llm.common import read, staged


def _only(docs: DataFrame, ids: DataFrame, how: str) -> DataFrame:
    """Rows of ``docs`` whose id is (``left_semi``) or is not (``left_anti``) among ``ids``; null matches null."""
    ids = ids.select(ids.doc_id.alias("_id")).distinct()
    return docs.join(ids, docs.doc_id.eqNullSafe(ids["_id"]), how)


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose toxicity score is under 0.5."""
    scored = toxicity.toxicity(spark, docs, read(spark, sf_dir, "labels"))
    return _only(docs, scored.where("predicted = 1"), "left_anti")


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts the document with the smallest id."""
    return _only(docs, exact_dedup.exact_dedup(spark, docs).where("kept"), "left_semi")


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group linked by shingle similarity the document with the smallest id."""
    return _only(docs, jaccard.similar(spark, docs).where("doc_id <=> component_id"), "left_semi")


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark window."""
    found = decontaminate.decontaminate(spark, docs, read(spark, sf_dir, "benchmark"))
    return _only(docs, found.where("n_hit > 0"), "left_anti")


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of training sequences of at most 2048 ids."""
    return packing.pack_documents(spark, docs)


STAGES = [("toxicity", drop_toxic), ("exact dedup", drop_copies), ("n-gram Jaccard join", drop_near_copies), ("benchmark decontamination", drop_contaminated), ("packing", pack)]

#: Nearest examples, components and tokens are beyond SQL; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = staged(spark, stage(spark, docs, sf_dir), "pipeline-" + name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)

"""Driver queries of this package: thin calls of the operators with production parameters."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from stablecf.llm import decontaminate, exact_dedup, jaccard, licences, merkle_audit, packing, ppm, repeats, sanitise, toxicity
from stablecf.llm.common import read


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.toxicity(spark, read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels")).drop("vote", "evidence")


def op2_merkle_audit(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = read(spark, sf_dir, "pages")
    return merkle_audit.audit(spark, pages, merkle_audit.damaged(pages), "page_id", ["url", "html"]).drop("left_copies", "right_copies")


def op3_ppm_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ppm.score_documents(spark, read(spark, sf_dir, "documents"))


def op4_licence_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licences.scan_documents(spark, read(spark, sf_dir, "documents")).drop("matches")


def op5_pack_sequences(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(spark, read(spark, sf_dir, "documents"))


def op6_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_dedup(spark, read(spark, sf_dir, "documents"))


def op7_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard.similar(spark, read(spark, sf_dir, "documents"))


def op8_sanitise(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sanitise.digest(sanitise.sanitise(spark, read(spark, sf_dir, "documents"), with_text=False))


def op9_remove_repeats(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeats.remove_repeats(spark, read(spark, sf_dir, "documents"), with_text=False).drop("kept")


def op10_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.digest(decontaminate.decontaminate(spark, read(spark, sf_dir, "documents"), read(spark, sf_dir, "benchmark")))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_toxicity, op2_merkle_audit, op3_ppm_score, op4_licence_scan, op5_pack_sequences, op6_exact_dedup, op7_jaccard_join, op8_sanitise, op9_remove_repeats, op10_decontaminate, pipeline)}


def oracle_sql() -> dict[str, str]:
    return {"op2_merkle_audit": merkle_audit.ORACLE, "op6_exact_dedup": exact_dedup.ORACLE, "op10_decontaminate": decontaminate.ORACLE}

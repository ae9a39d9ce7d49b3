"""The queries of this subpackage, with production parameters, and their SQL twins."""

from __future__ import annotations

from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

from bitsort.llm import decontamination, html_text, jaccard_join, license_scan, oracles, packing, quality, secrets, sharding, substring_dedup, suffix_dedup
from bitsort.llm.stages import table

#: The folder that holds this package; Python workers on executors find it through their PYTHONPATH.
BATCH_ROWS = 1000
HOME = str(Path(__file__).resolve().parents[2])


def ready(spark: SparkSession) -> None:
    """Let Python workers import this package wherever it lies at the same path, and get texts in small batches."""
    known = spark.sparkContext.environment.get("PYTHONPATH", "")
    if HOME not in known.split(":"):
        spark.sparkContext.environment["PYTHONPATH"] = f"{HOME}:{known}".rstrip(":")
    if int(spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch", "10000")) > BATCH_ROWS:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(BATCH_ROWS))


def tokenizer_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def op1_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    ready(spark)
    return packing.packed_documents(table(spark, sf_dir, "documents"), tokenizer_path())


def op2_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    ready(spark)
    return substring_dedup.digest(substring_dedup.deduplicated(table(spark, sf_dir, "documents")))


def op3_suffix_array_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    ready(spark)
    return suffix_dedup.deduplication_report(table(spark, sf_dir, "documents"))


def op4_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    ready(spark)
    return html_text.main_text(table(spark, sf_dir, "pages"))


def op5_license_scans(spark: SparkSession, sf_dir: str) -> DataFrame:
    ready(spark)
    return license_scan.license_report(table(spark, sf_dir, "documents"))


def op6_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.quality_report(table(spark, sf_dir, "documents"))


def op7_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    ready(spark)
    return jaccard_join.near_duplicates(table(spark, sf_dir, "documents"), n=4, threshold=85).drop("text_hash")


def op8_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.sharded(table(spark, sf_dir, "documents"))


def op9_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    ready(spark)
    return decontamination.leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op10_secret_scans(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.secret_report(table(spark, sf_dir, "documents"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict:
    ops = (
        op1_best_fit_packing,
        op2_substring_dedup,
        op3_suffix_array_dedup,
        op4_html_extraction,
        op5_license_scans,
        op6_quality_rules,
        op7_ngram_jaccard_join,
        op8_sharding,
        op9_benchmark_decontamination,
        op10_secret_scans,
        pipeline,
    )
    return {f.__name__: f for f in ops}


def oracle_sql() -> dict[str, str]:
    return {"op2_substring_dedup": oracles.SUBSTRING_DEDUP, "op7_ngram_jaccard_join": oracles.NGRAM_JACCARD_JOIN}

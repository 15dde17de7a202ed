"""Queries of the text operators: name -> (spark, sf_dir) -> DataFrame, with SQL where it can say the same."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


def _documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def op1_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    from gleaner.llm.licenses import license_scan

    return license_scan(_documents(spark, sf_dir))


def op2_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from gleaner.llm.suffix_dedup import suffix_dedup

    return suffix_dedup(_documents(spark, sf_dir))


def op3_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from gleaner.llm.toxicity import toxicity

    return toxicity(_documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"))


def op4_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from gleaner.llm.packing import pack

    return pack(_documents(spark, sf_dir))


def op5_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from gleaner.llm.exact_dedup import exact_dedup

    return exact_dedup(_documents(spark, sf_dir))


def op6_merge_dropout(spark: SparkSession, sf_dir: str) -> DataFrame:
    from gleaner.llm.merge_dropout import round_trip

    return round_trip(_documents(spark, sf_dir))


def op7_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    from gleaner.llm.html_text import extract

    return extract(spark.read.parquet(f"{sf_dir}/pages.parquet"))


def op8_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    from gleaner.llm.minhash import fingerprints

    return fingerprints(_documents(spark, sf_dir))


def op9_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    from gleaner.llm.langid import identify

    return identify(_documents(spark, sf_dir))


def op10_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    from gleaner.llm.simhash import simhash_components

    return simhash_components(_documents(spark, sf_dir))


def queries() -> dict:
    return {f.__name__: f for f in (op1_licenses, op2_suffix_dedup, op3_toxicity, op4_packing, op5_exact_dedup, op6_merge_dropout, op7_html_text, op8_minhash, op9_language, op10_simhash)}


def oracle_sql() -> dict[str, str]:
    return {
        "op5_exact_dedup": """
            WITH t AS (SELECT doc_id, regexp_replace(coalesce(text, ''), '[\\x20\\x09-\\x0D]+', ' ', 'g') AS x FROM documents)
            SELECT doc_id, min(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size, doc_id = min(doc_id) OVER w AS kept,
                   sha256(x) AS text_sha256
            FROM t WINDOW w AS (PARTITION BY x)
        """,
    }

"""Queries of the operators, with production parameters, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from canopy.llm import cotraining, html_text, kneser_ney, language_id, packing, secrets, shards, simhash, tiling, url_rules
from canopy.storage import fresh_path


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.near_duplicates(table(spark, sf_dir, "documents"))
    return found.select("doc_id", simhash.hex_fingerprint().alias("fingerprint"), "component_id", "n_linked")


def op2(spark: SparkSession, sf_dir: str) -> DataFrame:
    judged = kneser_ney.judge(table(spark, sf_dir, "documents"))
    return judged.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "log_perplexity")


def op3(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return cotraining.classify(docs, cotraining.train(docs, table(spark, sf_dir, "labels")))


def op4(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.digest(secrets.scan_versions(table(spark, sf_dir, "documents")))


def op5(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tiling.contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op6(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_text.extract(table(spark, sf_dir, "pages"))


def op7(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_rules.judge(table(spark, sf_dir, "pages"), url_rules.rule_table(spark))


def op8(spark: SparkSession, sf_dir: str) -> DataFrame:
    store = shards.ShardStore(spark, fresh_path(spark, "store"))
    store.append(table(spark, sf_dir, "documents"))
    version = store.compact()
    store.expire()
    return store.read(version).select("doc_id", "lang", "source", "n_chars", F.md5(F.col("text").cast("binary")).alias("text_md5"))


def op9(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"))


def op10(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    codes = language_id.train(docs, ~language_id.held_out())
    return language_id.identify(docs, codes).withColumn("held_out", language_id.held_out()).select("doc_id", "held_out", "lang_pred", "score", "ambiguous")


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_simhash_near_duplicates": op1,
        "op2_kneser_ney_quality": op2,
        "op3_cotraining_quality": op3,
        "op4_secret_ledger": op4,
        "op5_string_tiling": op5,
        "op6_html_main_text": op6,
        "op7_url_rules": op7,
        "op8_size_tiered_shards": op8,
        "op9_lexical_packing": op9,
        "op10_language_codes": op10,
        "pipeline": pipeline,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op7_url_rules": url_rules.oracle(),
        "op8_size_tiered_shards": "SELECT doc_id, lang, source, n_chars, md5(text) AS text_md5 FROM documents",
    }

"""The queries of this subpackage: each operator over its whole table, with production parameters."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from hitcodec.llm.common import table
from hitcodec.llm.decontaminate import contaminated
from hitcodec.llm.license_scan import license_digest, license_scan
from hitcodec.llm.line_dedup import line_digest
from hitcodec.llm.media import media_digest, store_texts
from hitcodec.llm.mixing import mix
from hitcodec.llm.ngram_join import ngram_join
from hitcodec.llm.secret_scan import secret_scan
from hitcodec.llm.token_output import token_digest
from hitcodec.llm.toxicity import fit, score
from hitcodec.llm.url_filter import url_filter
from hitcodec.session import ship_package


def op1_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix(table(spark, sf_dir, "documents"))


def vocabulary_file(name: str = "byte_bpe_50k.json") -> str:
    """The path of a public tokenizer's file."""
    import public_tokenizers

    return public_tokenizers.path(name)


def op2_token_output(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship_package(spark)
    return token_digest(table(spark, sf_dir, "documents"), vocabulary_file())


def op3_media_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship_package(spark)
    return media_digest(store_texts(table(spark, sf_dir, "documents")))


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship_package(spark)
    docs = table(spark, sf_dir, "documents")
    return score(docs, fit(docs, table(spark, sf_dir, "labels")))


def op5_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship_package(spark)
    return secret_scan(table(spark, sf_dir, "documents")).select("doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans")


def op6_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contaminated(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark")).drop("tk")


def op7_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship_package(spark)
    return ngram_join(table(spark, sf_dir, "documents"))


def op8_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship_package(spark)
    return license_digest(license_scan(table(spark, sf_dir, "documents")))


def op9_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship_package(spark)
    return line_digest(table(spark, sf_dir, "documents"))


# The rules of the query, as (host, path, verdict).
URL_RULES = [("net", "/", "block"), ("example.net", "/en/", "allow"), ("example.com", "/de/", "block"), ("org", "/fr/", "allow")]


def op10_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    rules = spark.createDataFrame(URL_RULES, "host string, path string, verdict string")
    return url_filter(table(spark, sf_dir, "pages"), rules)


QUERIES = {f.__name__: f for f in (op1_source_mixing, op2_token_output, op3_media_columns, op4_toxicity, op5_secret_scan, op6_decontaminate, op7_ngram_join, op8_license_scan, op9_line_dedup, op10_url_filter)}

"""The given tables with explicit schemas, and readers and writers of other formats."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

SCHEMAS = {
    "region": "r_regionkey INT, r_name STRING",
    "nation": "n_nationkey INT, n_name STRING, n_regionkey INT",
    "customer": "c_custkey BIGINT, c_name STRING, c_nationkey INT, c_acctbal DOUBLE, c_mktsegment STRING",
    "supplier": "s_suppkey BIGINT, s_name STRING, s_nationkey INT, s_acctbal DOUBLE",
    "part": "p_partkey BIGINT, p_name STRING, p_brand STRING, p_type STRING, p_size INT, p_retailprice DOUBLE",
    "orders": "o_orderkey BIGINT, o_custkey BIGINT, o_orderstatus STRING, o_totalprice DOUBLE, o_orderdate TIMESTAMP_NTZ, o_orderpriority STRING",
    "lineitem": "l_orderkey BIGINT, l_partkey BIGINT, l_suppkey BIGINT, l_linenumber INT, l_quantity DOUBLE, l_extendedprice DOUBLE, l_discount DOUBLE, l_tax DOUBLE, l_returnflag STRING, l_linestatus STRING, l_shipdate TIMESTAMP_NTZ",
    "events": "event_id BIGINT, ts TIMESTAMP_NTZ, user_id BIGINT, event_type STRING, value DOUBLE, props STRING",
    "documents": "doc_id BIGINT, text STRING, lang STRING, source STRING, n_chars BIGINT",
    "embeddings": "vec_id BIGINT, embedding ARRAY<FLOAT>, label INT",
    "pages": "page_id BIGINT, url STRING, html STRING",
    "benchmark": "item_id BIGINT, text STRING",
    "labels": "doc_id BIGINT, quality INT, toxic INT",
    "conversations": "conv_id BIGINT, turn BIGINT, role STRING, text STRING",
}


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table, its schema declared rather than inferred."""
    return spark.read.schema(SCHEMAS[name]).parquet(f"{sf_dir}/{name}.parquet")


def read_as(spark: SparkSession, path: str, form: str, schema: str) -> DataFrame:
    """CSV, JSON, ORC, text or Parquet files with a declared schema."""
    reader = spark.read.schema(schema)
    if form == "csv":
        reader = reader.option("header", True)
    return reader.format(form).load(path)


def write_as(df: DataFrame, path: str, form: str, partition_by: list[str] | None = None) -> None:
    """The rows as files of a format."""
    writer = df.write.mode("overwrite").format(form)
    if form == "csv":
        writer = writer.option("header", True)
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    writer.save(path)


def stream_events(spark: SparkSession, sf_dir: str, files_per_trigger: int = 1) -> DataFrame:
    """The events table as a stream of files."""
    return spark.readStream.schema(SCHEMAS["events"]).option("pathGlobFilter", "events.parquet").option("maxFilesPerTrigger", files_per_trigger).parquet(sf_dir)


def rate_hits(spark: SparkSession, rows_per_second: int = 1000, channels: int = 48) -> DataFrame:
    """An endless stream of synthetic pulses for soak tests."""
    return spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load().selectExpr(
        "value div 24 AS event", f"CAST(value % {channels} AS INT) AS channel", "value * 500 AS rise", "value * 500 + 100 + value % 97 AS fall"
    )

"""Given tables with their schemas declared, as batches and as streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SCHEMAS = {
    "events": "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string",
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "orders": "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "customer": "c_custkey long, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "lineitem": "l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "part": "p_partkey long, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "supplier": "s_suppkey long, s_name string, s_nationkey int, s_acctbal double",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "region": "r_regionkey int, r_name string",
    "pages": "page_id long, url string, html string",
    "conversations": "conv_id long, turn long, role string, text string",
    "labels": "doc_id long, quality int, toxic int",
    "benchmark": "item_id long, text string",
}


def _as_instants(df: DataFrame) -> DataFrame:
    """Times without a zone as UTC instants, which watermarks need."""
    return df.withColumns({f.name: F.col(f.name).cast("timestamp") for f in df.schema.fields if f.dataType.typeName() == "timestamp_ntz"})


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return _as_instants(spark.read.parquet(f"{sf_dir}/{name}.parquet"))


def stream(spark: SparkSession, path: str, name: str, files_per_trigger: int = 1) -> DataFrame:
    """A folder of the table's Parquet parts as a stream."""
    return _as_instants(spark.readStream.schema(SCHEMAS[name]).option("maxFilesPerTrigger", files_per_trigger).parquet(path))


def rate(spark: SparkSession, rows_per_second: int = 1000) -> DataFrame:
    """A load generator: seq, ts, msg_id of Spark's rate source."""
    return spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load().select(F.col("value").alias("seq"), F.col("timestamp").alias("ts"), F.col("value").alias("msg_id"))


def asked_json(spark: SparkSession, path: str) -> DataFrame:
    """Queries from JSON lines: qid, terms, cell, k."""
    return spark.read.schema("qid long, terms array<string>, cell int, k int").json(path)


def asked_csv(spark: SparkSession, path: str) -> DataFrame:
    """Place-frequency queries from CSV with a header: qid, term, cell."""
    return spark.read.schema("qid long, term string, cell int").option("header", True).csv(path)

"""Readers of the synthetic tables, by column."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


#: Rows and bytes of a batch that goes to Python; by default Spark sends 10,000 rows, whatever the length of their texts.
BATCH = {"spark.sql.execution.arrow.maxRecordsPerBatch": "1000", "spark.sql.execution.arrow.maxBytesPerBatch": "4194304"}


def bounded_batches(df: DataFrame) -> DataFrame:
    """df, in a session whose Arrow batches are small, so that a worker's memory does not follow the texts.

    Settings that the user has chosen, other than Spark's defaults, stay.
    """
    spark = df.sparkSession
    for key, value in BATCH.items():
        if spark.conf.get(key, None) in (None, "10000", "67108864b", "67108864", "64MB", "9223372036854775807", "-1"):
            spark.conf.set(key, value)
    return df


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def documents(spark: SparkSession, sf_dir: str, *columns: str) -> DataFrame:
    return table(spark, sf_dir, "documents", *(columns or COLUMNS))

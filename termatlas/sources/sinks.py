"""Sinks of summaries, models and maps."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def write_by_bucket(df: DataFrame, path: str, buckets: int = 64, key: str = "term") -> None:
    """Parquet folders by a hash bucket of the term, so that a term's query reads one folder."""
    df.withColumn("bucket", F.pmod(F.xxhash64(key), F.lit(buckets))).repartition(buckets, "bucket").write.mode("overwrite").partitionBy("bucket").parquet(path)


def write_table(df: DataFrame, name: str, buckets: int = 64, key: str = "term") -> None:
    """A bucketed table; joins of two such tables by key need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(name)


def idempotent(path: str):
    """A foreachBatch function: a batch's folder is overwritten when the batch is run again."""

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")

    return put


def latest(spark, path: str, key: str = "term") -> DataFrame:
    """The last version of each key among the batches that idempotent() wrote."""
    every = spark.read.parquet(path)
    names = [c for c in every.columns if c not in (key, "batch")]
    return every.groupBy(key).agg(F.max_by(F.struct(*names), "batch").alias("v")).select(key, "v.*")


def map_features(answers: DataFrame, size_e6: int = 1_000_000) -> DataFrame:
    """One GeoJSON-like feature a row (column feature), from term, cell, est."""
    from termatlas.functions import geo

    point = F.struct(F.lit("Point").alias("type"), F.array(geo.centre_lon("cell", size_e6), geo.centre_lat("cell", size_e6)).alias("coordinates"))
    shape = F.struct(F.lit("Feature").alias("type"), point.alias("geometry"), F.struct("term", "cell", "est").alias("properties"))
    return answers.select(F.to_json(shape).alias("feature"))

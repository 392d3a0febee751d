"""Encoding and training as two jobs: the first writes what the second reads."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def produce(encoded: DataFrame, folder: str, shards: int = 8) -> None:
    """The encoder's job: its outputs as Parquet files, about ``shards`` of them."""
    encoded.repartition(shards).write.mode("append").parquet(folder)


def consume(spark: SparkSession, folder: str, schema) -> DataFrame:
    """The trainer's job over all that is there."""
    return spark.read.schema(schema).parquet(folder)


def consume_stream(spark: SparkSession, folder: str, schema, files: int = 4) -> DataFrame:
    """The same while the producer still writes: a stream of its files."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(folder)


def throughput(encode: Column, train: Column) -> list[Column]:
    """Time of a unit where both share their devices, and where the slower of two jobs decides."""
    return [(encode + train).alias("co_located"), F.greatest(encode, train).alias("decoupled")]

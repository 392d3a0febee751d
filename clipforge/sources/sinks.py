"""Sinks: bucketed Parquet, line-delimited JSON shards, co-located tables, and files partitioned for pruning."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


def write_bucketed(df: DataFrame, path: str, by: list[str], max_records: int = 1_000_000) -> None:
    """Parquet partitioned by bucket, so later stages read only theirs; REBALANCE splits a bucket that holds most rows."""
    df.hint("rebalance", *by).write.option("maxRecordsPerFile", max_records).partitionBy(*by).mode("overwrite").parquet(path)


def write_json_shards(df: DataFrame, path: str, shards: int) -> None:
    df.repartition(shards).write.mode("overwrite").json(path)


def write_colocated(df: DataFrame, table: str, keys: list[str], buckets: int) -> None:
    """A bucketed table: joins and aggregates on ``keys`` need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, *keys).sortBy(*keys).saveAsTable(table)


def read_partition(spark: SparkSession, path: str, schema: str, where: str) -> DataFrame:
    return spark.read.schema(schema).parquet(path).filter(where)


def foreach_batch_once(path: str):
    """A streaming sink that is idempotent by batch: a batch that is run again overwrites its own folder."""
    def write(df: DataFrame, batch_id: int) -> None:
        df.write.mode("overwrite").parquet(f"{path.rstrip('/')}/batch={batch_id}")

    return write

"""Readers and sinks.  Readers take the columns wanted, so scans stay pruned."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def read_table(spark: SparkSession, sf_dir: str, name: str, *cols: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def read_any(spark: SparkSession, path: str, fmt: str, schema) -> DataFrame:
    """CSV, JSON, ORC or Parquet with the schema given, never inferred."""
    reader = spark.read.schema(schema)
    return reader.option("header", True).csv(path) if fmt == "csv" else reader.format(fmt).load(path)


def write_any(df: DataFrame, path: str, fmt: str, partition_by: tuple[str, ...] = ()) -> None:
    writer = df.write.mode("overwrite").partitionBy(*partition_by)
    writer.option("header", True).csv(path) if fmt == "csv" else writer.format(fmt).save(path)


def write_bucketed(df: DataFrame, table: str, key: str, buckets: int) -> None:
    """Later joins and aggregates on ``key`` need no exchange."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(table)


def upsert(target: str, key: tuple[str, ...]):
    """A foreachBatch sink that keeps the newest row of each key in a Parquet folder with two
    alternating versions, so a failed batch leaves the last one readable."""

    def write(batch: DataFrame, epoch: int) -> None:
        spark = batch.sparkSession
        try:
            old = spark.read.parquet(f"{target}/v{(epoch + 1) % 2}")
            rows = old.join(batch, list(key), "left_anti").unionByName(batch)
        except Exception as e:
            if "PATH_NOT_FOUND" not in str(e):
                raise
            rows = batch
        rows.write.mode("overwrite").parquet(f"{target}/v{epoch % 2}")

    return write

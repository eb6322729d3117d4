"""Parquet tables, and stored sketch states partitioned by key."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def save_states(packed: DataFrame, path: str) -> None:
    packed.write.mode("append").partitionBy("key_id").parquet(path)


def load_states(spark: SparkSession, path: str, key_id: str) -> DataFrame:
    return spark.read.parquet(path).where(f"key_id = '{key_id}'")

"""Sources and sinks: pruned scans, formats, views, partitioned and bucketed tables, models and ledgers."""

from __future__ import annotations

import json
from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def table(spark: SparkSession, sf_dir: str, name: str, columns: Sequence[str] | None = None) -> DataFrame:
    """Parquet scan; with ``columns`` only those are read."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def load(spark: SparkSession, path: str, kind: str = "parquet", schema: str | None = None, **options: str) -> DataFrame:
    """CSV, JSON, ORC, text, JDBC (a passthrough) and whatever else the session can read."""
    reader = spark.read.format(kind).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def register_views(spark: SparkSession, sf_dir: str, names: Sequence[str] = TABLES) -> None:
    for name in names:
        table(spark, sf_dir, name).createOrReplaceTempView(name)


def save_frame(df: DataFrame, path: str, partition: Sequence[str] = (), mode: str = "errorifexists") -> None:
    df.write.mode(mode).partitionBy(*partition).parquet(path)


def save_bucketed(df: DataFrame, name: str, key: str, buckets: int, mode: str = "errorifexists") -> None:
    """Managed table bucketed and sorted by its key: joins on the key then need no shuffle."""
    df.write.mode(mode).bucketBy(buckets, key).sortBy(key).saveAsTable(name)


def append_model(model: DataFrame, path: str) -> None:
    model.write.mode("append").parquet(path)


def model_json(model: dict) -> str:
    return json.dumps(model, sort_keys=True)

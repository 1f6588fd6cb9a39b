"""Scans and sinks."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
#: The order that is total on ``lineitem`` at every scale.
LINEITEM_ORDER = ("l_shipdate", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice")
EVENTS_ORDER = ("ts", "event_id")


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def load_as(spark: SparkSession, fmt: str, path: str, schema=None, **options) -> DataFrame:
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema is not None else reader).load(path)


def save(df: DataFrame, path: str, fmt: str = "parquet", partition_by: Sequence[str] = (), sort_by: Sequence[str] = (), mode: str = "error") -> None:
    """Write rows, partitioned by series and sorted inside files, so that later filters prune and read in order."""
    rows = df.repartition(*partition_by).sortWithinPartitions(*partition_by, *sort_by) if partition_by else df.sortWithinPartitions(*sort_by) if sort_by else df
    writer = rows.write.format(fmt).mode(mode)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def save_bucketed(df: DataFrame, table: str, buckets: int, by: Sequence[str], sort_by: Sequence[str] = ()) -> None:
    """A managed table whose series are co-located, so that a filter by series needs no exchange."""
    writer = df.write.bucketBy(buckets, *by)
    (writer.sortBy(*sort_by) if sort_by else writer).mode("overwrite").saveAsTable(table)

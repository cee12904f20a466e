"""Readers and writers with explicit schemas."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T


def read(spark: SparkSession, path: str, schema: T.StructType, kind: str = "parquet", **options) -> DataFrame:
    """parquet, orc, json, csv or text; types are never inferred."""
    return spark.read.format(kind).schema(schema).options(**options).load(path)


def write_edges(df: DataFrame, path: str, kind: str = "parquet", by_level: bool = True, mode: str = "overwrite", **options) -> None:
    """Edges by level, sorted by scene within files, so that a scene's filter skips row groups."""
    w = df.sortWithinPartitions("scene_id").write.format(kind).mode(mode).options(**options)
    (w.partitionBy("level") if by_level and "level" in df.columns else w).save(path)


def write_bucketed(df: DataFrame, name: str, buckets: int, key: str = "scene_id") -> None:
    """A table bucketed and sorted by scene: later joins by scene need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(name)

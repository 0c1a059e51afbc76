"""Segments at rest: Parquet by dataset, sorted so that row-group statistics prune by series and time."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.codec import decode, encode


def write_segments(segments: DataFrame, path: str, dataset: str = "default", mode: str = "append") -> None:
    """Appends segments; bodies are already packed, so Parquet's own compression is left off for them."""
    out = segments.withColumn("dataset_id", F.lit(dataset)).sortWithinPartitions("series_id", "t_start")
    out.write.mode(mode).partitionBy("dataset_id").option("compression", "uncompressed").parquet(path)


def read_segments(spark: SparkSession, path: str, dataset: str | None = None) -> DataFrame:
    out = spark.read.parquet(path)
    return out if dataset is None else out.where(F.col("dataset_id") == dataset)


def compact(segments: DataFrame, options, segment_length: int) -> DataFrame:
    """Small segments decoded and encoded anew in longer ones."""
    return encode(decode(segments), options, segment_length=segment_length)

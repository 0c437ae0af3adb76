"""Meter dumps as CSV or JSON lines, with a declared schema."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

DUMP = "stream_id bigint, pos int, sym bigint"


def read_csv(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(DUMP).option("header", True).option("mode", "FAILFAST").csv(path)


def read_json(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(DUMP).option("mode", "FAILFAST").json(path)


def read_blobs(spark: SparkSession, path: str) -> DataFrame:
    """Raw files as byte strings: (path, length, content)."""
    return spark.read.format("binaryFile").load(path).select("path", "length", "content")

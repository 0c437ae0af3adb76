"""The packed sink: Parquet by window, a manifest beside it, and reads of chosen streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def write_packed(packed: DataFrame, path: str) -> None:
    """Rows by window_no, not compressed again: files are about as large as the payloads. The manifest has no payload."""
    packed.write.mode("overwrite").partitionBy("window_no").option("compression", "none").parquet(f"{path}/blocks")
    spark = packed.sparkSession
    spark.read.parquet(f"{path}/blocks").select("window_no", "batch_id", "cluster_id", "part", "stream_ids", "payload_bits", "side_bits", "orig_bits").write.mode("overwrite").parquet(f"{path}/manifest")


def read_packed(spark: SparkSession, path: str, window_no: int | None = None) -> DataFrame:
    out = spark.read.parquet(f"{path}/blocks")
    return out if window_no is None else out.where(F.col("window_no") == window_no)


def find_streams(spark: SparkSession, path: str, stream_ids: list[int]) -> DataFrame:
    """Packed rows that hold one of the streams: the manifest tells windows and groups, the join prunes the windows."""
    wanted = F.array(*(F.lit(int(i)) for i in stream_ids)).cast("array<bigint>")
    hits = spark.read.parquet(f"{path}/manifest").where(F.arrays_overlap("stream_ids", wanted)).select("window_no", "batch_id", "cluster_id", "part")
    return read_packed(spark, path).join(hits, ["window_no", "batch_id", "cluster_id", "part"], "left_semi")

"""Dense ranks of a whole table without a single-task window, and tables kept between rounds."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir. Where it is unset, one of our own if all run on this
    machine; on a cluster that would lose files, so there it is an error."""
    top = spark.conf.get("spark.checkpoint.dir", None)
    if top:
        return top
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir is unset: name a folder that driver and executors share")
    return f"file://{tempfile.gettempdir()}/checkpoints"


def kept(df: DataFrame, name: str) -> DataFrame:
    """Written once to the shared folder and read back."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def dense_ranks(df: DataFrame, *keys: str) -> DataFrame:
    """df with its rows' dense rank (from 0) by keys, in place of an earlier rank. Range partitions hold whole key values; a rank in
    each partition plus the number of distinct keys in those before is the rank of all. The ranged rows are written first,
    since their partition numbers are used twice."""
    ranged = kept(df.repartitionByRange(*keys).withColumn("__mp_part", F.spark_partition_id()), "ranged")
    inside = ranged.withColumn("__mp_rank", F.dense_rank().over(Window.partitionBy("__mp_part").orderBy(*keys)))
    sizes = inside.groupBy("__mp_part").agg(F.max("__mp_rank").alias("n"))
    before = Window.orderBy("__mp_part").rowsBetween(Window.unboundedPreceding, -1)  # one row a partition
    offsets = sizes.select("__mp_part", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("__mp_offset"))
    out = inside.join(F.broadcast(offsets), "__mp_part")
    return out.withColumn("rank", (F.col("__mp_offset") + F.col("__mp_rank") - 1).cast("bigint")).drop("__mp_part", "__mp_rank", "__mp_offset")

"""The streaming front end: readings in, packed blocks out."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from meterpack.kernels.codec import Config
from meterpack.operators.firststage import first_stage
from meterpack.plans.recompress import batch_by_rank, recompress
from meterpack.schemas import STREAMS

EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def read_events(spark: SparkSession, path: str, files_per_batch: int = 1) -> DataFrame:
    """The events files of a folder as a stream; ts becomes a timestamp, since watermarks refuse the kind without a zone."""
    raw = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_batch).option("pathGlobFilter", "events*.parquet").parquet(path)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def readings(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """(event_id, stream_id, ts, sym) behind a watermark, each event once."""
    rows = events.select("event_id", F.col("user_id").alias("stream_id"), "ts", F.round(F.col("value") * 100).cast("bigint").alias("sym"))
    return rows.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


#: The meter of end-of-input marks: they move the watermark and are no readings.
MARK = -(1 << 63)


def marks(spark: SparkSession, path: str) -> DataFrame:
    """A stream of end-of-input marks under path, in the columns of read_events; close_input() writes one."""
    if not spark._jvm.org.apache.hadoop.fs.Path(path).getFileSystem(spark._jsc.hadoopConfiguration()).exists(spark._jvm.org.apache.hadoop.fs.Path(path)):
        spark.createDataFrame([], EVENTS).write.parquet(path)
    return spark.readStream.schema(EVENTS).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def close_input(spark: SparkSession, path: str, at: str = "2262-01-01") -> None:
    """Says that no reading before `at` will come any more: the next run of a query that reads marks(path) flushes all blocks."""
    mark = spark.range(1).select(F.lit(MARK).alias("event_id"), F.lit(at).cast("timestamp_ntz").alias("ts"), F.lit(MARK).alias("user_id"), F.lit("mark").alias("event_type"), F.lit(0.0).alias("value"), F.lit("{}").alias("props"))
    mark.coalesce(1).write.mode("append").parquet(path)


def assemble(rows: DataFrame, block_len: int, wait_ms: int = 3_600_000) -> DataFrame:
    """Blocks (stream_id, block_no, n_readings, readings) of a stream of readings in order of time and event_id, as the batch
    form cuts them: a full one once the watermark has passed its last reading, a short one once the watermark is wait_ms
    behind the newest reading of its meter. A meter's state is its readings that the watermark has not passed, and less
    than one block more.

    A reading that comes late, but before the watermark, takes its own place. One behind the watermark never gets here.
    After a short block a meter goes on with the next block number, so that later places start at a block's border."""

    def step(key, frames, state: GroupState):
        import pandas as pd

        number, held = 0, []
        if state.exists:
            number, *columns = state.get
            held = list(zip(*map(list, columns), strict=True))
        for frame in frames:
            held += zip((t.value // 1_000 for t in frame["ts"]), frame["event_id"].tolist(), frame["sym"].tolist(), strict=True)
        if key[0] == MARK:
            return
        held.sort()
        passed = state.getCurrentWatermarkMs() * 1_000
        out = []
        while len(held) >= block_len and held[block_len - 1][0] < passed:
            out.append(held[:block_len])
            held = held[block_len:]
        if held and held[-1][0] + wait_ms * 1_000 < passed:
            out.append(held)
            held = []
        state.update((number + len(out), *([h[i] for h in held] for i in range(3))))
        if held:
            due = held[block_len - 1][0] if len(held) >= block_len else held[-1][0] + wait_ms * 1_000
            state.setTimeoutTimestamp(max(due, passed) // 1_000 + 1)
        if out:
            yield pd.DataFrame({"stream_id": [key[0]] * len(out), "block_no": range(number, number + len(out)), "n_readings": list(map(len, out)), "readings": [[h[2] for h in block] for block in out]})

    return rows.groupBy("stream_id").applyInPandasWithState(
        step, "stream_id bigint, block_no int, n_readings int, readings array<bigint>", "number int, ts array<bigint>, ids array<bigint>, syms array<bigint>", "append", GroupStateTimeout.EventTimeTimeout
    )


def pack_sink(path: str, coder: str = "gaussian_ac", cfg: Config = Config(grouping="random", k=1)) -> Callable[[DataFrame, int], None]:
    """For foreachBatch: packs each micro-batch's blocks into path/epoch=N. A replayed epoch overwrites itself.

    The compressed streams are written first, beside path: packing reads them more than once, and the state's operators
    must not run again each time."""

    def write(blocks: DataFrame, epoch: int) -> None:
        held = f"{path}-streams/epoch={epoch}"
        first_stage(blocks, coder).write.mode("overwrite").parquet(held)
        streams = blocks.sparkSession.read.schema(STREAMS).parquet(held)
        recompress(batch_by_rank(streams), cfg).write.mode("overwrite").parquet(f"{path}/epoch={epoch}")

    return write


def slot_sums(rows: DataFrame, slot: str = "30 minutes") -> DataFrame:
    """Tumbling sums by meter and slot."""
    return rows.groupBy(F.window("ts", slot), "stream_id").agg(F.sum("sym").alias("sym")).select("stream_id", F.col("window.start").alias("slot_start"), "sym")


def sliding_load(rows: DataFrame, width: str = "1 hour", every: str = "30 minutes") -> DataFrame:
    return rows.groupBy(F.window("ts", width, every)).agg(F.sum("sym").alias("load"), F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("start"), "load", "n")


def sessions(rows: DataFrame, gap: str = "2 hours") -> DataFrame:
    return rows.groupBy("stream_id", F.session_window("ts", gap)).agg(F.count(F.lit(1)).alias("n")).select("stream_id", F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), "n")


def assign_frozen(vectors: DataFrame, centers: DataFrame) -> DataFrame:
    """Streaming vectors (stream_id, vec) to centres that no longer move: the k centres are one array in a one-row table,
    so that a row needs no aggregate."""
    packed = centers.agg(F.array_sort(F.collect_list(F.struct("cluster_id", "centroid"))).alias("centers"))
    d = lambda c: F.aggregate(F.zip_with("vec", c["centroid"], lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, x: s + x)
    nearest = F.array_min(F.transform("centers", lambda c: F.struct(d(c).alias("dist2"), c["cluster_id"].alias("cluster_id"))))
    return vectors.crossJoin(F.broadcast(packed)).select("stream_id", nearest["cluster_id"].alias("cluster_id"), nearest["dist2"].alias("dist2"))


def split_late(path: str, late_seconds: int = 3600) -> Callable[[DataFrame, int], None]:
    """For foreachBatch: appends to path/late the rows that are older than the newest ts of all earlier micro-batches less
    late_seconds, and to path/fresh all others. The newest ts is kept in path/newest, one file an epoch."""

    def write(rows: DataFrame, epoch: int) -> None:
        spark = rows.sparkSession
        newest = None
        try:
            newest = spark.read.parquet(f"{path}/newest").where(F.col("epoch") < epoch).agg(F.max("ts")).first()[0]
        except Exception as e:  # no earlier epoch has written yet
            if "PATH_NOT_FOUND" not in str(e) and "UNABLE_TO_INFER_SCHEMA" not in str(e):
                raise
        late = F.col("ts") < F.lit(newest) - F.expr(f"interval {late_seconds} seconds") if newest is not None else F.lit(False)
        rows.where(late).write.mode("overwrite").parquet(f"{path}/late/epoch={epoch}")
        rows.where(~late).write.mode("overwrite").parquet(f"{path}/fresh/epoch={epoch}")
        rows.agg(F.max("ts").alias("ts")).where("ts is not null").write.mode("overwrite").parquet(f"{path}/newest/epoch={epoch}")

    return write

"""The streams of the given tables, as long rows (stream_id, pos, sym) in a total order."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

SLOTS, SLOT_SECONDS, ORIGIN = 1440, 1800, "2024-01-01"
BLOCK = 1500
LARGEST = 65535


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _numbered(df: DataFrame, stream: str, order: list, sym: Column) -> DataFrame:
    w = Window.partitionBy(stream).orderBy(*order)
    return df.select(F.col(stream).cast("bigint").alias("stream_id"), (F.row_number().over(w) - 1).alias("pos"), sym.cast("bigint").alias("sym"))


def cents(c: str) -> Column:
    return F.round(F.col(c) * 100).cast("bigint")


def two_words(rows: DataFrame) -> DataFrame:
    """Symbols beyond 16 bits as two: the high word, then the low one."""
    words = F.posexplode(F.array(F.shiftright("sym", 16), F.col("sym").bitwiseAND(LARGEST)))
    return rows.select("stream_id", F.col("pos"), words.alias("half", "word")).select("stream_id", (F.col("pos") * 2 + F.col("half")).alias("pos"), F.col("word").alias("sym"))


def filled(sums: DataFrame, n: int, first: int = 0) -> DataFrame:
    """(stream_id, slot, sym) sums on a grid of n slots from the first, zero where there is none."""
    grid = sums.select("stream_id").distinct().select("stream_id", F.explode(F.sequence(F.lit(first), F.lit(first + n - 1))).alias("slot"))
    return grid.join(sums, ["stream_id", "slot"], "left").select("stream_id", F.col("slot").alias("pos"), F.coalesce("sym", F.lit(0).cast("bigint")).alias("sym"))


def meter_value(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _numbered(table(spark, sf_dir, "events"), "user_id", ["ts", "event_id"], cents("value"))


def slot_of(ts: str) -> Column:
    return F.floor(F.timestamp_diff("SECOND", F.lit(ORIGIN).cast("timestamp_ntz"), F.col(ts)) / SLOT_SECONDS).cast("int")


def slot_sums(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, int, int]:
    """(sums by meter and slot, slots of the grid, its first slot)."""
    events = table(spark, sf_dir, "events").select(F.col("user_id").alias("stream_id"), slot_of("ts").alias("slot"), cents("value").alias("c"))
    span = events.agg(F.min("slot").alias("first"), F.max("slot").alias("last")).first()
    low, high = min(0, (span["first"] or 0) // SLOTS), max(0, (span["last"] or 0) // SLOTS)
    return events.groupBy("stream_id", "slot").agg(F.sum("c").alias("sym")), (high - low + 1) * SLOTS, low * SLOTS


def meter_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sums by slot from ORIGIN on: SLOTS of them, and as many more before and after, in whole blocks of SLOTS, as the
    readings span. A reading without a time has no slot."""
    return filled(*slot_sums(spark, sf_dir))


def grid_blocks(spark: SparkSession, sf_dir: str, block_len: int) -> DataFrame:
    """blocks(meter_grid(...), block_len), with the empty slots of a meter filled in its arrays instead of a row for each."""
    sums, n, first = slot_sums(spark, sf_dir)
    timed = F.when(F.col("slot").isNotNull() & F.col("stream_id").isNotNull(), F.struct((F.col("slot") - first).alias("at"), F.coalesce("sym", F.lit(0).cast("bigint")).alias("sym")))
    meters = sums.groupBy("stream_id").agg(F.collect_list(timed).alias("x")).select("stream_id", F.col("x.at").alias("at"), F.col("x.sym").alias("sym"))
    numbers = np.arange(first // block_len, (first + n - 1) // block_len + 1)
    cuts = np.clip(np.append(numbers, numbers[-1] + 1) * block_len - first, 0, n)

    def run(batches):
        for b in batches:
            for i in range(0, len(b), 64):
                ids, at, sym = (b.column(c)[i : i + 64] for c in range(3))
                full = np.zeros((len(ids), n), np.int64)
                meter = np.repeat(np.arange(len(ids)), pc.list_value_length(at).to_numpy())
                full[meter, at.flatten().to_numpy()] = sym.flatten().to_numpy()
                ends = np.append((np.arange(len(ids))[:, None] * n + cuts[:-1]).ravel(), len(ids) * n).astype(np.int32)
                columns = [ids.take(pa.array(np.repeat(np.arange(len(ids)), len(numbers)))), pa.array(np.tile(numbers, len(ids)).astype(np.int32)), pa.array(np.diff(ends)), pa.ListArray.from_arrays(pa.array(ends), pa.array(full.ravel()))]
                yield pa.RecordBatch.from_arrays(columns, names=["stream_id", "block_no", "n_readings", "readings"])

    return meters.mapInArrow(run, "stream_id bigint, block_no int, n_readings int, readings array<bigint>")


def blocks_of(spark: SparkSession, sf_dir: str, name: str, block_len: int) -> DataFrame:
    """blocks() of a carrier."""
    return grid_blocks(spark, sf_dir, block_len) if name == "meter_grid" else blocks(carrier(spark, sf_dir, name), block_len)


LINE_ORDER = ["l_shipdate", "l_orderkey", "l_linenumber", "l_partkey", "l_extendedprice"]


def supplier_qty(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _numbered(table(spark, sf_dir, "lineitem"), "l_suppkey", LINE_ORDER, F.col("l_quantity"))


def supplier_price(spark: SparkSession, sf_dir: str) -> DataFrame:
    return two_words(_numbered(table(spark, sf_dir, "lineitem"), "l_suppkey", LINE_ORDER, cents("l_extendedprice")))


def supplier_day(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = table(spark, sf_dir, "lineitem").select(F.col("l_suppkey").alias("stream_id"), F.to_date("l_shipdate").alias("day"), F.col("l_quantity").cast("bigint").alias("q"))
    span = lines.agg(F.min("day").alias("first"), F.max("day").alias("last")).first()
    days = (span["last"] - span["first"]).days + 1 if span["first"] else 0
    sums = lines.groupBy("stream_id", F.datediff("day", F.lit(span["first"])).alias("slot")).agg(F.sum("q").alias("sym"))
    return filled(sums, max(1, days))


def customer_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    return two_words(_numbered(table(spark, sf_dir, "orders"), "o_custkey", ["o_orderdate", "o_orderkey"], cents("o_totalprice")))


def vector_int(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("stream_id"), F.posexplode("embedding").alias("pos", "x"))
    return vectors.select("stream_id", "pos", (F.round(F.col("x").cast("double") * 1000).cast("bigint") + 600).alias("sym"))


def _byte_lists():
    @F.arrow_udf("array<bigint>")
    def run(text: pa.Array) -> pa.Array:
        return pa.array([np.frombuffer(t, np.uint8).astype(np.int64) for t in text.cast(pa.binary()).to_pylist()], pa.list_(pa.int64()))

    return run


def text_bytes(spark: SparkSession, sf_dir: str, name: str = "documents", key: str = "doc_id", text: str = "text") -> DataFrame:
    """UTF-8 bytes of a text column, one stream a row."""
    rows = table(spark, sf_dir, name).where(F.octet_length(text) > 0)
    return rows.select(F.col(key).alias("stream_id"), F.posexplode(_byte_lists()(F.col(text))).alias("pos", "sym"))


def dim_codes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Small alphabets: part sizes (stream 0), nations of customers (1) and of suppliers (2), by key."""
    parts = []
    for i, (name, key, sym) in enumerate((("part", "p_partkey", "p_size"), ("customer", "c_custkey", "c_nationkey"), ("supplier", "s_suppkey", "s_nationkey"))):
        rows = table(spark, sf_dir, name).select(F.lit(i).alias("s"), F.col(key).alias("k"), F.col(sym).alias("v"))
        parts.append(_numbered(rows, "s", ["k"], F.col("v")))
    return parts[0].union(parts[1]).union(parts[2])


CARRIERS = {f.__name__: f for f in (meter_value, meter_grid, supplier_qty, supplier_price, supplier_day, customer_orders, vector_int, text_bytes, dim_codes)}
BLOCK_OF = {"meter_grid": SLOTS}


def carrier(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return CARRIERS[name](spark, sf_dir)


def fit(rows: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(readings of 0..65535, all others): unfit readings go aside, none is clipped."""
    ok = F.coalesce(F.col("sym").between(0, LARGEST), F.lit(False))
    return rows.where(ok), rows.where(~ok)


def blocks(rows: DataFrame, block_len: int = BLOCK) -> DataFrame:
    """(stream_id, block_no, n_readings, readings): a group holds block_len readings at most."""
    cut = rows.select("stream_id", F.floor(F.col("pos") / block_len).cast("int").alias("block_no"), F.struct("pos", "sym").alias("x"))
    out = cut.groupBy("stream_id", "block_no").agg(F.array_sort(F.collect_list("x")).alias("x"))
    return out.select("stream_id", "block_no", F.size("x").alias("n_readings"), F.col("x.sym").alias("readings"))


def three_houses(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Readings of the first three meters of the grid."""
    return meter_grid(spark, sf_dir).where(F.col("stream_id").isin([r.user_id for r in table(spark, sf_dir, "events").select("user_id").distinct().orderBy("user_id").limit(3).collect()]))


def premises(spark: SparkSession, sf_dir: str, n: int = 400) -> DataFrame:
    """Readings of the first n meters of the grid, or of all there are."""
    first = table(spark, sf_dir, "events").select(F.col("user_id").alias("stream_id")).distinct().orderBy("stream_id").limit(n)
    return meter_grid(spark, sf_dir).join(first, "stream_id", "left_semi")

"""First-stage compression of blocks of readings, and its inverse. Map-only."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession

from meterpack.kernels.firststage import CODERS, coder_for, decode_block, encode_blocks
from meterpack.schemas import READINGS, STREAMS


def spread(df: DataFrame, *keys: str) -> DataFrame:
    """df hashed by keys into as many partitions as the session shuffles into, or has cores for. A group costs far more
    time than its bytes tell, so adaptive execution must not merge these partitions, as it would by size; a grouping by
    the same keys needs no exchange after it."""
    return df.repartition(width(df.sparkSession), *keys)


def width(spark: SparkSession) -> int:
    """How many partitions the session shuffles into, or has cores for."""
    return max(int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism)


def dealt(df: DataFrame, number: Column, n: int) -> DataFrame:
    """df in n partitions by a number of 0..n-1: for a few large groups, of which a hash would put some together."""
    return df.repartitionById(n, number.cast("int"))


def rows_of(column: pa.Array) -> list[np.ndarray]:
    """The cells of a list column as arrays."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    values, ends = column.values.to_numpy(zero_copy_only=False), column.offsets.to_numpy()
    return [values[a:z] for a, z in zip(ends, ends[1:], strict=False)]


def readings_of(column: pa.Array) -> list[np.ndarray]:
    """rows_of, masked where a cell holds null."""
    values = column.values
    if not values.null_count:
        return rows_of(column)
    x, ends = np.ma.MaskedArray(values.fill_null(0).to_numpy(), values.is_null().to_numpy(zero_copy_only=False)), column.offsets.to_numpy()
    return [x[a:z] for a, z in zip(ends, ends[1:], strict=False)]


def first_stage(blocks: DataFrame, coder: str = "gaussian_ac") -> DataFrame:
    """Compressed streams (STREAMS) of blocks (stream_id, block_no, n_readings, readings). A block with readings
    that do not fit the coder takes its wide form, so that none is lost or moved."""
    if coder not in CODERS:
        raise ValueError(f"no first-stage coder {coder!r}; there are {', '.join(CODERS)}")

    def run(batches):
        for b in batches:
            readings = readings_of(b.column(3))
            coders = [coder_for(x, coder) for x in readings]
            done = encode_blocks(readings, coders)
            n_bits, mu, sigma, first, words = zip(*done, strict=True) if done else ((),) * 5
            columns = [b.column(0), b.column(1), pa.array(coders, pa.string()), b.column(2), pa.array(n_bits, pa.int64()), pa.array(mu, pa.int32()), pa.array(sigma, pa.int32()), pa.array(first, pa.int64()), pa.array(words, pa.list_(pa.int32()))]
            yield pa.RecordBatch.from_arrays(columns, names=["stream_id", "block_no", "coder", "n_readings", "n_bits", "mu", "sigma", "first", "words"])

    return spread(blocks.select("stream_id", "block_no", "n_readings", "readings"), "stream_id", "block_no").mapInArrow(run, STREAMS)


def first_stage_inverse(streams: DataFrame, block_len: int) -> DataFrame:
    """Long readings of compressed streams; block_len places the blocks within their stream."""

    def run(batches):
        for b in batches:
            for row, words in zip(b.select([n for n in b.schema.names if n != "words"]).to_pylist(), rows_of(b.column(b.schema.names.index("words"))), strict=True):
                x = decode_block(words, row["coder"], row["n_readings"], row["n_bits"], row["mu"], row["sigma"], row["first"])
                pos = np.arange(len(x), dtype=np.int32) + row["block_no"] * block_len
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(x), row["stream_id"], np.int64)), pa.array(pos.astype(np.int32)), pa.array(x.astype(np.int64))], names=["stream_id", "pos", "sym"])

    return streams.select(*[c.split()[0] for c in STREAMS.split(", ")]).mapInArrow(run, READINGS)

"""Direct re-compression by known coders, of single streams and of whole batches."""

from __future__ import annotations

import bz2
import lzma
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from meterpack.kernels.arith import ac_encode, adaptive_encode, gaussian_encode
from meterpack.kernels.codec import column_order
from meterpack.kernels.huffman import huffman_encode
from meterpack.kernels.lz import lz77_encode, lz78_encode, lzw_encode
from meterpack.operators.firststage import rows_of, spread


def _bytes(x: np.ndarray) -> bytes:
    return np.asarray(x).astype(">u2").tobytes()


#: Bits of a block of 16-bit words under each coder, side data counted. The last three are library coders, for reference.
CODERS = {
    "huffman": lambda x: (lambda r: r[2] + 8 * len(r[1]))(huffman_encode(x)),
    "gaussian_ac": lambda x: 8 * len(gaussian_encode(x)[0]) + 32,
    "static_ac": lambda x: 8 * sum(map(len, ac_encode(x))),
    "adaptive_ac": lambda x: 8 * sum(map(len, adaptive_encode(x))),
    "lz77": lambda x: 8 * len(lz77_encode(x)),
    "lz78": lambda x: 8 * len(lz78_encode(x)),
    "lzw": lambda x: 8 * len(lzw_encode(_bytes(x))),
    "zlib": lambda x: 8 * len(zlib.compress(_bytes(x), 9)),
    "bz2": lambda x: 8 * len(bz2.compress(_bytes(x))),
    "lzma": lambda x: 8 * len(lzma.compress(_bytes(x))),
}


def single(streams: DataFrame, coders: tuple[str, ...] = ("huffman", "gaussian_ac", "lz77", "lz78", "lzw")) -> DataFrame:
    """(stream_id, block_no, coder, orig_bits, new_bits, cr) of every stream under every coder. Map-only."""

    def run(batches):
        for b in batches:
            ids, nos, bits, words = b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist(), rows_of(b.column(3))
            out = [(i, n, c, o, CODERS[c](w)) for i, n, o, w in zip(ids, nos, bits, words, strict=True) if len(w) for c in coders]
            i, n, c, o, new = zip(*out, strict=True) if out else ((),) * 5
            cr = [round(a / z, 6) if z else None for a, z in zip(o, new, strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(i, pa.int64()), pa.array(n, pa.int32()), pa.array(c, pa.string()), pa.array(o, pa.int64()), pa.array(new, pa.int64()), pa.array(cr, pa.float64())], names=["stream_id", "block_no", "coder", "orig_bits", "new_bits", "cr"])

    return spread(streams.select("stream_id", "block_no", "n_bits", "words"), "stream_id", "block_no").mapInArrow(run, "stream_id bigint, block_no int, coder string, orig_bits bigint, new_bits bigint, cr double")


def collection(streams: DataFrame, coders: tuple[str, ...] = ("huffman", "gaussian_ac", "lz77", "lz78", "lzw"), layout: str = "concat") -> DataFrame:
    """The same of whole batches (streams with a batch_id), their streams laid end to end or interleaved."""

    def run(t: pa.Table) -> pa.Table:
        ids = t["stream_id"].to_numpy()
        words = [rows_of(t["words"])[i] for i in np.argsort(ids)]
        x = np.concatenate(words)[column_order(np.array(list(map(len, words))), layout)]
        orig, n = int(t["n_bits"].to_numpy().sum()), len(coders)
        new = [CODERS[c](x) for c in coders]
        return pa.table({"batch_id": pa.array([t["batch_id"][0].as_py()] * n, pa.int64()), "block_no": pa.array([t["block_no"][0].as_py()] * n, pa.int32()), "coder": pa.array(list(coders)), "n_streams": pa.array([len(ids)] * n, pa.int64()), "orig_bits": pa.array([orig] * n, pa.int64()), "new_bits": pa.array(new, pa.int64()), "cr": pa.array([round(orig / z, 6) for z in new])})

    return spread(streams.select("batch_id", "block_no", "stream_id", "n_bits", "words"), "batch_id", "block_no").groupBy("batch_id", "block_no").applyInArrow(run, "batch_id bigint, block_no int, coder string, n_streams bigint, orig_bits bigint, new_bits bigint, cr double")

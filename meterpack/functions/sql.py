"""SQL functions: mp_* over arrays, and the table function that unpacks packed rows."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from meterpack.kernels.arith import ac_decode, ac_encode
from meterpack.kernels.bwt import bwt, bwt_inverse
from meterpack.kernels.huffman import huffman_encode
from meterpack.kernels.lz import lz77_encode
from meterpack.kernels.mtf import mtf, mtf_inverse
from meterpack.kernels.rle import rle_dynamic, rle_dynamic_inverse
from meterpack.operators.firststage import rows_of
from meterpack.plans.recompress import unpack

#: Plain SQL over higher-order functions: no Python.
SQL_FUNCTIONS = {
    "mp_delta": "CREATE OR REPLACE TEMPORARY FUNCTION mp_delta(a ARRAY<BIGINT>) RETURNS ARRAY<BIGINT> RETURN transform(a, (x, i) -> x - CASE WHEN i = 0 THEN 0L ELSE a[i - 1] END)",
    "mp_undelta": "CREATE OR REPLACE TEMPORARY FUNCTION mp_undelta(a ARRAY<BIGINT>) RETURNS ARRAY<BIGINT> RETURN aggregate(a, CAST(array() AS ARRAY<BIGINT>), (acc, x) -> concat(acc, array(x + coalesce(try_element_at(acc, -1), 0L))))",
    "mp_dist2": "CREATE OR REPLACE TEMPORARY FUNCTION mp_dist2(a ARRAY<BIGINT>, b ARRAY<BIGINT>) RETURNS BIGINT RETURN aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0L, (s, x) -> s + x)",
}

LONGS = pa.list_(pa.int64())


def _cells(kernel, kind, ddl):
    """An Arrow function of list cells by a kernel that takes one array."""

    @F.arrow_udf(ddl)
    def run(column: pa.Array) -> pa.Array:
        return pa.array([None if missing else kernel(x) for x, missing in zip(rows_of(column), column.is_null().to_pylist(), strict=True)], kind)

    return run


def _structs(kernel, kind, ddl):
    """The same of struct cells, whose fields are lists, numbers or bytes."""

    @F.arrow_udf(ddl)
    def run(column: pa.Array) -> pa.Array:
        return pa.array([None if cell is None else kernel(cell) for cell in column.to_pylist()], kind)

    return run


def _coded(encode):
    def kernel(x):
        payload, model = encode(x)[:2]
        return {"payload": payload, "model": model, "bits": 8 * (len(payload) + len(model))}

    return _cells(kernel, pa.struct([("payload", pa.binary()), ("model", pa.binary()), ("bits", pa.int64())]), "struct<payload:binary,model:binary,bits:bigint>")


def register(spark: SparkSession) -> list[str]:
    """Registers all functions in the session; their names."""
    for statement in SQL_FUNCTIONS.values():
        spark.sql(statement)
    column = pa.struct([("last", LONGS), ("primary", pa.int64())])
    ranked = pa.struct([("ranks", LONGS), ("alphabet", LONGS)])
    cut = pa.struct([("applied", pa.bool_()), ("t", pa.int64()), ("syms", LONGS), ("counts", LONGS)])
    array = np.array
    udfs = {
        "mp_bwt": _cells(lambda x: dict(zip(("last", "primary"), bwt(x), strict=True)), column, "struct<last:array<bigint>,primary:bigint>"),
        "mp_ibwt": _structs(lambda c: bwt_inverse(array(c["last"], np.int64), c["primary"]), LONGS, "array<bigint>"),
        "mp_mtf": _cells(lambda x: dict(zip(("ranks", "alphabet"), mtf(x), strict=True)), ranked, "struct<ranks:array<bigint>,alphabet:array<bigint>>"),
        "mp_imtf": _structs(lambda c: mtf_inverse(array(c["ranks"], np.int64), array(c["alphabet"], np.int64)), LONGS, "array<bigint>"),
        "mp_rle": _cells(lambda x: dict(zip(("applied", "t", "syms", "counts"), rle_dynamic(x), strict=True)), cut, "struct<applied:boolean,t:bigint,syms:array<bigint>,counts:array<bigint>>"),
        "mp_irle": _structs(lambda c: rle_dynamic_inverse(c["applied"], c["t"], array(c["syms"], np.int64), array(c["counts"], np.int64)), LONGS, "array<bigint>"),
        "mp_ac_encode": _coded(ac_encode),
        "mp_ac_decode": _structs(lambda c: ac_decode(c["payload"], c["model"])[0], LONGS, "array<bigint>"),
        "mp_huffman": _coded(huffman_encode),
        "mp_lz": _coded(lambda x: (lz77_encode(x), b"")),
    }
    for name, f in udfs.items():
        spark.udf.register(name, f)

    return [*SQL_FUNCTIONS, *udfs]


def register_entropy(spark: SparkSession) -> None:
    """mp_entropy(sym), a grouped aggregate; the two-level count of operators.measures is the form for large groups."""

    def entropy(sym):
        n = sym.value_counts().to_numpy()
        return float(abs(np.log2(n.sum()) - (n * np.log2(n)).sum() / n.sum())) if len(n) else 0.0

    spark.udf.register("mp_entropy", F.pandas_udf(entropy, "double", F.PandasUDFType.GROUPED_AGG))


class Unpack:
    """Rows (stream_id, pos, word) of one packed row."""

    def eval(self, row):
        fields = row.asDict()
        for s in unpack(fields | {"applied": fields["rle_applied"], "t": fields["rle_threshold"]}):
            for pos, word in enumerate(s["words"].tolist()):
                yield s["stream_id"], s["block_no"], pos, word


def register_unpack(spark: SparkSession) -> None:
    """mp_unpack(TABLE(packed)) in SQL."""
    spark.udtf.register("mp_unpack", F.udtf(Unpack, returnType="stream_id bigint, block_no int, pos int, word bigint"))

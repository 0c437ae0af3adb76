"""Re-compression of batches of compressed streams, and their recovery.

Encoding shuffles once, by batch; grouping and the whole chain run in that task, which holds one batch of bounded size.
Recovery is map-only: a packed row has all that it takes.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator
from itertools import groupby

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from meterpack.kernels.bits import get_varints, put_varints, unzigzag, zigzag
from meterpack.kernels.codec import Config, decode_group, encode_many, read_config, transformed
from meterpack.kernels.firststage import CODERS, decode_block
from meterpack.kernels.group import lloyd, pad, random_cluster, seeds
from meterpack.operators.firststage import rows_of, spread
from meterpack.operators.ranks import dense_ranks
from meterpack.schemas import PACKED, READINGS, STREAMS

BATCH = 56
#: Words of the parts of groups that are coded in step.
TOGETHER = 1 << 24
#: Bytes of a packed row beside its binary columns: cluster, part, flags, thresholds, counts.
HEADER_BYTES = 12


def batch_by_rank(streams: DataFrame, size: int = BATCH) -> DataFrame:
    """batch_id: the first `size` streams by id, the next `size`, and so on.

    The rank is taken over distinct ids in two levels (a rank in each range, offsets of the ranges), so that no task
    sorts all ids; the ranges are written first, as a lost executor would else deal them anew."""
    ranked = dense_ranks(streams.select("stream_id").distinct(), "stream_id").select("stream_id", F.floor(F.col("rank") / size).cast("bigint").alias("batch_id"))
    return streams.join(ranked, "stream_id")


def batch_by_hash(streams: DataFrame, n: int, seed: int = 42) -> DataFrame:
    """batch_id: one of n, by md5 of the id; no rank, no shuffle."""
    return streams.withColumn("batch_id", md5_draw(F.col("stream_id"), seed, n).cast("bigint"))


def md5_draw(stream_id: Column, seed: int, k: int) -> Column:
    """The draw of random grouping: first 8 hex digits of md5("id:seed"), modulo k."""
    digits = F.substring(F.md5(F.concat(stream_id.cast("string"), F.lit(f":{seed}"))), 1, 8)
    return F.pmod(F.conv(digits, 16, 10).cast("bigint"), F.lit(k))


def group_labels(ids: np.ndarray, words: list[np.ndarray], cfg: Config, batch: int) -> np.ndarray:
    """Cluster of each stream of a batch (ids ascend)."""
    n = len(ids)
    if cfg.grouping == "none":
        return np.zeros(n, np.int64)
    if cfg.grouping == "each":
        return np.arange(n)
    if cfg.k > n:
        raise ValueError(f"k = {cfg.k} groups of {n} streams")
    if cfg.grouping == "random":
        return np.array([random_cluster(int(i), cfg.k, cfg.seed) for i in ids])
    if cfg.grouping != "kmeans":
        raise ValueError(f"no grouping {cfg.grouping!r}")
    x = pad(words, cfg.vector)
    labels, *_ = lloyd(x, x[seeds(x, ids, cfg.k, cfg.seed, batch, cfg.seed_scope, cfg.init)], cfg.max_iter)
    return labels


def _parts(members: list[int], sizes: list[int], most: int) -> list[list[int]]:
    """Members in runs of at most `most` symbols (one member at least)."""
    out, room = [], 0
    for m in members:
        if not out or room < sizes[m]:
            out.append([])
            room = most
        out[-1].append(m)
        room -= sizes[m]
    return out


def pack_batch(batch_id: int, window_no: int, rows: list[dict], *cfgs: Config) -> list[dict]:
    """Packed rows of one batch; rows are its streams. Several configurations may differ in their run lengths and coder only: what
    comes before is done once for all, a part of a group at a time."""
    return list(pack_batches([(batch_id, window_no, rows, cfgs)]))


def pack_batches(batches: Iterable[tuple[int, int, list[dict], tuple[Config, ...]]]) -> Iterator[dict]:
    """pack_batch of each (batch_id, window_no, rows, configurations); parts of TOGETHER words in all are coded in step."""
    held, n = [], 0
    for batch_id, window_no, rows, cfgs in batches:
        if len({c.but(rle=None, coder="arith") for c in cfgs}) > 1:
            raise ValueError("configurations differ in more than run lengths and coder")
        rows = sorted(rows, key=lambda r: r["stream_id"])
        words = [np.asarray(r["words"]) for r in rows]
        ids = np.array([r["stream_id"] for r in rows], np.int64)
        labels = group_labels(ids, words, cfgs[0], batch_id)
        for c in np.unique(labels):
            for part, members in enumerate(_parts(np.flatnonzero(labels == c).tolist(), [len(w) for w in words], cfgs[0].max_block)):
                size = sum(len(words[m]) for m in members)
                if held and n + size > TOGETHER:
                    yield from _pack(held)
                    held, n = [], 0
                held.append((batch_id, window_no, int(c), part, [rows[m] for m in members], [words[m] for m in members], cfgs))
                n += size
    yield from _pack(held)


def _pack(parts: list[tuple]) -> Iterator[dict]:
    """Packed rows of parts (batch_id, window_no, cluster, part, rows, words, configurations)."""

    def groups():
        for *_, streams, cfgs in parts:
            before = transformed(streams, cfgs[0])
            yield from ((streams, cfg, before) for cfg in cfgs)

    coded = iter(encode_many(groups()))
    for batch_id, window_no, c, part, own, streams, cfgs in parts:
        meta = put_varints(v for r in own for v in (CODERS.index(r["coder"]), r["n_readings"], r["n_bits"], int(zigzag(np.array(r["mu"]))), r["sigma"], int(zigzag(np.array(r["first"])))))
        lengths = [len(w) for w in streams]
        names = put_varints(np.diff([0, *(r["stream_id"] for r in own)])) + put_varints(lengths)
        for cfg in cfgs:
            e = next(coded)
            side = 8 * (HEADER_BYTES + len(names) + len(meta) + len(e["alphabet"]) + len(e["model"]))
            yield {
                "batch_id": batch_id, "window_no": window_no, "k": cfg.k, "cluster_id": c, "part": part, "grouping": cfg.grouping, "config": cfg.text(),
                "stream_ids": [r["stream_id"] for r in own], "stream_lengths": lengths, "n_symbols": sum(lengths), "rle_applied": e["applied"], "rle_threshold": e["t"],
                "streams_meta": meta, "alphabet": e["alphabet"], "model": e["model"], "payload": e["payload"], "payload_bits": 8 * len(e["payload"]), "side_bits": side,
                "orig_bits": sum(r["n_bits"] for r in own), "raw_bits": sum(16 * r["n_readings"] for r in own), "crc": e["crc"],
            }


def stream_rows(table: pa.Table | pa.RecordBatch) -> list[dict]:
    """Streams as rows, their words as arrays."""
    rows = table.drop_columns(["words"]).to_pylist()
    for r, w in zip(rows, rows_of(table.column("words")), strict=True):
        r["words"] = w
    return rows


def packed_by(streams: DataFrame, keys: list[str], batch: Callable[[list[dict]], tuple[int, int, list[dict], tuple[Config, ...]] | None], placed: DataFrame | None = None) -> DataFrame:
    """Packed rows of streams grouped by keys, where batch() tells what to pack of the rows of a group. A task goes through its
    groups in order, so that small ones are coded in step too. placed: the streams where each group is in one partition."""
    schema = arrow_schema(PACKED)

    def run(batches):
        rows = (r for b in batches for r in stream_rows(b))
        grouped = (batch(list(own)) for _, own in groupby(rows, key=lambda r: tuple(r[k] for k in keys)))
        out: list[dict] = []
        for row in pack_batches(b for b in grouped if b):
            out.append(row)
            if len(out) == 256:
                yield from pa.Table.from_pylist(out, schema).to_batches()
                out = []
        yield from pa.Table.from_pylist(out, schema).to_batches()

    return (spread(streams, *keys) if placed is None else placed).sortWithinPartitions(*keys).mapInArrow(run, PACKED)


ARROW = {"bigint": pa.int64(), "int": pa.int32(), "string": pa.string(), "boolean": pa.bool_(), "binary": pa.binary(), "double": pa.float64(), "array<bigint>": pa.list_(pa.int64()), "array<int>": pa.list_(pa.int32())}


def arrow_schema(ddl: str) -> pa.Schema:
    return pa.schema([(c.split()[0], ARROW[c.split()[1]]) for c in ddl.split(", ")])


def recompress(streams: DataFrame, cfg: Config = Config()) -> DataFrame:
    """Packed rows (PACKED) of streams with a batch_id; each (batch_id, block_no) is coded on its own."""
    own = [c.split()[0] for c in STREAMS.split(", ")]
    return packed_by(streams.select("batch_id", *own), ["batch_id", "block_no"], lambda rows: (rows[0]["batch_id"], rows[0]["block_no"], rows, (cfg,)))


def unpack(row: dict) -> list[dict]:
    """Compressed streams of one packed row."""
    words = decode_group(row, row["stream_lengths"], read_config(row["config"]))
    meta, _ = get_varints(row["streams_meta"])
    out = []
    for i, (stream_id, w) in enumerate(zip(row["stream_ids"], words, strict=True)):
        coder, n, bits, mu, sigma, first = meta[6 * i : 6 * i + 6]
        out.append({"stream_id": stream_id, "block_no": row["window_no"], "coder": CODERS[coder], "n_readings": n, "n_bits": bits, "mu": int(unzigzag(np.array(mu))), "sigma": sigma, "first": int(unzigzag(np.array(first))), "words": w})
    return out


NEEDED = ["window_no", "stream_ids", "stream_lengths", "config", "rle_applied", "rle_threshold", "streams_meta", "alphabet", "model", "payload", "crc"]


def _rows(batch: pa.RecordBatch):
    for row in batch.to_pylist():
        yield row | {"applied": row["rle_applied"], "t": row["rle_threshold"]}


def recover_streams(packed: DataFrame, stream_ids: list[int] | None = None) -> DataFrame:
    """The compressed streams; with stream_ids, of these only, and only rows that hold one are decoded."""
    schema, wanted = arrow_schema(STREAMS), set(stream_ids) if stream_ids is not None else None
    if wanted is not None:
        packed = packed.where(F.arrays_overlap("stream_ids", F.array(*(F.lit(int(i)) for i in wanted)).cast("array<bigint>")))

    def run(batches):
        for b in batches:
            for row in _rows(b):
                found = [s for s in unpack(row) if wanted is None or s["stream_id"] in wanted]
                yield from pa.Table.from_pylist([s | {"words": s["words"].astype(np.int32)} for s in found], schema).to_batches()

    return packed.select(*NEEDED).mapInArrow(run, STREAMS)


def recover_readings(packed: DataFrame, block_len: int, stream_ids: list[int] | None = None) -> DataFrame:
    """The readings, in the same task that decodes the streams."""
    wanted = set(stream_ids) if stream_ids is not None else None
    if wanted is not None:
        packed = packed.where(F.arrays_overlap("stream_ids", F.array(*(F.lit(int(i)) for i in wanted)).cast("array<bigint>")))

    def run(batches):
        for b in batches:
            for row in _rows(b):
                for s in unpack(row):
                    if wanted is None or s["stream_id"] in wanted:
                        x = decode_block(s["words"], s["coder"], s["n_readings"], s["n_bits"], s["mu"], s["sigma"], s["first"])
                        pos = (np.arange(len(x)) + s["block_no"] * block_len).astype(np.int32)
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(x), s["stream_id"], np.int64)), pa.array(pos), pa.array(x)], names=["stream_id", "pos", "sym"])

    return packed.select(*NEEDED).mapInArrow(run, READINGS)


def compression_ratio(packed: DataFrame, *by: str) -> DataFrame:
    """cr_total counts side data, cr_payload does not; cr_end_to_end is against 16-bit readings."""
    o, p, s = F.sum("orig_bits"), F.sum("payload_bits"), F.sum("side_bits")
    ratio = lambda top, low: F.round(top / F.when(low > 0, low), 6)
    return packed.groupBy(*by).agg(o.alias("orig_bits"), p.alias("payload_bits"), s.alias("side_bits"), F.sum("n_symbols").alias("n_symbols"), ratio(o, p + s).alias("cr_total"), ratio(o, p).alias("cr_payload"), F.round(1 - (p + s) / o, 6).alias("saving"), ratio(F.sum("raw_bits"), p + s).alias("cr_end_to_end"))

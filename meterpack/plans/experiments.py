"""The experiment workloads: what each returns is a table of measures by carrier, parameters and configuration."""

from __future__ import annotations

import time
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from meterpack.kernels.codec import Config, encode, stages
from meterpack.kernels.arith import ac_decode, ac_encode
from meterpack.kernels.bwt import bwt, bwt_inverse
from meterpack.kernels.group import silhouette
from meterpack.kernels.mtf import mtf, mtf_inverse
from meterpack.kernels.rle import ideal_bits, rle_dynamic, rle_dynamic_inverse
from meterpack.operators.baselines import collection, single
from meterpack.operators.firststage import dealt, first_stage, rows_of, spread, width
from meterpack.operators.ranks import dense_ranks, kept
from meterpack.plans.recompress import batch_by_rank, compression_ratio, group_labels, packed_by, recompress
from meterpack.schemas import STREAMS
from meterpack.kernels.group import pad
from meterpack.sources.carriers import BLOCK, BLOCK_OF, blocks_of

KS = (2, 4, 6, 8, 10, 12)


def streams_of(spark: SparkSession, sf_dir: str, name: str, coder: str = "identity") -> DataFrame:
    return first_stage(blocks_of(spark, sf_dir, name, BLOCK_OF.get(name, BLOCK)), coder)


def single_cr(spark: SparkSession, sf_dir: str, carriers=("meter_grid", "meter_value", "supplier_qty"), first=("gaussian_ac", "identity")) -> DataFrame:
    """Each compressed stream on its own under each known coder."""
    parts = [single(streams_of(spark, sf_dir, c, f)).select(F.lit(c).alias("carrier"), F.lit(f).alias("first_stage"), "*") for c in carriers for f in first]
    return _all(parts)


def collection_cr(spark: SparkSession, sf_dir: str, carriers=("meter_grid", "meter_value", "supplier_qty"), first=("gaussian_ac", "identity"), size: int = 56) -> DataFrame:
    """56 compressed streams together under each known coder; a short last batch shows by its n_streams."""
    parts = [collection(batch_by_rank(streams_of(spark, sf_dir, c, f), size)).select(F.lit(c).alias("carrier"), F.lit(f).alias("first_stage"), "*") for c in carriers for f in first]
    return _all(parts)


def _all(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


#: What all experiments run on, as published: compressed streams. The last two show what the first stage does to them.
CASES = (("meter_grid", "gaussian_ac"), ("meter_value", "gaussian_ac"), ("supplier_qty", "gaussian_ac"), ("vector_int", "gaussian_ac"), ("meter_grid", "delta_varint"), ("meter_grid", "identity"))


def over(run: Callable[..., DataFrame], spark: SparkSession, sf_dir: str, cases=CASES) -> DataFrame:
    """One experiment over all cases, with their names."""
    named = []
    for name, first in cases:
        rows = run(spark, sf_dir, name, first)
        named.append(rows.select(F.lit(name).alias("carrier"), F.lit(first).alias("first_stage"), *(c for c in rows.columns if c not in ("carrier", "first_stage"))))
    return _all(named)


def records(streams: DataFrame, n: int = 4, seed: int = 42) -> DataFrame:
    """streams with a record (1..n): n even parts of the streams in md5 order, by ranks in two levels; the first parts take
    what is left over."""
    order = F.md5(F.concat(F.col("stream_id").cast("string"), F.lit(f":{seed}")))
    ranked = dense_ranks(streams.select("stream_id").distinct().withColumn("__mp_order", order), "__mp_order")
    total = ranked.count()
    size, more = divmod(total, n)
    r = F.col("rank")
    part = F.when(r < (size + 1) * more, F.floor(r / (size + 1))).otherwise(more + F.floor((r - (size + 1) * more) / max(1, size))) + 1
    return streams.join(ranked.select("stream_id", part.cast("int").alias("record")), "stream_id")


CONFIGS = [(g, r) for g in ("random", "kmeans") for r in ("static", "dynamic")]


def grid(spark: SparkSession, sf_dir: str, name: str = "meter_grid", first: str = "gaussian_ac", ks=KS, base: Config = Config()) -> DataFrame:
    """(carrier, first_stage, record, k, grouping, rle, cr_total, cr_payload, n_symbols): 4 records for each k, under two
    groupings and two run lengths. A k above the streams of a record is left out."""
    return _grid(records(kept(streams_of(spark, sf_dir, name, first), "streams")), name, first, ks, base)


def _grid(recorded: DataFrame, name: str, first: str, ks, base: Config) -> DataFrame:
    table = spark_configs(recorded.sparkSession, ks)

    def batch(rows: list[dict]):
        k, grouping, record, block_no = (rows[0][c] for c in ("k", "grouping", "record", "block_no"))
        cfgs = tuple(base.but(k=k, grouping=grouping, rle=rle) for g, rle in CONFIGS if g == grouping)
        return (record, block_no, rows, cfgs) if len(rows) >= k else None

    own = [c.split()[0] for c in STREAMS.split(", ")]
    configured = recorded.select("record", *own).crossJoin(F.broadcast(table))
    # a task of its own for each configuration of each record and some blocks; those that take longest go first
    each = 2 * len(ks)
    n_blocks = -(-width(recorded.sparkSession) // (4 * each))
    number = (F.pmod("block_no", F.lit(n_blocks)) * 4 + F.pmod("record", F.lit(4))) * each + F.col("no")
    packed = packed_by(configured, ["record", "k", "grouping", "block_no"], batch, dealt(configured, number, n_blocks * 4 * each))
    rle = F.get_json_object("config", "$.rle")
    ratios = compression_ratio(packed.withColumn("rle", rle), "batch_id", "k", "grouping", "rle")
    return ratios.select(F.lit(name).alias("carrier"), F.lit(first).alias("first_stage"), F.col("batch_id").alias("record"), "k", "grouping", "rle", "cr_total", "cr_payload", "n_symbols")


def spark_configs(spark: SparkSession, ks) -> DataFrame:
    """What groups streams; both run lengths are coded in the same task."""
    both = [(k, g) for g in sorted({g for g, _ in CONFIGS}) for k in sorted(ks, reverse=True)]
    return spark.createDataFrame([(*c, no) for no, c in enumerate(both)], "k int, grouping string, no int")


def grid_means(grid_rows: DataFrame) -> DataFrame:
    """(grouping, rle, k, mean_cr): means of records by configuration and k; k null: of all k; grouping and rle null: of all."""
    return grid_rows.rollup("grouping", "rle", "k").agg(F.round(F.avg("cr_total"), 4).alias("mean_cr_total"), F.round(F.avg("cr_payload"), 4).alias("mean_cr_payload"), F.count(F.lit(1)).alias("records"))


def entropy_by_stage(spark: SparkSession, sf_dir: str, name: str = "meter_grid", first: str = "gaussian_ac", cfg: Config = Config()) -> DataFrame:
    """(batch_id, grouping, cluster_id, stage, n, h): zero-order entropy after each step, for random and for k-means
    groups of each batch. Where runs have a list of counts, `rle` is all bits over the input symbols; `coded` is the bits paid."""
    streams = batch_by_rank(streams_of(spark, sf_dir, name, first))

    def run(t: pa.Table) -> pa.Table:
        order = np.argsort(t["stream_id"].to_numpy())
        ids, words = t["stream_id"].to_numpy()[order], [rows_of(t["words"])[i].astype(np.int64) for i in order]
        out = []
        for grouping in ("random", "kmeans"):
            c = cfg.but(grouping=grouping, k=min(cfg.k, len(ids)))
            labels = group_labels(ids, words, c, t["batch_id"][0].as_py())
            for label in np.unique(labels):
                s = stages([words[i] for i in np.flatnonzero(labels == label)], c)
                n = len(s["raw"])
                for stage in ("raw", "interleaved", "delta", "bwt", "mtf"):
                    out.append((grouping, int(label), stage, len(s[stage]), ideal_bits(s[stage]) / max(1, len(s[stage]))))
                out.append((grouping, int(label), "rle", n, sum(map(ideal_bits, s["lists"])) / max(1, n)))
                # what is paid: the payload of the coder, and with its tables
                e = encode([words[i] for i in np.flatnonzero(labels == label)], c)
                out.append((grouping, int(label), "coded", n, 8 * len(e["payload"]) / max(1, n)))
                out.append((grouping, int(label), "coded with tables", n, 8 * sum(len(e[x]) for x in ("payload", "model", "alphabet")) / max(1, n)))
        g, label, stage, n, h = zip(*out, strict=True)
        return pa.table({"batch_id": pa.array([t["batch_id"][0].as_py()] * len(g), pa.int64()), "block_no": pa.array([t["block_no"][0].as_py()] * len(g), pa.int32()), "grouping": pa.array(g), "cluster_id": pa.array(label, pa.int32()), "stage": pa.array(stage), "n": pa.array(n, pa.int64()), "h": pa.array([round(abs(x), 6) for x in h])})

    return spread(streams, "batch_id", "block_no").groupBy("batch_id", "block_no").applyInArrow(run, "batch_id bigint, block_no int, grouping string, cluster_id int, stage string, n bigint, h double")


def entropy_means(by_stage: DataFrame) -> DataFrame:
    """(grouping, stage, mean_h, implied_ratio): the ratio is raw entropy over the stage's, the gain that entropy promises; of the
    coded stages, the one achieved against an ideal coder of the raw words."""
    means = by_stage.groupBy("grouping", "stage").agg(F.round(F.sum(F.col("h") * F.col("n")) / F.sum("n"), 6).alias("mean_h"))
    raw = F.max(F.when(F.col("stage") == "raw", F.col("mean_h"))).over(Window.partitionBy("grouping"))
    return means.withColumn("implied_ratio", F.round(raw / F.nullif("mean_h", F.lit(0.0)), 4))


def silhouette_by_k(spark: SparkSession, sf_dir: str, name: str = "meter_grid", first: str = "gaussian_ac", ks=KS, base: Config = Config()) -> DataFrame:
    """(batch_id, block_no, k, grouping, silhouette, n) for k-means and random groups of each block of each batch of 56."""
    streams = batch_by_rank(streams_of(spark, sf_dir, name, first))

    def run(t: pa.Table) -> pa.Table:
        order = np.argsort(t["stream_id"].to_numpy())
        ids, words = t["stream_id"].to_numpy()[order], [rows_of(t["words"])[i].astype(np.int64) for i in order]
        x, out = pad(words, base.vector), []
        for k in ks:
            for grouping in ("random", "kmeans"):
                if k <= len(ids):
                    s = silhouette(x, group_labels(ids, words, base.but(k=k, grouping=grouping), t["batch_id"][0].as_py()))
                    out.append((k, grouping, None if np.isnan(s).all() else round(float(s.mean()), 6), len(ids)))
        k, g, s, n = zip(*out, strict=True) if out else ((),) * 4
        return pa.table({"batch_id": pa.array([t["batch_id"][0].as_py()] * len(k), pa.int64()), "block_no": pa.array([t["block_no"][0].as_py()] * len(k), pa.int32()), "k": pa.array(k, pa.int32()), "grouping": pa.array(g, pa.string()), "silhouette": pa.array(s, pa.float64()), "n": pa.array(n, pa.int64())})

    return spread(streams, "batch_id", "block_no").groupBy("batch_id", "block_no").applyInArrow(run, "batch_id bigint, block_no int, k int, grouping string, silhouette double, n bigint")


def throughput(spark: SparkSession, sf_dir: str, name: str = "meter_grid", first: str = "gaussian_ac", cfg: Config = Config()) -> DataFrame:
    """(batch_id, block_no, step, n, seconds): time of each step of the chain, forth and back, over the words of a batch."""

    def run(t: pa.Table) -> pa.Table:
        order = np.argsort(t["stream_id"].to_numpy())
        ids, words = t["stream_id"].to_numpy()[order], [rows_of(t["words"])[i].astype(np.int64) for i in order]
        spent, clock = {}, time.perf_counter

        def timed(step, f, *args):
            began = clock()
            out = f(*args)
            spent[step] = spent.get(step, 0.0) + clock() - began
            return out

        c = cfg.but(k=min(cfg.k, len(ids)))
        labels = timed("group", group_labels, ids, words, c, t["batch_id"][0].as_py())
        for label in np.unique(labels):
            own = [words[i] for i in np.flatnonzero(labels == label)]
            x = timed("interleave and difference", stages, own, c.but(bwt=None, mtf=False, rle=None))["delta"]
            last, primary = timed("block sort", bwt, x)
            ranks, alphabet = timed("move to front", mtf, last)
            runs = timed("run lengths", rle_dynamic, ranks)
            coded = [timed("arithmetic coding", ac_encode, part) for part in (runs[2:] if runs[0] else runs[2:3])]
            parts = [timed("arithmetic decoding", ac_decode, *part)[0] for part in coded]
            back = timed("run lengths back", rle_dynamic_inverse, runs[0], runs[1], parts[0], parts[1] if runs[0] else np.empty(0))
            timed("block sort back", bwt_inverse, timed("move to front back", mtf_inverse, back, alphabet), primary)
        n = sum(map(len, words))
        return pa.table({"batch_id": pa.array([t["batch_id"][0].as_py()] * len(spent), pa.int64()), "block_no": pa.array([t["block_no"][0].as_py()] * len(spent), pa.int32()), "step": pa.array(list(spent)), "n": pa.array([n] * len(spent), pa.int64()), "seconds": pa.array(list(spent.values()))})

    streams = batch_by_rank(streams_of(spark, sf_dir, name, first))
    return spread(streams, "batch_id", "block_no").groupBy("batch_id", "block_no").applyInArrow(run, "batch_id bigint, block_no int, step string, n bigint, seconds double")


def throughput_by_step(timed: DataFrame) -> DataFrame:
    """(step, n, seconds, core_us_a_word, mb_a_core_second): words are 16 bits."""
    sums = timed.groupBy("step").agg(F.sum("n").alias("n"), F.sum("seconds").alias("seconds"))
    return sums.select("step", "n", F.round("seconds", 3).alias("seconds"), F.round(F.col("seconds") / F.col("n") * 1e6, 3).alias("core_us_a_word"), F.round(F.col("n") * 2e-6 / F.col("seconds"), 3).alias("mb_a_core_second"))


ABLATIONS = {"none": {}, "cluster": {"grouping": "random"}, "interleave": {"layout": "concat"}, "delta": {"delta_order": 0}, "delta in streams": {"delta_scope": "stream"}, "bwt": {"bwt": None}, "mtf": {"mtf": False, "rle": None}, "rle": {"rle": None}, "arithmetic": {"coder": "huffman"}, "static model": {"coder": "adaptive"}, "all but coder": {"grouping": "none", "layout": "concat", "delta_order": 0, "bwt": None, "mtf": False, "rle": None}}


def ablation(spark: SparkSession, sf_dir: str, name: str = "meter_grid", first: str = "gaussian_ac", base: Config = Config()) -> DataFrame:
    """(dropped, cr_total, cr_payload): one step left out, or replaced, at a time. mtf goes with run lengths of signed symbols."""
    streams = batch_by_rank(streams_of(spark, sf_dir, name, first))
    return _all([compression_ratio(recompress(streams, base.but(**change))).select(F.lit(what).alias("dropped"), "cr_total", "cr_payload") for what, change in ABLATIONS.items()])


def scaling(spark: SparkSession, sf_dir: str, name: str = "meter_grid", sizes=(8, 16, 32, 56, 112), lengths=(256, 512, 1024, 1440), first: str = "gaussian_ac", k: int = 4, grouping: str = "kmeans") -> DataFrame:
    """(batch_size, block_len, cr_total, cr_payload, seconds): how many streams and how many samples go together."""
    out = []
    for length in lengths:
        streams = kept(first_stage(blocks_of(spark, sf_dir, name, length), first), "streams")
        ranked = kept(batch_by_rank(streams, 1).withColumnRenamed("batch_id", "rank"), "ranked")
        for size in sizes:
            batched = ranked.withColumn("batch_id", F.floor(F.col("rank") / size).cast("bigint")).drop("rank")
            few = batched.groupBy("batch_id", "block_no").count().where(F.col("count") < min(k, size)).drop("count")
            if few.limit(1).count():  # a short last batch has too few for k groups
                batched = batched.join(few, ["batch_id", "block_no"], "left_anti")
            began = time.time()
            r = compression_ratio(recompress(batched, Config(k=min(k, size), grouping=grouping))).first()
            out.append((size, length, r.cr_total, r.cr_payload, round(time.time() - began, 3)))
    return spark.createDataFrame(out, "batch_size int, block_len int, cr_total double, cr_payload double, seconds double")


def four_homes(spark: SparkSession, sf_dir: str, n: int = 4, first: str = "gaussian_ac") -> DataFrame:
    """(stream_id, series, pos, sym): the compressed words of n meters, and their readings after recovery."""
    from meterpack.plans.recompress import recover_readings

    streams = streams_of(spark, sf_dir, "meter_grid", first)
    ids = [r.stream_id for r in streams.select("stream_id").distinct().orderBy("stream_id").limit(n).collect()]
    own = streams.where(F.col("stream_id").isin(ids))
    words = own.select("stream_id", F.lit("compressed").alias("series"), F.posexplode("words").alias("pos", "sym"))
    packed = recompress(own.withColumn("batch_id", F.lit(0).cast("bigint")), Config(k=min(2, n)))
    back = recover_readings(packed, BLOCK_OF["meter_grid"])
    return words.select("stream_id", "series", "pos", F.col("sym").cast("bigint").alias("sym")).union(back.select("stream_id", F.lit("recovered"), "pos", "sym"))

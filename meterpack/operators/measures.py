"""Measures: entropy and its bounds, Silhouette, within-cluster squares, purity, losslessness."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from meterpack.operators.firststage import spread
from meterpack.operators.ranks import kept


def entropy(rows: DataFrame, *group: str) -> DataFrame:
    """(group, n, n_distinct, h, h_max): zero-order bits a symbol, from counts by symbol; two levels, the first partial."""
    counts = rows.groupBy(*group, "sym").agg(F.count(F.lit(1)).alias("c"))
    n = F.sum("c")
    h = F.log2(n) - F.sum(F.col("c") * F.log2("c")) / n
    return counts.groupBy(*group).agg(n.alias("n"), F.count(F.lit(1)).alias("n_distinct"), F.round(F.abs(h), 6).alias("h"), F.round(F.log2(F.count(F.lit(1))), 6).alias("h_max"))


def ideal_bits(rows: DataFrame, *group: str) -> DataFrame:
    """(group, bits): what an ideal coder with the sequence's own counts needs."""
    counts = rows.groupBy(*group, "sym").agg(F.count(F.lit(1)).alias("c"))
    n = F.sum("c")
    return counts.groupBy(*group).agg(F.round(F.abs(n * F.log2(n) - F.sum(F.col("c") * F.log2("c"))), 4).alias("bits"))


def dist2(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0).cast("bigint"), lambda s, x: s + x)


#: Numbers in a block of vectors that a task holds beside another, and rows.
BLOCK_CELLS, BLOCK_ROWS = 1 << 20, 2000


def _packed_block(t: pa.Table) -> pa.Table:
    """One row a block: ids, labels and numbers as bytes; numbers in the narrowest type that holds them."""
    x = t["vec"].combine_chunks()
    cells = x.values.to_numpy(zero_copy_only=False)[x.offsets[0].as_py() : x.offsets[-1].as_py()]
    most = int(np.abs(cells).max()) if len(cells) else 0
    kind = next((k for k in ("<i2", "<i4") if most <= np.iinfo(k).max), "<i8")
    labels = np.stack([t[c].to_numpy() for c in t.column_names[3:]], 1)
    row = {"block": t["block"][0].as_py(), "ids": t["stream_id"].to_numpy().astype("<i8").tobytes(), "labels": labels.astype("<i4").tobytes(), "kind": kind, "vecs": cells.astype(kind).tobytes()}
    return pa.Table.from_pylist([row], pa.schema([("block", pa.int32()), ("ids", pa.binary()), ("labels", pa.binary()), ("kind", pa.string()), ("vecs", pa.binary())]))


def distances(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Euclidean distances of integer rows; squares are exact: by one matrix product where its sums fit a double."""
    most = max((int(np.abs(m).max()) for m in (a, b) if m.size), default=0)
    if most * most * max(1, a.shape[1]) < 1 << 51:
        x, y = a.astype(np.float64), b.astype(np.float64)
        d = x @ y.T
        d *= -2
        d += (x * x).sum(1)[:, None]
        d += (y * y).sum(1)
    else:
        d = np.stack([((b.astype(np.int64) - row) ** 2).sum(1) for row in a.astype(np.int64)]).astype(np.float64)
    return np.sqrt(d, out=d)


def _block_sums(cells: list[tuple[int, int]]):
    """(stream_id, m0, m1, ...): sums of distances to the members of each cell (a labelling and a cluster of it), over the pairs of
    blocks of a task."""

    def unpack(row, side):
        ids, labels = np.frombuffer(row[f"{side}_ids"], "<i8"), np.frombuffer(row[f"{side}_labels"], "<i4")
        labels = labels.reshape(len(ids), -1)
        member = np.stack([labels[:, i] == c for i, c in cells], 1).astype(np.float64)
        return row[f"{side}_block"], ids, member, np.frombuffer(row[f"{side}_vecs"], row[f"{side}_kind"]).reshape(len(ids), -1)

    def run(batches):
        sums = {}
        for batch in batches:
            for row in (batch.slice(i, 1).to_pylist()[0] for i in range(len(batch))):
                (a, a_ids, a_in, x), (b, b_ids, b_in, y) = unpack(row, "a"), unpack(row, "b")
                d = distances(x, y)
                for block, ids, own in ((a, a_ids, d @ b_in), (b, b_ids, d.T @ a_in))[: 1 if a == b else 2]:
                    sums[block] = (ids, sums[block][1] + own if block in sums else own)
        for ids, own in sums.values():
            yield pa.RecordBatch.from_arrays([pa.array(ids), *(pa.array(c) for c in np.ascontiguousarray(own.T))], names=["stream_id", *(f"m{i}" for i in range(len(cells)))])

    return run


def silhouette(vectors: DataFrame, *labels: str) -> DataFrame:
    """(labelling, stream_id, cluster_id, s, s_piecewise): exact, by plain Euclidean distance of integer vectors (vec) of one length,
    for each labelling (column of cluster numbers; cluster_id alone if none is named); both algebraic forms. Alone in a group: 0;
    one group only: null; a single vector has no row. Every pair is measured once, for all labellings: blocks of vectors meet in
    tasks, which sum the distances to each cluster. Clusters are some hundreds at most."""
    spark, labels = vectors.sparkSession, labels or ("cluster_id",)
    vectors = kept(vectors.select("stream_id", "vec", *labels), "vectors")
    shape = vectors.agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.max(F.size("vec")), F.lit(1)).alias("d")).first()
    blocks = max(1, -(-shape.n // max(1, min(BLOCK_ROWS, BLOCK_CELLS // max(1, shape.d)))))
    sizes = {(i, r[0]): r[1] for i, c in enumerate(labels) for r in vectors.groupBy(c).count().collect()} or {(i, 0): 1 for i in range(len(labels))}
    cells = sorted(sizes)
    dealt = vectors.select(F.pmod(F.xxhash64("stream_id"), F.lit(blocks)).cast("int").alias("block"), "stream_id", "vec", *(F.col(c).cast("int").alias(f"label_{i}") for i, c in enumerate(labels)))
    packed = kept(spread(dealt, "block").groupBy("block").applyInArrow(_packed_block, "block int, ids binary, labels binary, kind string, vecs binary"), "blocks")
    tasks = min(blocks, max(1, math.isqrt(4 * spark.sparkContext.defaultParallelism)))
    side = lambda s: packed.repartition(tasks, "block").select(*(F.col(c).alias(f"{s}_{c}") for c in packed.columns))
    pairs = side("a").hint("shuffle_replicate_nl").crossJoin(side("b")).where("a_block <= b_block")
    sums = pairs.mapInArrow(_block_sums(cells), ", ".join(["stream_id bigint", *(f"m{i} double" for i in range(len(cells)))]))
    sums = sums.groupBy("stream_id").agg(*(F.sum(f"m{i}").alias(f"m{i}") for i in range(len(cells)))).where(F.lit(shape.n > 1))
    sums = sums.join(vectors.select(F.col("stream_id").alias("of"), *(F.col(c).alias(f"label_{i}") for i, c in enumerate(labels))), F.col("stream_id") == F.col("of"))
    each = []
    for i, name in enumerate(labels):
        own = [(F.col(f"label_{i}") == c, F.col(f"m{j}"), sizes[at, c]) for j, (at, c) in enumerate(cells) if at == i]
        x = F.coalesce(*(F.when(same & F.lit(n > 1), m / max(1, n - 1)) for same, m, n in own)) if own else F.lit(None).cast("double")
        y = F.array_min(F.array(*(F.when(~same, m / n) for same, m, n in own)))
        each.append(F.struct(F.lit(name).alias("labelling"), F.col(f"label_{i}").alias("cluster_id"), x.alias("x"), y.alias("y")))
    xy = sums.select("stream_id", F.explode(F.array(*each)).alias("e")).select("e.labelling", "stream_id", "e.cluster_id", "e.x", "e.y")
    ratio = (F.col("y") - F.col("x")) / F.nullif(F.greatest("x", "y"), F.lit(0.0))
    pieces = F.when(F.col("x") < F.col("y"), 1 - F.col("x") / F.col("y")).when(F.col("x") == F.col("y"), 0.0).otherwise(F.col("y") / F.col("x") - 1)
    tidy = lambda c: F.when(F.col("y").isNull(), None).when(F.col("x").isNull(), 0.0).otherwise(F.round(F.coalesce(c, F.lit(0.0)), 6))
    return xy.select("labelling", "stream_id", "cluster_id", tidy(ratio).alias("s"), tidy(pieces).alias("s_piecewise"))


def simplified_silhouette(assigned: DataFrame, centers: DataFrame) -> DataFrame:
    """s by distances to centres instead of members, for tables where pairs are too many. centers: at most some hundreds
    of rows (cluster_id, centroid)."""
    far = assigned.crossJoin(F.broadcast(centers.select(F.col("cluster_id").alias("c_id"), "centroid")))
    d = F.sqrt(F.aggregate(F.zip_with("vec", "centroid", lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, x: s + x))
    xy = far.groupBy("stream_id", "cluster_id").agg(F.max(F.when(F.col("c_id") == F.col("cluster_id"), d)).alias("x"), F.min(F.when(F.col("c_id") != F.col("cluster_id"), d)).alias("y"))
    return xy.withColumn("s", F.round((F.col("y") - F.col("x")) / F.greatest("x", "y"), 6))


def wcss(assigned: DataFrame, *group: str) -> DataFrame:
    return assigned.groupBy(*group).agg(F.sum("dist2").alias("wcss"))


def purity(labelled: DataFrame) -> DataFrame:
    """(cluster_id, label, n): the contingency of clusters and true labels."""
    return labelled.groupBy("cluster_id", "label").agg(F.count(F.lit(1)).alias("n"))


def adjusted_rand(labelled: DataFrame) -> DataFrame:
    """One row: the adjusted Rand index of cluster_id against label."""
    cells = purity(labelled)
    two = lambda c: F.col(c) * (F.col(c) - 1) / 2
    total = cells.agg(F.sum("n").alias("n"), F.sum(two("n")).alias("both"))
    rows = cells.groupBy("cluster_id").agg(F.sum("n").alias("n")).agg(F.sum(two("n")).alias("a"))
    columns = cells.groupBy("label").agg(F.sum("n").alias("n")).agg(F.sum(two("n")).alias("b"))
    all_ = total.crossJoin(rows).crossJoin(columns)  # one row each
    chance = F.col("a") * F.col("b") / two("n")
    return all_.select(F.round((F.col("both") - chance) / ((F.col("a") + F.col("b")) / 2 - chance), 6).alias("ari"))


def lossless(source: DataFrame, recovered: DataFrame) -> DataFrame:
    """Rows of either side that the other lacks: empty if nothing was lost."""
    names = source.columns
    recovered = recovered.select(*names)
    return source.exceptAll(recovered).withColumn("side", F.lit("source")).union(recovered.exceptAll(source).withColumn("side", F.lit("recovered")))

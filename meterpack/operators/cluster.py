"""k-means in DataFrame expressions over integer vectors, exact enough for another engine to repeat; a driver loop for
tables of any size; MLlib's for comparison."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from meterpack.operators.measures import dist2
from meterpack.operators.ranks import kept


def padded(rows: DataFrame, *carry: str) -> DataFrame:
    """Integer vectors of streams, padded with zeros to the longest: (stream_id, vec)."""
    cells = rows.groupBy("stream_id", *carry).agg(F.array_sort(F.collect_list(F.struct("pos", "sym"))).alias("x"))
    longest = cells.agg(F.max(F.size("x")).alias("d"))
    return cells.crossJoin(F.broadcast(longest)).select("stream_id", *carry, F.concat(F.col("x.sym"), F.array_repeat(F.lit(0).cast("bigint"), F.col("d") - F.size("x"))).alias("vec"))


def draw(r: int, seed: int, batch: str = "0"):
    return F.conv(F.substring(F.md5(F.lit(f"{batch}:{seed}:{r}")), 1, 12), 16, 10).cast("bigint")


def seed_rows(vectors: DataFrame, k: int, seed: int) -> DataFrame:
    """(cluster_id, stream_id, vec): the first by least md5, each next by a draw weighted with squared distance. The sums of
    ranges of ids say which range a draw falls in, and running weights are taken in that one only. Where every vector is a
    seed already, there are no more."""
    ranged = vectors.select("stream_id", "vec").repartitionByRange("stream_id").withColumn("__mp_range", F.spark_partition_id())
    vectors = kept(ranged, "vectors")
    first = vectors.orderBy(F.md5(F.concat(F.col("stream_id").cast("string"), F.lit(f":{seed}:0")))).limit(1)
    seeds = first.select(F.lit(0).alias("cluster_id"), "stream_id", "vec")
    for r in range(1, k):
        seeds = kept(seeds, "seeds")
        every = seeds.agg(F.collect_list("vec").alias("centers"))  # k rows at most, as one
        near = vectors.crossJoin(F.broadcast(every)).select("stream_id", "vec", "__mp_range", F.array_min(F.transform("centers", lambda c: dist2(F.col("vec"), c))).alias("w"))
        before = Window.orderBy("__mp_range").rowsBetween(Window.unboundedPreceding, -1)  # one row a range
        sums = near.groupBy("__mp_range").agg(F.sum("w").alias("own"))
        sums = sums.select("__mp_range", "own", F.coalesce(F.sum("own").over(before), F.lit(0)).alias("before"), F.sum("own").over(Window.partitionBy()).alias("all"))
        there = sums.withColumn("at", F.pmod(draw(r, seed), F.nullif(F.col("all"), F.lit(0))) - F.col("before")).where("at >= 0 and at < own").select("__mp_range", "at")
        inside = near.join(F.broadcast(there), "__mp_range")
        w = Window.partitionBy("__mp_range").orderBy("stream_id").rowsBetween(Window.unboundedPreceding, 0)
        hit = inside.withColumn("upto", F.sum("w").over(w)).where("upto > at").orderBy("stream_id").limit(1)
        seeds = seeds.union(hit.select(F.lit(r), "stream_id", "vec"))
    return seeds


def assign(vectors: DataFrame, centers: DataFrame) -> DataFrame:
    """(stream_id, cluster_id, dist2, vec); ties to the lower cluster. centers: (cluster_id, centroid), k rows."""
    every = centers.agg(F.collect_list(F.struct("cluster_id", "centroid")).alias("centers"))
    d = lambda c: F.aggregate(F.zip_with("vec", c["centroid"], lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, x: s + x)
    best = F.array_min(F.transform("centers", lambda c: F.struct(d(c).alias("dist2"), c["cluster_id"].alias("cluster_id"))))
    out = vectors.crossJoin(F.broadcast(every)).withColumn("best", best)  # map-only: the centres are one row
    return out.select("stream_id", F.col("best.cluster_id").alias("cluster_id"), F.col("best.dist2").alias("dist2"), "vec")


def update(assigned: DataFrame) -> DataFrame:
    """(cluster_id, centroid): means by component, from exact sums."""
    each = assigned.select("cluster_id", F.posexplode("vec").alias("dim", "x"))
    means = each.groupBy("cluster_id", "dim").agg((F.sum("x").cast("double") / F.count(F.lit(1))).alias("m"))
    return means.groupBy("cluster_id").agg(F.array_sort(F.collect_list(F.struct("dim", "m"))).alias("c")).select("cluster_id", F.col("c.m").alias("centroid"))


def as_centers(seeds: DataFrame) -> DataFrame:
    return seeds.select("cluster_id", F.transform("vec", lambda x: x.cast("double")).alias("centroid"))


def lloyd(vectors: DataFrame, centers: DataFrame, max_iter: int = 50) -> tuple[DataFrame, DataFrame, list[float]]:
    """(assigned, centers, within-cluster squares by round) for a table of any size: each round ships k centres to the
    data and k * d sums back, and starts from numbers, so that plans do not grow. An empty cluster keeps its centre."""
    vectors = kept(vectors.select("stream_id", "vec"), "vectors")
    spark, trace, last = vectors.sparkSession, [], None
    now = {r.cluster_id: r.centroid for r in centers.collect()}
    for _ in range(max_iter):
        table = spark.createDataFrame(sorted(now.items()), "cluster_id int, centroid array<double>")
        assigned = kept(assign(vectors, table), "lloyd")
        marks = assigned.agg(F.sum("dist2").alias("w"), F.sum(F.xxhash64("stream_id", "cluster_id").cast("decimal(38,0)")).alias("h")).first()
        trace.append(marks.w)
        if marks.h == last:
            break
        last = marks.h
        now |= {r.cluster_id: r.centroid for r in update(assigned).collect()}
    return assigned, table, trace


def race_seeds(vectors: DataFrame, k: int, seed: int) -> DataFrame:
    """Seeding for a table of any size: one aggregate a round picks the row with the least exponential arrival time at a
    rate of its squared distance, which is the weighted draw without running sums."""
    vectors = kept(vectors.select("stream_id", "vec"), "vectors")
    seeds = kept(seed_rows(vectors, 1, seed), "seeds")
    for r in range(1, k):
        u = (F.conv(F.substring(F.md5(F.concat(F.col("stream_id").cast("string"), F.lit(f":{seed}:{r}"))), 1, 12), 16, 10).cast("double") + 1) / float(1 << 48)
        every = seeds.agg(F.collect_list("vec").alias("centers"))
        near = vectors.crossJoin(F.broadcast(every)).select("stream_id", "vec", F.array_min(F.transform("centers", lambda c: dist2(F.col("vec"), c))).alias("w"))
        hit = near.where("w > 0").agg(F.min_by(F.struct("stream_id", "vec"), -F.ln(u) / F.col("w")).alias("s")).where("s is not null")
        seeds = kept(seeds.union(hit.select(F.lit(r), "s.stream_id", "s.vec")), "seeds")
    return seeds


def mllib(vectors: DataFrame, k: int, seed: int = 42) -> DataFrame:
    """(stream_id, cluster_id) by MLlib's k-means||."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    x = vectors.select("stream_id", array_to_vector(F.transform("vec", lambda v: v.cast("double"))).alias("features"))
    model = KMeans(k=k, seed=seed, initMode="k-means||").fit(x)
    return model.transform(x).select("stream_id", F.col("prediction").alias("cluster_id"))

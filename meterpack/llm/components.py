"""Connected components of a link table, by rounds of joins and minima; nothing is gathered on the driver but two numbers
a round."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from meterpack.llm.common import staged


def _settle(edges: DataFrame) -> tuple[DataFrame, tuple]:
    out = staged(edges.where("u <> v").distinct(), "links")
    marks = out.agg(F.count(F.lit(1)).alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("h")).first()
    return out, (marks.n, marks.h)


def components(links: DataFrame) -> DataFrame:
    """(id, component) for every id in links (a, b): component is the smallest id it reaches.

    Large-star and small-star steps in turn: every round each id passes its neighbours on to its smallest one, and a
    component is a star after about log(n) rounds. A hub with very many neighbours is a skewed join, not a gathered list."""
    edges, state = _settle(links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")))
    while True:
        both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.col("u"), F.min("v")).alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = large.where("u <> v").distinct()
        low = large.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
        least = low.groupBy("u").agg(F.min("v").alias("m"))
        small = low.join(least, "u").select(F.explode(F.array(F.struct(F.col("v").alias("u"), F.col("m").alias("v")), F.struct("u", F.col("m").alias("v")))).alias("e")).select("e.*")
        edges, new = _settle(small)
        if new == state:
            break
        state = new
    return edges.select(F.col("u").alias("id"), F.col("v").alias("component")).union(edges.select(F.col("v").alias("id"), F.col("v").alias("component")).distinct())

"""The chain's steps over long rows (group columns, gpos, sym), as DataFrame expressions with no Python in them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def interleave(rows: DataFrame, *group: str) -> DataFrame:
    """gpos: first element of every stream of the group, then the second elements, and so on."""
    w = Window.partitionBy(*group).orderBy("pos", "stream_id")
    return rows.withColumn("gpos", F.row_number().over(w) - 1)


def concatenate(rows: DataFrame, *group: str) -> DataFrame:
    """gpos: stream after stream."""
    w = Window.partitionBy(*group).orderBy("stream_id", "pos")
    return rows.withColumn("gpos", F.row_number().over(w) - 1)


def delta(rows: DataFrame, *group: str, order: str = "gpos", times: int = 1) -> DataFrame:
    """sym minus the sym before it; the first of a group stays, so that running sums undo it."""
    w = Window.partitionBy(*group).orderBy(order)
    for _ in range(times):
        rows = rows.withColumn("sym", F.col("sym") - F.coalesce(F.lag("sym").over(w), F.lit(0).cast("bigint")))
    return rows


def undelta(rows: DataFrame, *group: str, order: str = "gpos", times: int = 1) -> DataFrame:
    w = Window.partitionBy(*group).orderBy(order).rowsBetween(Window.unboundedPreceding, 0)
    for _ in range(times):
        rows = rows.withColumn("sym", F.sum("sym").over(w))
    return rows


def runs(rows: DataFrame, *group: str, order: str = "gpos") -> DataFrame:
    """(group, run_no, sym, len) of the maximal runs."""
    w = Window.partitionBy(*group).orderBy(order)
    before = F.lag("sym").over(w)
    marked = rows.withColumn("head", F.when(before.isNull() | (before != F.col("sym")), 1).otherwise(0))
    numbered = marked.withColumn("run_no", F.sum("head").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return numbered.groupBy(*group, "run_no").agg(F.first("sym").alias("sym"), F.count(F.lit(1)).alias("len"))


def bit_width(c: Column) -> Column:
    """Bits of a non-negative integer, one at least."""
    return F.greatest(F.lit(1), F.length(F.bin(c))).cast("bigint")


def dynamic_choice(run_rows: DataFrame, thresholds: tuple[int, ...], *group: str) -> DataFrame:
    """(group, off_bits, bits, t): the cheapest run threshold, t = 0 where leaving runs alone is no dearer. The few
    thresholds travel as an array in each run row and are summed in one aggregate."""
    width = run_rows.groupBy(*group).agg(bit_width(F.max("sym")).alias("b"), F.sum("len").alias("n"), *(bit_width(F.coalesce(F.max(F.when(F.col("len") >= t, F.col("len") - t)), F.lit(0))).alias(f"c{t}") for t in thresholds), *(F.sum(F.least("len", F.lit(t))).alias(f"s{t}") for t in thresholds), *(F.count_if(F.col("len") >= t).alias(f"k{t}") for t in thresholds))
    options = F.array(*(F.struct((F.col(f"s{t}") * F.col("b") + F.col(f"k{t}") * F.col(f"c{t}")).alias("bits"), F.lit(t).alias("t")) for t in thresholds))
    best = width.select(*group, (F.col("n") * F.col("b")).alias("off_bits"), F.array_min(options).alias("best"))
    pays = F.col("best.bits") < F.col("off_bits")
    return best.select(*group, "off_bits", F.when(pays, F.col("best.bits")).otherwise(F.col("off_bits")).alias("bits"), F.when(pays, F.col("best.t")).otherwise(0).cast("int").alias("t"))


def mtf_ranks(cells: DataFrame, x: str = "x") -> DataFrame:
    """cells with `ranks`: each symbol's place in a list that begins as the sorted alphabet and moves every symbol read to its
    front. A fold over the array, for cells of a bounded block."""
    start = F.struct(F.array_sort(F.array_distinct(x)).alias("line"), F.array().cast("array<bigint>").alias("ranks"))

    def step(acc: Column, sym: Column) -> Column:
        line = F.concat(F.array(sym), F.array_remove(acc["line"], sym))
        return F.struct(line.alias("line"), F.array_append(acc["ranks"], F.array_position(acc["line"], sym) - 1).alias("ranks"))

    return cells.withColumn("ranks", F.aggregate(x, start, step, lambda acc: acc["ranks"]))


def cumulative(rows: DataFrame, *group: str) -> DataFrame:
    """(group, sym, freq, cum, total): integer counts and the counts of all smaller symbols."""
    counts = rows.groupBy(*group, "sym").agg(F.count(F.lit(1)).alias("freq"))
    w = Window.partitionBy(*group).orderBy("sym").rowsBetween(Window.unboundedPreceding, 0)
    return counts.select(*group, "sym", "freq", (F.sum("freq").over(w) - F.col("freq")).alias("cum"), F.sum("freq").over(Window.partitionBy(*group)).alias("total"))


def rotations(cells: DataFrame, x: str = "x") -> DataFrame:
    """last, primary (from 1) of short arrays by sorting all rotations: a twin of the kernel for blocks of some dozens."""
    n = F.size(x)
    rows = F.transform(F.sequence(F.lit(1), n), lambda i: F.struct(F.concat(F.slice(x, i, n), F.slice(x, 1, i - 1)).alias("rot"), i.alias("i")))
    ordered = F.array_sort(rows)
    return cells.withColumn("last", F.transform(ordered, lambda r: F.element_at(r["rot"], -1))).withColumn("primary", F.array_position(F.transform(ordered, lambda r: r["i"]), 1))


def bwt_distributed(rows: DataFrame) -> tuple[DataFrame, int]:
    """(row, last) of one sequence (gpos, sym) too large for a task, and the row of the original.

    Prefix doubling: each round ranks positions by their own rank and that 2**j further on. A rank is a range-partitioned
    sort with offsets, never a single task; rounds are written to the shared folder, so that plans stay small."""
    from meterpack.operators.ranks import dense_ranks, kept

    n = rows.count()
    ranked = kept(dense_ranks(rows.select("gpos", "sym"), "sym"), "bwt")
    step = 1
    while step < n and ranked.agg(F.max("rank")).first()[0] < n - 1:
        ahead = ranked.select(F.pmod(F.col("gpos") - step, F.lit(n)).alias("gpos"), F.col("rank").alias("next"))
        ranked = kept(dense_ranks(ranked.join(ahead, "gpos"), "rank", "next").drop("next"), "bwt")
        step *= 2
    placed = kept(dense_ranks(ranked, "rank", "gpos"), "bwt")
    before = rows.select(F.pmod(F.col("gpos") + 1, F.lit(n)).alias("gpos"), F.col("sym").alias("last"))
    primary = placed.where("gpos = 0").first()["rank"] if n else 0
    return placed.select("gpos", F.col("rank").alias("row")).join(before, "gpos").select("row", "last"), primary

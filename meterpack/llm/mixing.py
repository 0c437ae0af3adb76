"""Mixing sources to target weights by Sainte-Laguë apportionment of equal-token blocks.

Each source's share of all words follows its weight, but never exceeds `most` times what the source has; the excess goes
round again. Blocks are dealt to sources by highest quotients, each source's blocks to its shards the same way, and every
shard takes its quota as whole rounds plus a seeded run of consecutive blocks of its seeded document order. So a document
is taken whole but for at most two in a shard. A source has a shard for every SHARD_WORDS words, so that one with a third of
all rows is many tasks. Sources are planned where they are, by sums over their table: the driver gets a few numbers only.

Contract for odd input: a null text has no words; a null source is a source of its own, last; sources without words get
no target; repeated rows are told apart by place in the order only and taken one by one; an empty table gives no rows;
columns of any name pass through.
"""

from __future__ import annotations

import hashlib
import heapq
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from meterpack.llm.common import staged
from meterpack.operators.ranks import dense_ranks

BLOCK = 16
#: Words of a shard, more or less.
SHARD_WORDS = 1 << 21
MOST = 3


def _won(weights: np.ndarray, caps: np.ndarray, quotient: float) -> np.ndarray:
    """Seats of each party whose quotients lie above this one."""
    return np.minimum(caps, np.floor((weights / (quotient * (1 + 1e-12)) + 1) / 2)).astype(np.int64)


def apportion(weights: list[float], seats: int, caps: list[int]) -> list[int]:
    """Sainte-Laguë with ceilings: seats go one by one to the highest weight / (2 * seats so far + 1), to the first of equals.

    A quotient that few seats lie below is found by bisection; only these are dealt one by one."""
    w, c = np.array(weights, np.float64), np.array(caps, np.int64)
    c[w <= 0] = 0
    if int(c.sum()) <= seats:
        return c.tolist()
    out = np.zeros(len(w), np.int64)
    if seats <= 0:
        return out.tolist()
    low, high = float(w[c > 0].min()) / (2 * int(c.max()) + 1) / 2, float(w.max()) * 2
    while high > low * (1 + 1e-11):
        middle = math.sqrt(low * high)
        now = _won(w, c, middle)
        if int(now.sum()) <= seats:
            high, out = middle, now
        else:
            low = middle
    out = out.tolist()
    left = seats - sum(out)
    heap = [(-weights[i] / (2 * out[i] + 1), i) for i in range(len(out)) if out[i] < c[i]]
    heapq.heapify(heap)
    for _ in range(left):
        _, i = heapq.heappop(heap)
        out[i] += 1
        if out[i] < c[i]:
            heapq.heappush(heap, (-weights[i] / (2 * out[i] + 1), i))
    return out


#: Quotients that one pass over the parties tries, and seats that may be left to deal one by one.
TRIES, LEFT = 64, 4096


def apportion_table(parties: DataFrame, seats: int) -> DataFrame:
    """(party, seats) as apportion() deals them, for a table (party bigint, weight double, cap bigint) of any length: some
    passes of sums find a quotient that few seats lie below, and these are ranked."""
    parties = parties.select("party", F.col("weight"), F.when(F.col("weight") > 0, F.col("cap")).otherwise(0).alias("cap"))
    marks = parties.where("cap > 0").agg(F.sum("cap").alias("caps"), F.min("weight").alias("low"), F.max("weight").alias("high"), F.max("cap").alias("cap")).first()
    if seats <= 0 or (marks.caps or 0) <= seats:
        return parties.select("party", (F.col("cap") if seats > 0 else F.lit(0).cast("bigint")).alias("seats"))
    won = lambda q: F.least(F.col("cap"), F.floor((F.col("weight") / (q * (1 + 1e-12)) + 1) / 2)).cast("bigint")
    low, high = (marks.low / (2 * marks.cap + 1) / 2, marks.caps), (marks.high * 2, 0)
    while high[0] > low[0] * (1 + 1e-11) and low[1] - high[1] > LEFT:
        tries = [high[0] * (low[0] / high[0]) ** (j / TRIES) for j in range(1, TRIES)]
        found = [high, *zip(tries, parties.agg(*(F.sum(won(q)).alias(f"t{j}") for j, q in enumerate(tries))).first(), strict=True), low]
        cut = max(j for j, (_, n) in enumerate(found) if n <= seats)
        if (found[cut][0], found[cut + 1][0]) == (high[0], low[0]):
            break
        high, low = found[cut], found[cut + 1]
    below = parties.select("party", "weight", won(high[0]).alias("sure"), F.least("cap", won(low[0] / (1 + 1e-9)) + 1).alias("most"))
    next_ = below.where("sure < most").select("party", "weight", F.explode(F.sequence("sure", F.col("most") - 1)).alias("seat"))
    ranked = dense_ranks(next_.select("party", "seat", (-F.col("weight") / (2 * F.col("seat") + 1)).alias("q")), "q", "party", "seat")
    more = ranked.where(F.col("rank") < seats - high[1]).groupBy("party").agg(F.count(F.lit(1)).alias("more"))
    return below.join(more, "party", "left").select("party", (F.col("sure") + F.coalesce("more", F.lit(0))).alias("seats"))


def levelled(sizes: DataFrame, most: int) -> tuple[int, float]:
    """(words in all, the level): a source's target is its weight times the level, or most * size where that is less. sizes:
    (size, weight). Each pass adds the sources that the last level stopped; none when it is done."""
    total = sizes.agg(F.sum("size").alias("n")).first().n or 0
    level = 0.0
    while total:
        stopped = F.col("size") * most <= F.col("weight") * level
        cut, mass = sizes.where("size > 0").agg(F.coalesce(F.sum(F.when(stopped, F.col("size") * most)), F.lit(0)), F.coalesce(F.sum(F.when(~stopped, F.col("weight"))), F.lit(0))).first()
        new = (total - cut) / mass if mass else math.inf
        if new <= level:
            break
        level = new
    return total, level


def words_in(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def source_plan(sizes: DataFrame, block: int, most: int) -> DataFrame:
    """(key, source_size, target, quota, shards) from (key, source, size), one row a source."""
    ranked = dense_ranks(sizes.withColumn("__mp_null", F.col("source").isNull()), "__mp_null", "source").withColumn("weight", 1 + F.col("rank") % 3)
    ranked = staged(ranked.select("key", F.col("rank").alias("party"), "size", "weight"), "sources")
    total, level = levelled(ranked, most)
    target = F.when(F.col("size") > 0, F.least(F.col("size") * float(most), F.col("weight") * F.lit(level))).otherwise(0.0)
    aimed = ranked.withColumn("target", target)
    caps = aimed.select("party", F.col("target").alias("weight"), (most * F.floor((F.col("size") + block // 2) / block)).cast("bigint").alias("cap"))
    seats = staged(apportion_table(caps, (total + block // 2) // block), "quotas")
    out = aimed.join(seats, "party").select("key", F.col("size").alias("source_size"), "target", F.col("seats").alias("quota"), F.greatest(F.lit(1), F.ceil(F.col("size") / SHARD_WORDS)).cast("int").alias("shards"))
    return staged(out, "plan")


CELLS = "key string, shard int, cell_size bigint, rounds bigint, first bigint, length bigint"


def _cells(block: int, seed: int, most: int):
    """Of one source's shards (key, shard, n, quota): how many whole rounds each takes, and which run of its words."""

    def run(t: pa.Table) -> pa.Table:
        t = t.sort_by("shard")
        key, quota = t["key"][0].as_py(), t["quota"][0].as_py()
        sizes = t["n"].to_pylist()
        blocks = [max(1, (n + block // 2) // block) if n else 0 for n in sizes]
        shares = apportion([float(n) for n in sizes], quota, [most * b for b in blocks])
        out = []
        for shard, n, b, q in zip(t["shard"].to_pylist(), sizes, blocks, shares, strict=True):
            rounds, rest = divmod(q, b) if b else (0, 0)
            draw = int.from_bytes(hashlib.sha256(f"{seed}:{key}:{shard}".encode()).digest()[:8]) % b if b else 0
            edge = lambda j, n=n, b=b: j * n // b if b else 0
            stop = draw + rest
            out.append((key, shard, n, rounds, edge(draw), edge(stop) - edge(draw) if stop <= b else n - edge(draw) + edge(stop - b)))
        schema = pa.schema([("key", pa.string()), ("shard", pa.int32()), *((c, pa.int64()) for c in ("cell_size", "rounds", "first", "length"))])
        return pa.Table.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*out, strict=True), schema, strict=True)], schema=schema)

    return run


def mix(docs: DataFrame, block: int = BLOCK, seed: int = 0, most: int = MOST, doc_id: str = "doc_id", text: str = "text", source: str = "source", keep_rows: bool = False) -> DataFrame:
    """One row a document: doc_id, size, source_size, target, taken; with keep_rows its own columns too, as `row`.

    A cell is a shard of a source. The words before a document in its cell come from a window over the cell, and which of its
    words lie in the taken run is arithmetic, so blocks are never materialised."""
    body = F.coalesce(F.col(text), F.lit(""))
    order = F.md5(F.concat_ws(":", F.lit(str(seed)), F.coalesce(F.col(doc_id).cast("string"), F.lit("null")), F.crc32(body)))
    key = F.coalesce(F.concat(F.lit("="), F.col(source).cast("string")), F.lit("null"))
    own = [F.struct("*").alias("row")] if keep_rows else []
    rows = docs.select(*own, F.col(doc_id).alias("doc_id"), key.alias("key"), words_in(F.col(text)).alias("size"), order.alias("order"))
    if not keep_rows:
        rows = staged(rows, "mix")
    sizes = rows.groupBy("key").agg(F.sum("size").alias("size")).withColumn("source", F.when(F.col("key") != "null", F.substring("key", 2, 1 << 30)))
    plan = source_plan(sizes, block, most)
    rows = rows.join(plan, "key").withColumn("shard", F.pmod(F.conv(F.substring("order", 1, 8), 16, 10).cast("long"), F.col("shards")).cast("int"))
    cells = rows.groupBy("key", "shard").agg(F.sum("size").alias("n"), F.first("quota").alias("quota"))
    cells = staged(cells.groupBy("key").applyInArrow(_cells(block, seed, most), CELLS), "cells").hint("merge")
    upto = Window.partitionBy("key", "shard").orderBy("order", F.col("doc_id").asc_nulls_first()).rowsBetween(Window.unboundedPreceding, 0)
    joined = rows.withColumn("end", F.sum("size").over(upto)).join(cells, ["key", "shard"])
    start, stop = F.col("end") - F.col("size"), F.col("first") + F.col("length")
    zero = F.lit(0).cast("long")
    overlap = lambda lo, hi: F.greatest(zero, F.least(F.col("end"), hi) - F.greatest(start, lo))
    taken = F.col("rounds") * F.col("size") + overlap(F.col("first"), F.least(stop, F.col("cell_size"))) + overlap(zero, stop - F.col("cell_size"))
    return joined.select(*(["row"] if keep_rows else []), "doc_id", "size", "source_size", "target", taken.alias("taken"))


def take_mix(docs: DataFrame, **how) -> DataFrame:
    """The mix itself: each document as many times as its taken words make up, the last time where they are half of it
    or more. It has the columns of docs."""
    mixed = mix(docs, keep_rows=True, **how).where(F.col("size") > 0)
    times = F.floor((2 * F.col("taken") + F.col("size")) / (2 * F.col("size"))).cast("int")
    out = mixed.withColumn("__mp_times", times).where(F.col("__mp_times") > 0).select("row", F.explode(F.sequence(F.lit(1), F.col("__mp_times"))).alias("__mp_time"))
    return out.select(*(F.col("row")[c].alias(c) for c in docs.columns))

"""Sharding by jump consistent hashing, in DataFrame functions only.

A row's key is the first 64 bits of md5 over its id. Appending a shard moves about 1/(n+1) of the rows, all of them into
the new shard, and needs no ring table. Contract for odd input: a null id hashes as the word "null"; a null text counts no
bytes and has the checksum of the empty string; repeated rows keep one slot each; extra columns do no harm.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Multiplier of the 64-bit congruential step of jump hashing, as two 32-bit halves (fixed values).
STEP_HIGH, STEP_LOW = 0x27BB2EE6, 0x87B0B0FD
WORD = 0xFFFFFFFF
#: Steps of the loop that are laid out. It takes about ln(n) of them; over 160 has a chance below 1e-90 at a million shards.
MAX_STEPS = 160
#: Parts of a shard in which slots are counted on their own, so that no shard is numbered by one task.
SLOT_PARTS = 256


def _advance(hi: Column, lo: Column) -> tuple[Column, Column]:
    """key * step + 1 modulo 2**64 on 32-bit halves; every product stays below 2**63, so ANSI mode never raises."""
    low16, low_rest = lo.bitwiseAND(0xFFFF), F.shiftright(lo, 16)
    upper = low_rest * STEP_LOW
    total = low16 * STEP_LOW + F.shiftleft(upper.bitwiseAND(0xFFFF), 16) + 1
    carry = F.shiftright(upper, 16) + F.shiftright(total, 32)
    cross = (hi.bitwiseAND(0xFFFF) * STEP_LOW + F.shiftleft((F.shiftright(hi, 16) * STEP_LOW).bitwiseAND(0xFFFF), 16)).bitwiseAND(WORD)
    return (carry + (lo * STEP_HIGH).bitwiseAND(WORD) + cross).bitwiseAND(WORD), total.bitwiseAND(WORD)


def jump_shards(hi: Column, lo: Column, n: int) -> Column:
    """struct(shard, grown): the shard of a 64-bit key among n and among n + 1 shards, from one walk."""
    if n < 1:
        raise ValueError("a sharding needs at least one shard")

    def step(s: Column, _: Column) -> Column:
        ahead = F.floor((s["grown"] + 1).cast("double") * (F.lit(float(1 << 31)) / (F.shiftright(s["hi"], 1) + 1).cast("double")))
        new_hi, new_lo = _advance(s["hi"], s["lo"])
        moved = F.struct(new_hi.alias("hi"), new_lo.alias("lo"), F.when(ahead < n, ahead).otherwise(s["shard"]).alias("shard"), ahead.alias("grown"))
        return F.when(ahead <= n, moved).otherwise(s)

    start = F.struct(hi.alias("hi"), lo.alias("lo"), F.lit(-1).cast("long").alias("shard"), F.lit(-1).cast("long").alias("grown"))
    end = F.aggregate(F.sequence(F.lit(1), F.lit(min(n + 1, MAX_STEPS))), start, step)
    return F.transform(F.array(end), lambda e: F.struct(e["shard"].cast("int").alias("shard"), e["grown"].cast("int").alias("grown")))[0]


def md5_half(c: Column, at: int) -> Column:
    return F.conv(F.substring(F.md5(c), at, 8), 16, 10).cast("long")


def shard_of(key: Column, n: int) -> Column:
    """The same for a key of any type, by its md5."""
    text = F.coalesce(key.cast("string"), F.lit("null"))
    return jump_shards(md5_half(text, 1), md5_half(text, 9), n)


def shard_documents(docs: DataFrame, n: int, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """One row a document: doc_id, size, text_crc32, law, shard, slot, grown_shard.

    Shards are a map-only expression. Slots run from 0 without gaps in each shard, by (part, doc_id, size, checksum): rows
    equal in all three are counted together before the shuffle, parts are numbered on their own, and the offsets of the
    n * SLOT_PARTS parts are joined in."""
    body = F.coalesce(F.col(text), F.lit(""))
    rows = docs.select(F.col(doc_id).alias("doc_id"), (F.octet_length(body) + 8).cast("long").alias("size"), F.crc32(body).alias("text_crc32"))
    name = F.concat_ws(":", F.coalesce(F.col("doc_id").cast("string"), F.lit("null")), F.col("size"), F.col("text_crc32"))
    alike = rows.groupBy("doc_id", "size", "text_crc32").agg(F.count(F.lit(1)).alias("n"))
    placed = alike.withColumn("at", shard_of(F.col("doc_id"), n)).select("*", F.col("at.shard").alias("shard"), F.col("at.grown").alias("grown_shard"), F.pmod(md5_half(name, 1), F.lit(SLOT_PARTS)).alias("part")).drop("at")
    inside = Window.partitionBy("shard", "part").orderBy(F.col("doc_id").asc_nulls_first(), "size", "text_crc32")
    numbered = placed.withColumn("start", F.sum("n").over(inside.rowsBetween(Window.unboundedPreceding, 0)) - F.col("n"))
    sizes = placed.groupBy("shard", "part").agg(F.sum("n").alias("rows"))
    before = Window.partitionBy("shard").orderBy("part").rowsBetween(Window.unboundedPreceding, 0)
    offsets = sizes.select("shard", "part", (F.sum("rows").over(before) - F.col("rows")).alias("offset"))
    slots = numbered.join(F.broadcast(offsets), ["shard", "part"])  # at most n * SLOT_PARTS rows
    first = F.col("offset") + F.col("start")
    return slots.select("doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard", F.explode(F.sequence(first, first + F.col("n") - 1)).alias("slot"), "grown_shard")

"""Near-duplicates by bottom-k sketches from one hash function.

A document's set is its five-word shingles as 64-bit hashes in rising order; its first K are the sketch. Documents of
equal sets collapse first. Inverted lists hold, of each sketch, only its rarest values: two sketches that share as many
values as links of the threshold must share are bound to meet in such a list. Lists with the same hub (the member with
the fewest values of its own) form one group. In a group every member is compared with the hub; then members that ended
up in another component than the hub are compared with all, block against block. A comparison estimates by the sketch of
the union and confirms on the full sets. So a group of near copies costs one comparison a member, and no link is lost to
a cap: for sets above K shingles the sketches meet with a chance of error below 1e-5 for a pair just at the threshold,
and smaller sets are treated exactly.

Contract for odd input: a null or empty text has an empty set, is linked with nothing and is kept; rows of equal text
are one group; rows that repeat an id share its component; on an empty table the result is empty.
"""

from __future__ import annotations

import hashlib
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from meterpack.llm.common import CHUNK_ROWS, FOLD, byte_chunks, small_batches, staged, trim, window_hashes, word_hashes
from meterpack.llm.components import components
from meterpack.operators.firststage import spread

SHINGLE = 5
#: The least similarity of a link, in percent, unless a caller names another.
PERCENT = 85
K = 96
#: Standard deviations by which a sketch may fall short of its mean before a pair at the threshold is missed.
SLACK = 4.5
#: Of one side of a comparison block: documents, and shingles of all its documents together.
BLOCK_DOCS, BLOCK_SHINGLES = 1024, 1_000_000


def shingle_sets(texts: list[bytes | None], size: int = SHINGLE) -> list[np.ndarray]:
    words = [t.translate(FOLD).split() if t else [] for t in texts]
    flat, at, out = word_hashes([w for ws in words for w in ws]), 0, []
    for ws in words:
        h = flat[at : at + len(ws)]
        at += len(ws)
        out.append(np.unique(window_hashes(h, min(size, len(ws)))) if len(ws) else np.empty(0, np.uint64))
    return out


def least_shared(n: int, percent: int = PERCENT, k: int = K) -> int:
    """Values that the sketch of a set of n shares at least with the sketch of any set linked to it."""
    j = percent / 100
    apart = (1 - j) / j * n  # at most so many shingles are in one of the two sets alone
    if n <= k:
        return max(1, min(math.ceil(j * n - 1e-9), math.ceil(k - apart - 1e-9)))
    return max(1, math.ceil(k - apart), math.floor(j * k - SLACK * math.sqrt(k * j * (1 - j))))


def _sketcher(percent: int):
    def run(batches):
        for batch in batches:
            ids = batch.column(0)
            for k, chunk in enumerate(byte_chunks(batch.column(1))):
                sets = shingle_sets(chunk)
                keys = [hashlib.blake2b(s.tobytes(), digest_size=16).digest() if len(s) else None for s in sets]
                tops = [min(len(s), K) - least_shared(len(s), percent) + 1 if len(s) else 0 for s in sets]
                n = pa.array([len(s) for s in sets], pa.int64())
                arrays = [ids.slice(k * CHUNK_ROWS, CHUNK_ROWS), n, pa.array(keys, pa.binary()), listed([s[:K] for s in sets])[1], pa.array(tops, pa.int32())]
                yield pa.RecordBatch.from_arrays(arrays, names=["id", "n", "key", "sketch", "prefix"])
        trim()

    return run


def sketches(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", percent: int = PERCENT) -> DataFrame:
    """(id, n, key, sketch, prefix): size and fingerprint of the set, its K least hashes, how many of the rarest of them
    go into lists."""
    small_batches(docs.sparkSession)
    rows = docs.select(F.col(doc_id).cast("bigint").alias("id"), F.col(text).alias("text"))
    return rows.mapInArrow(_sketcher(percent), "id bigint, n bigint, key binary, sketch array<bigint>, prefix int")


def listed(sets: list[np.ndarray]) -> tuple[pa.Array, pa.Array]:
    """(sizes, sets) as Arrow columns, with one copy of the values."""
    sizes = np.fromiter(map(len, sets), np.int64, len(sets))
    offsets = np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32)
    values = np.concatenate(sets) if len(sets) else np.empty(0, np.uint64)
    return pa.array(sizes), pa.ListArray.from_arrays(pa.array(offsets), pa.array(values.view(np.int64)))


def _sets(batches):
    """Of neighbouring rows with one id the first."""
    last = None
    for batch in batches:
        ids = batch.column(0).to_numpy()
        first = np.append(ids[:1] != last, ids[1:] != ids[:-1])
        last = ids[-1] if len(ids) else last
        batch = batch.filter(pa.array(first))
        ids = batch.column(0)
        for k, chunk in enumerate(byte_chunks(batch.column(1))):
            yield pa.RecordBatch.from_arrays([ids.slice(k * CHUNK_ROWS, CHUNK_ROWS), *listed(shingle_sets(chunk))], names=["id", "n", "shingles"])
    trim()


def groups(reps: DataFrame) -> DataFrame:
    """(hub, id) over all inverted lists that hold two or more sets; the hub itself is among the ids.

    A value that only one sketch has takes up room among a document's rarest, but never travels."""
    each = reps.select("id", "prefix", F.size("sketch").alias("kept"), F.explode("sketch").alias("value"))
    # written, so that the joins meet plain tables and adaptive execution can split a hot value
    common = staged(each.groupBy("value").agg(F.count(F.lit(1)).alias("df")).where("df > 1"), "common")
    shared = each.join(common, "value").groupBy("id", "prefix", "kept").agg(F.array_sort(F.collect_list(F.struct("df", "value"))).alias("shared"))
    alone = F.col("kept") - F.size("shared")
    listed = shared.select("id", alone.alias("alone"), F.slice("shared", 1, F.greatest(F.lit(0), F.col("prefix") - alone)).alias("rare"))
    posts = staged(listed.where(F.size("rare") > 0).select("id", "alone", F.explode("rare.value").alias("value")), "postings")
    hubs = posts.groupBy("value").agg(F.min(F.struct("alone", "id")).alias("hub"), F.count(F.lit(1)).alias("members")).where("members > 1").select("value", F.col("hub.id").alias("hub"))
    return posts.join(staged(hubs, "hubs"), "value").select("hub", "id").distinct()


def estimate(a: np.ndarray, b: np.ndarray, k: int = K) -> float:
    """Jaccard similarity by the k least values of the union of two sets."""
    a, b = a[:k], b[:k]
    union = np.union1d(a, b)[:k]
    return np.count_nonzero(np.isin(union, a, assume_unique=True) & np.isin(union, b, assume_unique=True)) / max(1, len(union))


def least_estimate(percent: int) -> float:
    """An estimate below this rules a pair out; where both sets lie within their sketches it is exact."""
    j = percent / 100
    return j - SLACK * math.sqrt(j * (1 - j) / K)


def linked(a: np.ndarray, b: np.ndarray, percent: int = PERCENT) -> bool:
    if 100 * min(len(a), len(b)) < percent * max(len(a), len(b)) or estimate(a, b) < least_estimate(percent):
        return False
    both = len(np.intersect1d(a, b, assume_unique=True))
    return 100 * both >= percent * (len(a) + len(b) - both)


def _overlaps(left: list[np.ndarray], right: list[np.ndarray]) -> np.ndarray:
    """How many values each left sketch shares with each right one."""
    sides = []
    values = np.intersect1d(np.concatenate([s[:K] for s in left]), np.concatenate([s[:K] for s in right]))
    if not len(values):
        return np.zeros((len(left), len(right)), np.float32)
    for side in (left, right):
        table = np.zeros((len(side), len(values)), np.float32)
        for i, s in enumerate(side):
            at = np.searchsorted(values, s[:K])
            at[at == len(values)] = 0
            table[i, at[values[at] == s[:K]]] = 1
        sides.append(table)
    return sides[0] @ sides[1].T


def links_between(left: list[tuple], right: list[tuple], percent: int = PERCENT, step: int = 256) -> list[tuple[int, int]]:
    """Links between (id, component, set) rows of two sides, of different components only; of each left row and right
    component one link will do, since the component stays whole."""
    out = []
    need_r = np.array([least_shared(len(s), percent) for _, _, s in right])
    for at in range(0, len(left), step):
        part = left[at : at + step]
        need_l = np.array([least_shared(len(s), percent) for _, _, s in part])
        for to in range(0, len(right), step):
            other = right[to : to + step]
            close = _overlaps([s for *_, s in part], [s for *_, s in other]) >= np.maximum(need_l[:, None], need_r[None, to : to + step])
            done = set()
            for i, j in zip(*np.nonzero(close), strict=True):
                (a, ca, sa), (b, cb, sb) = part[i], other[j]
                if ca != cb and a != b and (a, cb) not in done and linked(sa, sb, percent):
                    done.add((a, cb))
                    out.append((a, b))
    return out


def _comparer(percent: int):
    def run(table: pa.Table) -> pa.Table:
        sides: tuple[list, list] = ([], [])
        for side, i, c, s in zip(*(table.column(n).to_pylist() for n in ("side", "id", "component")), table.column("shingles"), strict=True):
            sides[side].append((i, c, s.values.to_numpy(zero_copy_only=False).view(np.uint64)))
        found = links_between(*sides, percent) if all(sides) else []
        del sides
        trim()
        return pa.table({"a": pa.array([a for a, _ in found], pa.int64()), "b": pa.array([b for _, b in found], pa.int64())})

    return run


def compared(jobs: DataFrame, sets: DataFrame, percent: int = PERCENT) -> DataFrame:
    """(a, b) links found by jobs (hub, l, r, side, id, component): in each (hub, l, r), side 0 against side 1."""
    rows = jobs.join(sets.select("id", "shingles"), "id")
    return spread(rows, "hub", "l", "r").groupBy("hub", "l", "r").applyInArrow(_comparer(percent), "a bigint, b bigint")


def _dealt(members: DataFrame, name: str) -> DataFrame:
    """members (hub, id, n, ...) with a block number and the number of blocks, so that a block keeps within its bounds."""
    sizes = members.groupBy("hub").agg(F.greatest(F.ceil(F.count(F.lit(1)) / BLOCK_DOCS), F.ceil(F.sum("n") / BLOCK_SHINGLES)).cast("int").alias(f"{name}s"))
    return members.join(sizes, "hub").withColumn(name, F.pmod(F.hash("id", F.lit(name)), F.col(f"{name}s")))


def find_links(reps: DataFrame, texts: DataFrame, percent: int = PERCENT) -> DataFrame:
    """(id, component) of all sets that are linked with another. texts: (id, text), one row at least for each rep."""
    small_batches(reps.sparkSession)
    grouped = staged(groups(reps).join(reps.select("id", "n"), "id"), "groups")
    # ids grow with the corpus: texts are dealt by id once, alike at every size, and come sorted, so that repeats are neighbours
    wanted = grouped.select("id").distinct().hint("merge")
    sets = staged(texts.join(wanted, "id", "left_semi").mapInArrow(_sets, "id bigint, n bigint, shingles array<bigint>"), "sets")
    members = _dealt(grouped.where("hub <> id"), "r")
    zero = F.lit(0)
    rights = members.select("hub", zero.alias("l"), "r", F.lit(1).alias("side"), "id", F.col("id").alias("component"))
    hubs = members.select("hub", "r").distinct().select("hub", zero.alias("l"), "r", zero.alias("side"), F.col("hub").alias("id"), F.col("hub").alias("component"))
    first = staged(compared(hubs.union(rights), sets, percent), "stars")
    parts = components(first)
    # what is not in the hub's component yet meets the whole group
    own = grouped.join(parts, "id", "left").select("hub", "id", "n", F.coalesce("component", "id").alias("component"))
    hub_parts = own.where("hub = id").select("hub", F.col("component").alias("hub_component"))
    own = staged(own.join(hub_parts, "hub"), "parts")
    rest = _dealt(own.where("component <> hub_component"), "l")
    lefts_of = rest.groupBy("hub").agg(F.max("ls").alias("ls"))
    whole = _dealt(own.join(lefts_of.select("hub"), "hub", "left_semi").where("hub <> id"), "r")
    rights_of = whole.groupBy("hub").agg(F.max("rs").alias("rs"))
    upto = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    left = rest.join(rights_of, "hub").select("hub", "l", upto("rs").alias("r"), zero.alias("side"), "id", "component")
    right = whole.join(lefts_of, "hub").select("hub", upto("ls").alias("l"), "r", F.lit(1).alias("side"), "id", "component")
    second = compared(left.union(right), sets, percent)
    return components(first.union(second))


def near_duplicates(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", percent: int = PERCENT) -> DataFrame:
    """One row a document: doc_id, n_shingles, component_id, kept. Links are pairs of percent / 100 or more."""
    drawn = staged(sketches(docs, doc_id, text, percent), "sketches")
    alike = drawn.where("key is not null").groupBy("key").agg(F.min("id").alias("rep"))
    reps = drawn.join(alike, "key").where("id = rep").select("id", "n", "sketch", "prefix")
    found = find_links(reps, docs.select(F.col(doc_id).cast("bigint").alias("id"), F.col(text).alias("text")), percent)
    heads = alike.join(found, alike["rep"] == found["id"], "left").select("key", F.coalesce("component", "rep").alias("component"))
    out = drawn.select("id", "n", "key").join(heads, "key", "left")
    component = F.when(F.col("key").isNull(), F.col("id")).otherwise(F.col("component"))
    return out.select(F.col("id").alias("doc_id"), F.col("n").alias("n_shingles"), component.alias("component_id"), F.col("id").eqNullSafe(component).alias("kept"))


def keep_first(docs: DataFrame, percent: int = PERCENT) -> DataFrame:
    """docs without all but the first document of each group of near-duplicates; of rows that repeat an id and its text
    one stays. Texts are shuffled once, by id, where no id is repeated."""
    judged = staged(near_duplicates(docs, percent=percent).select("doc_id", "kept"), "kept")
    gone = judged.where(~F.col("kept")).select("doc_id").distinct()
    left = docs.join(gone.hint("merge"), "doc_id", "left_anti").select(*docs.columns)
    twice = staged(judged.where("kept").groupBy("doc_id").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("doc_id"), "twice")
    if twice.isEmpty():
        return left
    again = left.join(twice, "doc_id", "left_semi").dropDuplicates(["doc_id", "text"])
    return left.join(twice, "doc_id", "left_anti").unionByName(again.select(*docs.columns)).select(*docs.columns)

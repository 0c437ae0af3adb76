"""Benchmark decontamination: windows of test words in a broadcast hash set, looked up along every training text.

A window is `size` consecutive words of an item; a shorter item is one window by itself. Hits found by hash are confirmed
word by word. Contract for odd input: a null text has no words and no hits; an item without words has no window; repeated
items and rows count one by one; extra columns pass through.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from meterpack.llm.common import byte_chunks, sent, small_batches, window_hashes, word_hashes

WINDOW = 10
#: Characters of benchmark text that one broadcast set may come from; a larger benchmark is scanned block by block.
MAX_BLOCK_CHARS = 64_000_000
#: Lower-cases A-Z, keeps digits, letters and all bytes beyond ASCII, and blanks out the rest.
WORD_BYTES = bytes(b + 32 if 65 <= b <= 90 else b if 48 <= b <= 57 or 97 <= b <= 122 or b >= 128 else 32 for b in range(256))


def words_of(text: bytes | None) -> list[bytes]:
    return text.translate(WORD_BYTES).split() if text else []


class WindowSet:
    """Sorted hashes of windows by length, and what each hash stands for."""

    def __init__(self, items: list[tuple[object, str | None]], size: int = WINDOW) -> None:
        by_size: dict[int, dict[tuple[bytes, ...], set[str]]] = {}
        for item_id, text in items:
            words = words_of(text.encode() if text is not None else None)
            n = min(size, len(words))
            for i in range(len(words) - n + 1 if n else 0):
                by_size.setdefault(n, {}).setdefault(tuple(words[i : i + n]), set()).add(str(item_id))
        self.sizes = {}
        for n, found in sorted(by_size.items()):
            at: dict[int, list] = {}
            for window, ids in found.items():
                at.setdefault(int(window_hashes(word_hashes(list(window)), n)[0]), []).append((window, frozenset(ids)))
            self.sizes[n] = (np.array(sorted(at), np.uint64), at)

    def scan(self, words: list[bytes], hashes: np.ndarray) -> tuple[np.ndarray, set[str]]:
        """Which words lie in a window's occurrence, and the items these windows belong to."""
        covered, items = np.zeros(len(words), bool), set()
        for n, (keys, at) in self.sizes.items():
            if len(words) < n or not len(keys):
                continue
            h = window_hashes(hashes, n)
            place = np.searchsorted(keys, h)
            place[place == len(keys)] = 0
            for i in np.flatnonzero(keys[place] == h):
                for window, ids in at[int(h[i])]:
                    if all(a == b for a, b in zip(window, words[i : i + n], strict=True)):
                        covered[i : i + n] = True
                        items |= ids
        return covered, items


HITS = "struct<n_words:bigint,hit:array<int>,items:array<string>>"
_HITS = pa.struct([("n_words", pa.int64()), ("hit", pa.list_(pa.int32())), ("items", pa.list_(pa.string()))])


def _scanner(windows):
    @F.arrow_udf(HITS)
    def scan(text: pa.Array) -> pa.Array:
        out, look = [], windows().scan
        for chunk in byte_chunks(text):
            split = [words_of(t) for t in chunk]
            flat = word_hashes([w for words in split for w in words])
            at = 0
            for words in split:
                covered, items = look(words, flat[at : at + len(words)])
                at += len(words)
                out.append({"n_words": len(words), "hit": np.flatnonzero(covered).astype(np.int32), "items": sorted(items)})
        return pa.array(out, _HITS)

    return scan


def blocks_of(benchmark: DataFrame, item_id: str, text: str, max_chars: int):
    """The benchmark on the driver, a block at a time: never more than max_chars characters at once (or one item)."""
    block, size = [], 0
    for row in benchmark.select(F.col(item_id).alias("i"), F.col(text).alias("t")).toLocalIterator():
        block.append((row.i, row.t))
        size += len(row.t or "")
        if size >= max_chars:
            yield block
            block, size = [], 0
    if block:
        yield block


def find_leaks(docs: DataFrame, benchmark: DataFrame, text: str = "text", item_id: str = "item_id", item_text: str = "text", size: int = WINDOW, max_chars: int = MAX_BLOCK_CHARS) -> DataFrame:
    """docs with `leak` beside its columns: n_words, the places of hit words, the ids (as strings) of items found. Map-only.

    Several blocks make several scans, whose places and ids are united."""
    small_batches(docs.sparkSession)
    sc = docs.sparkSession.sparkContext
    out, names = docs, []
    for k, block in enumerate(blocks_of(benchmark, item_id, item_text, max_chars)):
        names.append(f"__mp_leak_{k}")
        out = out.withColumn(names[-1], _scanner(sent(sc, WindowSet(block, size)))(F.col(text)))
    if not names:
        names = ["__mp_leak_0"]
        out = out.withColumn(names[0], _scanner(sent(sc, WindowSet([], size)))(F.col(text)))
    leak = F.col(names[0])
    for name in names[1:]:
        other = F.col(name)
        leak = F.struct(leak["n_words"].alias("n_words"), F.array_union(leak["hit"], other["hit"]).alias("hit"), F.array_union(leak["items"], other["items"]).alias("items"))
    return out.withColumn("leak", leak).drop(*names)


def leak_report(docs: DataFrame, benchmark: DataFrame, doc_id: str = "doc_id", **how) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256, contaminated: the digest of find_leaks."""
    found = find_leaks(docs.select(F.col(doc_id).alias("doc_id"), "text"), benchmark, **how)
    n_hit = F.size("leak.hit").cast("long")
    return found.select("doc_id", F.col("leak.n_words").alias("n_words"), n_hit.alias("n_hit"), F.size("leak.items").cast("long").alias("n_items"), F.sha2(F.array_join(F.array_sort("leak.items"), ","), 256).alias("items_sha256"), (n_hit > 0).alias("contaminated"))


def drop_leaks(docs: DataFrame, benchmark: DataFrame, **how) -> DataFrame:
    """Documents without a hit, with their own columns. A document of which any word is hit goes."""
    own = docs.columns
    return find_leaks(docs.select(F.struct("*").alias("__mp_row"), "text"), benchmark, **how).where(F.size("leak.hit") == 0).select(*(F.col("__mp_row")[c].alias(c) for c in own))


def _cutter():
    @F.arrow_udf("string")
    def cut(text: pa.Array, hit: pa.Array) -> pa.Array:
        out = []
        for t, places in zip(text.to_pylist(), hit.to_pylist(), strict=True):
            if not t or not places:
                out.append(t)
                continue
            raw = t.encode()
            blank = raw.translate(WORD_BYTES)
            bounds, at = [], 0
            for w in blank.split():
                at = blank.index(w, at)
                bounds.append((at, at + len(w)))
                at += len(w)
            kept, last, places = [], 0, sorted(places)
            i = 0
            while i < len(places):
                j = i
                while j + 1 < len(places) and places[j + 1] == places[j] + 1:
                    j += 1
                kept.append(raw[last : bounds[places[i]][0]])
                last = bounds[places[j]][1]
                i = j + 1
            out.append((b"".join(kept) + raw[last:]).decode(errors="replace"))
        return pa.array(out, pa.string())

    return cut


def cut_leaks(docs: DataFrame, benchmark: DataFrame, **how) -> DataFrame:
    """Every document, with the spans of hit words removed from its text."""
    own = docs.columns
    found = find_leaks(docs.select(F.struct("*").alias("__mp_row"), "text"), benchmark, **how)
    new = _cutter()(F.col("text"), F.col("leak.hit"))
    return found.select(*((new if c == "text" else F.col("__mp_row")[c]).alias(c) for c in own))


def items_digest(ids: list[str]) -> str:
    return hashlib.sha256(",".join(sorted(ids)).encode()).hexdigest()

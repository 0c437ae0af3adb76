"""Helpers that the training-data operators share: text normal forms, chunked Arrow columns, staged tables."""

from __future__ import annotations

import ctypes
import pickle
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import SparkContext, cloudpickle
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from meterpack.operators.ranks import shared_dir

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
LOWER = UPPER.lower()
#: Bytes A-Z to a-z, all others as they are.
FOLD = bytes.maketrans(UPPER.encode(), LOWER.encode())
#: bytes.split() and bytes.strip() cut at exactly these.
BLANKS = b" \t\n\r\x0b\x0c"
#: UTF-8 bytes that start no code point.
TAIL_BYTES = bytes(range(0x80, 0xC0))
#: Rows that a kernel holds as Python objects at a time.
CHUNK_ROWS = 128


def fold_ascii(c: Column) -> Column:
    """A-Z lower-cased, every other character kept."""
    return F.translate(c, UPPER, LOWER)


def sf_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def sent(sc: SparkContext, what: object, keep: bool = True) -> Callable[[], object]:
    """Broadcasts an object of this package; the function returned gives it on a worker, unpacked once a task, or at every
    call where it is not to be kept. The packed bytes are read from the worker's own disk and not held beside it."""
    box, unpacked = sc.broadcast(cloudpickle.dumps(what)), []

    def get() -> object:
        if unpacked:
            return unpacked[0]
        found = pickle.loads(box.value)
        vars(box).pop("_value", None)  # else PySpark holds them; they are read again when next asked for
        if keep:
            unpacked.append(found)
        return found

    return get


#: Rows of a text column that go to a Python worker at a time, and bytes, whichever is fewer: texts and packed hashes are long,
#: and an executor holds several batches, on both sides of the pipe.
BATCH_ROWS, BATCH_BYTES = 1024, 8 << 20


def small_batches(spark: SparkSession) -> None:
    """Lowers the session's Arrow batches to BATCH_ROWS where it allows more, and to BATCH_BYTES where it names no size; runtime
    settings that any job may lower. A batch is closed by the row that passes the limit, so a longer text is a batch of its own."""
    rows, size = "spark.sql.execution.arrow.maxRecordsPerBatch", "spark.sql.execution.arrow.maxBytesPerBatch"
    if not 0 < int(spark.conf.get(rows, "10000")) <= BATCH_ROWS:
        spark.conf.set(rows, str(BATCH_ROWS))
    if spark.conf.get(size, None) is None:
        spark.conf.set(size, str(BATCH_BYTES))


def trim() -> None:
    """Gives what a worker no longer uses back to the machine: idle workers stay beside the executor's own memory."""
    pa.default_memory_pool().release_unused()
    libc = ctypes.CDLL(None)
    if hasattr(libc, "malloc_trim"):
        libc.malloc_trim(0)


def byte_chunks(column: pa.Array, rows: int = CHUNK_ROWS) -> Iterator[list[bytes | None]]:
    """The UTF-8 bytes of a string column, some rows at a time."""
    raw = column.cast(pa.large_binary()) if pa.types.is_large_string(column.type) else column.cast(pa.binary())
    for at in range(0, len(raw), rows):
        yield raw.slice(at, rows).to_pylist()


def text_chunks(column: pa.Array, rows: int = CHUNK_ROWS) -> Iterator[list[str | None]]:
    for at in range(0, len(column), rows):
        yield column.slice(at, rows).to_pylist()


def mix64(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: every input bit moves every output bit."""
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xFF51AFD7ED558CCD)
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(33))


def starts_of(hashes: np.ndarray) -> np.ndarray:
    """Where hashes in rising order begin that share their first bits, which are as many as give one hash each, more or less."""
    bits = max(1, len(hashes).bit_length())
    starts = np.searchsorted(hashes, np.arange(1 << bits, dtype=np.uint64) << np.uint64(64 - bits))
    return np.minimum(starts, max(0, len(hashes) - 1)).astype(np.uint32)


def find(hashes: np.ndarray, starts: np.ndarray, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(place among the hashes, whether it is there) of each h."""
    if not len(hashes):
        return np.zeros(len(h), np.int64), np.zeros(len(h), bool)
    at = starts[(h >> np.uint64(65 - len(starts).bit_length())).astype(np.int64)].astype(np.int64)
    behind = np.flatnonzero(hashes[at] < h)
    while len(behind):
        behind = behind[at[behind] < len(hashes) - 1]
        at[behind] += 1
        behind = behind[hashes[at[behind]] < h[behind]]
    return at, hashes[at] == h


#: Odd base of the byte polynomial and its inverse modulo 2**64.
BASE = 0x9E3779B97F4A7C15
UNBASE = pow(BASE, -1, 1 << 64)
_POWERS: dict[str, np.ndarray] = {}


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """BASE**i and UNBASE**i for i in 0..n, kept for the worker's life; they double when a longer text comes."""
    if "up" not in _POWERS or len(_POWERS["up"]) <= n:
        size = 1 << max(12, int(n).bit_length())
        for name, base in (("up", BASE), ("down", UNBASE)):
            steps = np.full(size, base, np.uint64)
            steps[0] = 1
            _POWERS[name] = np.multiply.accumulate(steps)
    return _POWERS["up"], _POWERS["down"]


#: Bytes that are hashed at a time.
HASH_BYTES = 1 << 19


def word_hashes(words: list[bytes]) -> np.ndarray:
    """One 64-bit hash a word, the same on every machine: a byte polynomial over many words at once, mixed."""
    lengths = np.fromiter(map(len, words), np.int64, len(words))
    out, ends, at = np.empty(len(words), np.uint64), np.cumsum(lengths), 0
    while at < len(words):
        before = int(ends[at] - lengths[at])
        to = max(at + 1, int(np.searchsorted(ends, before + HASH_BYTES, "right")))
        data = np.frombuffer(b"".join(words[at:to]), np.uint8).astype(np.uint64)
        data += np.uint64(1)
        up, down = powers(len(data) + 1)
        data *= up[: len(data)]
        sums = np.empty(len(data) + 1, np.uint64)
        sums[0] = 0
        np.cumsum(data, out=sums[1:])
        stop = ends[at:to] - before
        start = stop - lengths[at:to]
        out[at:to] = mix64((sums[stop] - sums[start]) * down[start] ^ lengths[at:to].astype(np.uint64))
        at = to
    return out


def window_hashes(h: np.ndarray, n: int) -> np.ndarray:
    """A 64-bit hash of every n consecutive word hashes; none for fewer words."""
    if len(h) < n:
        return np.empty(0, np.uint64)
    up, _ = powers(n + 1)
    out = np.zeros(len(h) - n + 1, np.uint64)
    for i in range(n):
        out += h[i : len(h) - n + 1 + i] * up[i + 1]
    return mix64(out)


#: Shuffle files of a query go when it ends; a runtime setting, on while a staged table is written.
CLEAN = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def staged(df: DataFrame, name: str) -> DataFrame:
    """Writes df once as Parquet in the shared folder and reads it back, so that later uses neither recompute it nor
    depend on an executor's own disk. Columns keep their names and types. What the query shuffled goes with its end."""
    spark = df.sparkSession
    path, before = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}", spark.conf.get(CLEAN, "false")
    spark.conf.set(CLEAN, "true")
    try:
        df.write.parquet(path)
    finally:
        spark.conf.set(CLEAN, before)
    out = spark.read.schema(df.schema).parquet(path)
    out._mp_path = path
    return out


def discard(*tables: DataFrame) -> None:
    """Deletes the files of staged tables that nothing will read again."""
    for t in tables:
        path = t.sparkSession._jvm.org.apache.hadoop.fs.Path(t._mp_path)
        path.getFileSystem(t.sparkSession._jsc.hadoopConfiguration()).delete(path, True)

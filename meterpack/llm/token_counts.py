"""Token counts as rollups kept up to date by deltas.

A batch of inserts (+), deletes (-) and revisions (- old, + new) shrinks to signed sums by source, language and tokenizer
version, committed as one folder named by the batch. Totals are the sum over committed folders. A folder appears by one
rename, and a batch that is there is not written again, so a batch may be replayed at any time.

Contract for odd input: a null text has no tokens; null sources and languages are groups of their own; repeated rows count
each time; an empty batch commits an empty folder; columns beyond those named are not read.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from meterpack.llm.common import text_chunks

KEYS = ("source", "lang", "tokenizer")
SCHEMA = "source string, lang string, tokenizer string, n_docs bigint, n_tokens bigint"


def words_v1(text: Column) -> Column:
    """Runs of anything but blanks."""
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("bigint")


def pieces_v1(text: Column) -> Column:
    """Runs of ASCII letters, runs of digits, and every other character that is no blank."""
    return F.coalesce(F.regexp_count(text, F.lit(r"[A-Za-z]+|[0-9]+|[^A-Za-z0-9\x20\x09-\x0D]")), F.lit(0)).cast("bigint")


def bpe(path: str, pattern: str) -> Callable[[Column], Column]:
    """Counts tokens of a byte-level vocabulary file (base64 token and rank a line), which workers read from `path`."""
    cache: dict = {}

    @F.arrow_udf("bigint")
    def count(text: pa.Array) -> pa.Array:
        if "encoder" not in cache:
            import base64

            import tiktoken

            with open(path, "rb") as f:
                ranks = {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, f)}
            cache["encoder"] = tiktoken.Encoding("counter", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
        encode = cache["encoder"].encode_ordinary
        return pa.array([len(encode(t)) if t else 0 for chunk in text_chunks(text) for t in chunk], pa.int64())

    return count


def changes(docs: DataFrame, tokenizer: str, tokens: Column, sign: int = 1, source: str = "source", lang: str = "lang") -> DataFrame:
    """Signed rows for documents that come (1) or go (-1)."""
    return docs.select(F.col(source).alias("source"), F.col(lang).alias("lang"), F.lit(tokenizer).alias("tokenizer"), F.lit(sign).cast("bigint").alias("n_docs"), (tokens * sign).alias("n_tokens"))


def revisions(docs: DataFrame, tokenizer: str, old: Column, new: Column, source: str = "source", lang: str = "lang") -> DataFrame:
    """Signed rows for documents whose count changes."""
    return changes(docs, tokenizer, new - old, 1, source, lang).withColumn("n_docs", F.lit(0).cast("bigint"))


def rolled(rows: DataFrame) -> DataFrame:
    return rows.groupBy(*KEYS).agg(F.sum("n_docs").alias("n_docs"), F.sum("n_tokens").alias("n_tokens"))


class TokenLedger:
    """The committed batches under one folder of any store that Spark reaches.

    batches/<name> holds a batch, bases/<number> the sums of many with their names. The highest base counts, and all batches
    that it does not name. Either appears by one rename; nothing that counts is ever deleted before."""

    def __init__(self, spark: SparkSession, root: str) -> None:
        self.spark, self.root = spark, root.rstrip("/")
        jvm = spark._jvm
        self._path = lambda name: jvm.org.apache.hadoop.fs.Path(f"{self.root}/{name}")
        self._fs = self._path("x").getFileSystem(spark._jsc.hadoopConfiguration())

    def _names(self, folder: str) -> list[str]:
        top = self._path(folder)
        return sorted(s.getPath().getName() for s in self._fs.listStatus(top)) if self._fs.exists(top) else []

    def _base(self) -> tuple[str | None, set[str]]:
        """(the folder of the base that counts, the batches it names)."""
        bases = self._names("bases")
        if not bases:
            return None, set()
        folder = f"{self.root}/bases/{bases[-1]}"
        return folder, {r.batch for r in self.spark.read.schema("batch string").parquet(f"{folder}/names").collect()}

    def committed(self) -> list[str]:
        return sorted(self._base()[1] | set(self._names("batches")))

    def _appear(self, draft: str, target: str) -> bool:
        """Renames a finished draft to its place; False, without it, where that is taken: some stores would nest it there."""
        nested = self._path(f"{target}/{draft.rpartition('/')[2]}")
        self._fs.mkdirs(self._path(target).getParent())
        done = not self._fs.exists(self._path(target)) and self._fs.rename(self._path(draft), self._path(target))
        if done and self._fs.exists(nested):
            self._fs.delete(nested, True)
            done = False
        if not done:
            self._fs.delete(self._path(draft), True)
        return done

    def commit(self, batch: str, rows: DataFrame) -> bool:
        """Adds a batch once; False where it is there already. rows: signed rows, or their sums."""
        if batch in self._base()[1] or self._fs.exists(self._path(f"batches/{batch}")):
            return False
        draft = f"drafts/{batch}-{uuid.uuid4().hex}"
        rolled(rows).write.parquet(f"{self.root}/{draft}")
        return self._appear(draft, f"batches/{batch}")

    def _sums(self, base: str | None, batches: list[str]) -> DataFrame:
        paths = ([f"{base}/sums"] if base else []) + [f"{self.root}/batches/{n}" for n in batches]
        rows = self.spark.read.schema(SCHEMA).parquet(*paths) if paths else self.spark.createDataFrame([], SCHEMA)
        return rolled(rows).where("n_docs <> 0 or n_tokens <> 0")

    def totals(self) -> DataFrame:
        """One scan over the base and all batches that it does not name."""
        base, folded = self._base()
        return self._sums(base, [n for n in self._names("batches") if n not in folded])

    def compact(self) -> bool:
        """Folds all batches so far into a new base. Folders of batches that an earlier base names go only afterwards: a reader
        that began with that base has what it needs, and replays are refused by name."""
        base, folded = self._base()
        batches = self._names("batches")
        new = [n for n in batches if n not in folded]
        number = int(base.rpartition("/")[2]) + 1 if base else 0
        draft = f"drafts/base-{uuid.uuid4().hex}"
        self._sums(base, new).write.parquet(f"{self.root}/{draft}/sums")
        self.spark.createDataFrame([(n,) for n in sorted(folded | set(new))], "batch string").write.parquet(f"{self.root}/{draft}/names")
        done = self._appear(draft, f"bases/{number:09d}")
        if done:
            for n in batches:
                if n in folded:
                    self._fs.delete(self._path(f"batches/{n}"), True)
        return done

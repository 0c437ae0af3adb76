"""Stupid-backoff scores: n-grams counted by hash partition, which answers every batch of documents with the counts it needs.

Words, bigrams and trigrams of all texts are counted, however rare: every table grows with the input. Documents fall into two
folds by the md5 of their text, and each is scored with the counts of the other fold, so that no document, nor its exact
copy, vouches for itself. Costs are whole micro-nats, made of rounded logarithms of counts, so that sums do not depend on
their order.

Texts are read once, and kept as hashes, in batches of documents of one fold and GATHER words or some more. A batch sends its
different n-grams with their counts, packed, one row for each bucket of hashes; the bucket adds up what all batches sent, and
answers each batch with what the other fold has of its n-grams, in their order, so that no hash travels back. Since a batch
holds the parts of its n-grams too, it knows all counts that its documents' costs are made of. So what travels is packed rows of
batches, and one row a document comes out; a frequent n-gram is one entry a batch. Counting goes in rounds by hash: shuffle
files of a round go when it is written, which bounds the disk.

Two n-grams of equal 64-bit hash would be counted as one: below 1e10 different ones, three such pairs are expected at most.

Contract for odd input: a null or empty text has no words and costs nothing; rows of equal text cost the same; an empty
table gives no rows; only the two columns named are read.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType, LongType, StructField, StructType

from meterpack.llm.common import byte_chunks, discard, find, small_batches, staged, starts_of, trim, word_hashes
from meterpack.llm.decontaminate import words_of

#: The word before the first, which is counted once a text.
START = 0x1E3779B97F4A7C15
BACKOFF = 0.4
MICRO = 1_000_000
#: Words that a task gathers in a row before it packs them.
GATHER = 500_000
#: Words of a bucket, more or less, and bytes taken for one.
BUCKET_WORDS, WORD_BYTES = 2_000_000, 6
#: Rounds in which n-grams are counted.
ROUNDS = 3
#: Counts from here on, 255 at most, travel beside the bytes of the others.
LEAST_HOT = 16
#: What each step back costs, and a word that the other fold lacks (half a word) in place of log(count).
STEP, HALF = round(-np.log(BACKOFF) * MICRO), round(np.log(0.5) * MICRO)


def fold_of(text: Column) -> Column:
    return F.pmod(F.conv(F.substring(F.md5(F.coalesce(text, F.lit(""))), 1, 1), 16, 10).cast("int"), F.lit(2))


def _turned(x: np.ndarray, by: int) -> np.ndarray:
    return x << np.uint64(by) | x >> np.uint64(64 - by)


#: Word hashes are mixed bits, so that turning the first part before it meets the second makes the order count.
TURN_WORD, TURN_BIGRAM = 1, 21


def bigram(v: np.ndarray, w: np.ndarray) -> np.ndarray:
    return _turned(v, TURN_WORD) ^ w


def trigram(uv: np.ndarray, vw: np.ndarray) -> np.ndarray:
    return _turned(uv, TURN_BIGRAM) ^ vw


def round_of(g: np.ndarray, rounds: int) -> np.ndarray:
    return (g & np.uint64(0x7FFFFFFF)) % np.uint64(rounds)


def bucket_of(g: np.ndarray, buckets: int) -> np.ndarray:
    """By the first bits, so that hashes in rising order have their buckets in rising order."""
    return ((g >> np.uint64(32)) * np.uint64(buckets) >> np.uint64(32)).astype(np.int32)


WORDS = "batch bigint, fold int, n_texts bigint, n_words bigint, ids binary, sizes binary, vocabulary binary, places binary"


def _boxed(ids: list[pa.Array]) -> bytes:
    sink, table = pa.BufferOutputStream(), pa.table({"doc_id": pa.chunked_array(ids)})
    with pa.ipc.new_stream(sink, table.schema) as out:
        out.write_table(table)
    return sink.getvalue().to_pybytes()


def _gather(batches):
    """Rows of documents of one fold (ids, words of each) with GATHER words or a few more: their different words as hashes, and
    the place there of every word. batches: (text, fold, doc_id)."""
    held, n, made, task = ([], []), [0, 0], 0, TaskContext.get().partitionId()

    def flush(fold):
        nonlocal made
        sizes, w = (np.concatenate([h[i] for h in held[fold]]) for i in (1, 2))
        vocabulary, places = np.unique(w, return_inverse=True)
        cells = (_boxed([h[0] for h in held[fold]]), *(c.tobytes() for c in (sizes.astype("<u4"), vocabulary, places.astype("<u4"))))
        heads = ((task << 32) + made, fold, int((sizes > 0).sum()), len(w))
        made += 1
        held[fold].clear()
        n[fold] = 0
        types = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), *[pa.binary()] * 4]
        return pa.RecordBatch.from_arrays([pa.array([c], t) for c, t in zip((*heads, *cells), types, strict=True)], names=[c.split()[0] for c in WORDS.split(", ")])

    for batch in batches:
        folds, at = batch.column(1).to_numpy(zero_copy_only=False), 0
        for chunk in byte_chunks(batch.column(0)):
            ids, own = batch.column(2).slice(at, len(chunk)), folds[at : at + len(chunk)]
            at += len(chunk)
            for fold in (0, 1):
                if len(mine := np.flatnonzero(own == fold)):
                    split = [words_of(chunk[i]) for i in mine]
                    held[fold].append((ids.take(pa.array(mine)), np.fromiter(map(len, split), np.int64, len(split)), word_hashes([x for ws in split for x in ws])))
                    n[fold] += len(held[fold][-1][2])
                    if n[fold] >= GATHER or sum(len(h[1]) for h in held[fold]) >= 60_000:
                        yield flush(fold)
    for fold in (0, 1):
        if held[fold]:
            yield flush(fold)
    trim()


def _numbers(cell: pa.Scalar, kind: str) -> np.ndarray:
    return np.frombuffer(cell.as_buffer(), kind)


def _orders(sizes: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(places of first words, bigrams that end at each word, places of words that end a trigram, these trigrams). The first word
    of a text follows START and is in no trigram."""
    first = np.zeros(len(w), bool)
    first[(np.cumsum(sizes) - sizes)[sizes > 0]] = True
    v = np.empty_like(w)
    v[1:], v[first] = w[:-1], START
    vw, later = bigram(v, w), np.flatnonzero(~first)
    return np.flatnonzero(first), vw, later, trigram(vw[later - 1], vw[later])


def _of_round(grams: list[np.ndarray], round_: int, rounds: int) -> tuple[np.ndarray, np.ndarray]:
    """(different n-grams of a round in rising order, how often each comes)."""
    g = np.sort(np.concatenate([x[round_of(x, rounds) == round_] for x in grams]))
    heads = np.flatnonzero(np.concatenate([[True], g[1:] != g[:-1]])) if len(g) else np.empty(0, np.int64)
    return g[heads], np.diff(np.append(heads, len(g)))


def _short(n: np.ndarray, most: int) -> tuple[bytes, bytes]:
    """Counts as bytes, and those that are too high for it."""
    return np.minimum(n, most).astype(np.uint8).tobytes(), n[n >= most].astype("<u8").tobytes()


def _long(low: np.ndarray, high: np.ndarray, most: int) -> np.ndarray:
    n = low.astype(np.int64)
    n[low == most] = high
    return n


SENT = "bucket int, batch bigint, fold int, grams binary, low binary, high binary"


def _sender(round_: int, rounds: int, buckets: int, most: int):
    def run(batches):
        for batch in batches:
            for row in batch.to_pylist():
                sizes, w = np.frombuffer(row["sizes"], "<u4").astype(np.int64), np.frombuffer(row["vocabulary"], np.uint64)[np.frombuffer(row["places"], "<u4")]
                _, two, _, three = _orders(sizes, w)
                g, n = _of_round([w, two, three], round_, rounds)
                bucket = bucket_of(g, buckets)
                ends = [0, *(np.flatnonzero(bucket[1:] != bucket[:-1]) + 1).tolist(), len(g)]
                out = [(int(bucket[a]), row["batch"], row["fold"], g[a:z].tobytes(), *_short(n[a:z], most)) for a, z in zip(ends, ends[1:], strict=False) if z > a]
                if out:
                    yield pa.RecordBatch.from_pylist([dict(zip(SENT_TYPES.names, x, strict=True)) for x in out], schema=SENT_TYPES)
        trim()

    return run


SENT_TYPES = pa.schema([("bucket", pa.int32()), ("batch", pa.int64()), ("fold", pa.int32()), ("grams", pa.binary()), ("low", pa.binary()), ("high", pa.binary())])
ANSWERS = "batch bigint, round int, bucket int, low binary, high binary"
ANSWER_TYPES = pa.schema([("batch", pa.int64()), ("round", pa.int32()), ("bucket", pa.int32()), ("low", pa.binary()), ("high", pa.binary())])


def _answerer(round_: int, most: int):
    """For each row that came to a bucket, how often the other fold has each of its n-grams."""

    def run(t: pa.Table) -> pa.Table:
        folds, sent_ = t["fold"].to_numpy(), [(_numbers(g, "<u8"), _long(_numbers(a, np.uint8), _numbers(b, "<u8"), most)) for g, a, b in zip(t["grams"], t["low"], t["high"], strict=True)]
        sizes = np.array([len(g) for g, _ in sent_])
        g, n = (np.concatenate([x[i] for x in sent_]) for i in (0, 1))
        order = np.argsort(g)
        g, n, fold = g[order], n[order], np.repeat(folds, sizes)[order]
        heads = np.flatnonzero(np.concatenate([[True], g[1:] != g[:-1]]))
        ones = np.add.reduceat(n * fold, heads)
        runs = np.diff(np.append(heads, len(g)))
        every = np.add.reduceat(n, heads)
        other = np.where(fold == 0, np.repeat(ones, runs), np.repeat(every - ones, runs))
        answer = np.empty(len(g), np.int64)
        answer[order] = other
        ends = np.cumsum(sizes)
        low, high = zip(*(_short(answer[a:z], most) for a, z in zip(ends - sizes, ends, strict=True)), strict=True)
        trim()
        return pa.table([t["batch"], pa.array([round_] * len(t), pa.int32()), t["bucket"], pa.array(low, pa.binary()), pa.array(high, pa.binary())], schema=ANSWER_TYPES)

    return run


def _log(n: np.ndarray) -> np.ndarray:
    return np.rint(np.log(np.maximum(n, 1)) * MICRO).astype(np.int64)


def _scorer(texts: list[int], logs: list[int], rounds: int, most: int):
    """(doc_id, fold, n_tokens, cost) of a batch's documents. texts: of each fold; logs: of the words of each."""

    def run(words: pa.Table, answers: pa.Table) -> pa.Table:
        answers, out = answers.sort_by([("round", "ascending"), ("bucket", "ascending")]), []
        n = _long(*(np.frombuffer(b"".join(answers[c].to_pylist()), kind) for c, kind in (("low", np.uint8), ("high", "<u8"))), most)
        for row in words.to_pylist():
            sizes, vocabulary, places = (np.frombuffer(row[c], k) for c, k in (("sizes", "<u4"), ("vocabulary", np.uint64), ("places", "<u4")))
            sizes, w, other = sizes.astype(np.int64), vocabulary[places], 1 - row["fold"]
            first, two, later, three = _orders(sizes, w)
            grams = np.concatenate([_of_round([w, two, three], r, rounds)[0] for r in range(rounds)])
            order = np.flatnonzero(n)
            order = order[np.argsort(grams[order])]
            grams, counts = grams[order], n[order]
            starts = starts_of(grams)

            def found(g):
                at, there = find(grams, starts, g)  # noqa: B023
                return (_log(counts[at]) if len(counts) else np.zeros(len(g), np.int64)), there  # noqa: B023

            (one, has_one), (l2, has_two), (l3, has_three) = found(vocabulary), found(two), found(three)
            l1, has_one = one[places], has_one[places]
            lv = np.empty_like(l1)
            lv[1:], lv[first] = l1[:-1], _log(np.array([texts[other]]))[0]
            cost = np.full(len(w), 2 * STEP + logs[other] - HALF, np.int64)
            cost[first] -= STEP
            cost += np.where(has_one, HALF - l1, 0) + np.where(has_two, lv - l2 - STEP - logs[other] + l1, 0)
            cost[later] += np.where(has_three, l2[later - 1] - l3 - STEP - lv[later] + l2[later], 0)
            upto, ends = np.concatenate([[0], np.cumsum(cost)]), np.cumsum(sizes)
            ids = pa.ipc.open_stream(row["ids"]).read_all()["doc_id"]
            out.append(pa.table({"doc_id": ids, "fold": pa.array([row["fold"]] * len(ids), pa.int32()), "n_tokens": sizes, "cost": upto[ends] - upto[ends - sizes]}))
        trim()
        return pa.concat_tables(out)

    return run


def score_documents(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """One row a document: doc_id, fold, n_tokens, cost (micro-nats), nats_per_token."""
    small_batches(docs.sparkSession)
    rows = docs.select(F.col(text).alias("text"), fold_of(F.col(text)).alias("fold"), F.col(doc_id).alias("doc_id"))
    words = staged(rows.mapInArrow(_gather, WORDS), "words")
    sums = {r.fold: r for r in words.groupBy("fold").agg(F.sum("n_texts").alias("texts"), F.sum("n_words").alias("words")).collect()}
    texts, totals = ([int(sums[f][c]) if f in sums else 0 for f in (0, 1)] for c in ("texts", "words"))
    logs = _log(np.array(totals)).tolist() if all(totals) else [0, 0]
    buckets = max(1, round(sum(totals) / BUCKET_WORDS))
    answers, most = [], min(LEAST_HOT, 255)
    for r in range(ROUNDS):
        asked = words.mapInArrow(_sender(r, ROUNDS, buckets, most), SENT)
        answers.append(staged(asked.groupBy("bucket").applyInArrow(_answerer(r, most), ANSWERS), "answers"))
    schema = StructType([StructField("doc_id", rows.schema["doc_id"].dataType), StructField("fold", IntegerType()), StructField("n_tokens", LongType()), StructField("cost", LongType())])
    own, known = words.select("batch", "fold", "ids", "sizes", "vocabulary", "places"), reduce(DataFrame.union, answers)
    scored = own.groupBy("batch").cogroup(known.groupBy("batch")).applyInArrow(_scorer(texts, logs, ROUNDS, most), schema)
    out = staged(scored, "scores")
    discard(words, *answers)
    return out.withColumn("nats_per_token", F.when(F.col("n_tokens") > 0, F.round(F.col("cost") / F.col("n_tokens") / MICRO, 6)))

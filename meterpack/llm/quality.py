"""Quality rules: plain text measures, and bands of perplexity under an n-gram model that Spark counts.

The model of each language is an interpolated modified Kneser-Ney model over ORDER code points, each text after ORDER - 1
pads. All documents count: n-grams are counted in tasks and summed by hash partition, lower orders count the different
n-grams that they end, discounts come from the counts of counts. All that the probability of an n-gram is made of shares the
last code point of its context, but for single code points and discounts: so n-grams are dealt by it, and every part works out
its own orders. More than MAX_MODEL n-grams are joined order by order instead. What a language
has grows with its corpus, and flattens. The model travels as sorted arrays of 64-bit hashes with log probabilities and
back-off weights. Above PIECE entries it travels in pieces by the same code point, and a worker holds one piece at a time; texts
are neither shuffled nor written. A model of more than MAX_MODEL
entries stays a table, and the n-grams of the documents are joined with it, order by order.

A language's band lies around the perplexities of documents that a rater found good (labels), or, where there are too few of
these, of all. Since short texts scatter more, what counts is the distance from the median, shrunk by sqrt(n / (n + SHORT))
for n code points. Characters stand in for words: most words of these texts occur once, so that a word model has only
novelty to go by, and its tables would have to be shuffled against every text.

Contract for odd input: a null text is empty; an empty text has no words and fails the base rules; a null language is a
language of its own; with an empty table the result is empty; repeated rows are judged one by one; columns pass through.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from meterpack.llm.common import BLANKS, TAIL_BYTES, byte_chunks, find, mix64, sent, small_batches, staged, starts_of, text_chunks, trim

SYMBOLS = b"#*$%&|<>"
_SYMBOLS = [bytes((s,)) for s in SYMBOLS]
MIN_WORDS = 50
MAX_REPEAT_PERCENT = 50
ORDER = 5
#: Stands before the first code point of a text.
PAD = "\x02"
#: Perplexities are compared as whole steps of 1/STEPS nat a code point.
STEPS = 500
#: Of the good documents of a language: shares cut off below and above, how far the band reaches beyond, in parts of what is
#: between, and how many there must be. The band never has less than MIN_SPREAD steps to each side of the median.
LOW_SHARE, HIGH_SHARE, MARGIN, LEAST_GOOD, MIN_SPREAD = 0.001, 0.999, 0.05, 200, 10
#: Code points at which the distance from the median counts for 0.7 of what it is in a very long text.
SHORT = 3000
#: With too few of them: this often the range from the fifth to the ninety-fifth percentile of all, around the median.
WIDE = 2.0
#: Entries of a model that is sent to all workers, and of what a worker or the driver holds of it at a time: 16 bytes each.
MAX_MODEL, PIECE = 64_000_000, 4_000_000
#: Code points that wait for each piece to come by, where there are several.
WAIT = 1 << 20
#: Code points that a task counts at a time, and entries it holds before it hands them on.
GATHER, HOLD = 1 << 21, 1_500_000
#: Parts of a language in which probabilities are worked out.
PARTS = 64
_BASE = np.uint64(0x9E3779B97F4A7C15)


def padded(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """(code points of all texts, each after its pads; sizes without pads)."""
    raw = "".join(PAD * (ORDER - 1) + t for t in texts).encode("utf-32-le", "surrogatepass")
    return np.frombuffer(raw, np.uint32), np.fromiter(map(len, texts), np.int64, len(texts))


def gram_hashes(points: np.ndarray, n: int) -> np.ndarray:
    """A 64-bit hash of every n code points in a row."""
    wide = points.astype(np.uint64)
    out = np.zeros(max(0, len(points) - n + 1), np.uint64)
    for i in range(n):
        out += wide[i : len(points) - n + 1 + i]
        out *= _BASE
        out ^= out >> np.uint64(29)
    return mix64(out)


def _own(sizes: np.ndarray) -> np.ndarray:
    """Places among all windows of ORDER code points of those that end in a text's own code point."""
    starts = np.cumsum(sizes + ORDER - 1) - (sizes + ORDER - 1)
    return np.repeat(starts - (np.cumsum(sizes) - sizes), sizes) + np.arange(int(sizes.sum()))


def _different(points: np.ndarray, own: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(n-grams, counts) of the windows that start at own. Places in the texts' alphabet make one number of a window."""
    alphabet = np.unique(points)
    if len(alphabet) ** ORDER >= 1 << 63:
        _, first, n = np.unique(gram_hashes(points, ORDER)[own], return_index=True, return_counts=True)
        return points[own[first][:, None] + np.arange(ORDER)], n
    places = np.zeros(int(alphabet[-1]) + 1 if len(alphabet) else 1, np.int64)
    places[alphabet] = np.arange(len(alphabet))
    digits = places[points]
    keys = digits[: len(points) - ORDER + 1].copy()
    for i in range(1, ORDER):
        keys *= len(alphabet)
        keys += digits[i : len(points) - ORDER + 1 + i]
    keys = np.sort(keys[own])
    heads = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]])) if len(keys) else np.empty(0, np.int64)
    n, left = np.diff(np.append(heads, len(keys))), keys[heads]
    grams = np.empty((len(left), ORDER), np.uint32)
    for i in range(ORDER - 1, -1, -1):
        left, digit = np.divmod(left, len(alphabet))
        grams[:, i] = alphabet[digit]
    return grams, n


def _row_hashes(grams: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each row of code points."""
    k = grams.shape[1]
    return gram_hashes(np.ascontiguousarray(grams).ravel(), k)[::k] if k and len(grams) else np.zeros(len(grams), np.uint64)


def _tally(texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(hashes in rising order, counts, code points) of the n-grams of some texts."""
    points, sizes = padded(texts)
    grams, n = _different(points, _own(sizes))
    order = np.argsort(h := _row_hashes(grams))
    return h[order], n[order], grams[order]


def _merged(parts: list[tuple]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Tallies as one."""
    h, n, grams = parts[0]
    for more, m, rows in parts[1:]:
        at = np.minimum(np.searchsorted(h, more), max(0, len(h) - 1))
        found = h[at] == more if len(h) else np.zeros(len(more), bool)
        n = n.copy()
        n[at[found]] += m[found]
        new = np.flatnonzero(~found)
        order = np.argsort(joined := np.concatenate([h, more[new]]), kind="stable")
        h, n, grams = joined[order], np.concatenate([n, m[new]])[order], np.concatenate([grams, rows[new]])[order]
    return h, n, grams


def _texts_of(grams: np.ndarray) -> pa.Array:
    """A string of each row of code points."""
    k, text = grams.shape[1], np.ascontiguousarray(grams, "<u4").tobytes().decode("utf-32-le", "surrogatepass")
    return pa.array([text[i : i + k] for i in range(0, len(text), k)], pa.string())


def _count_grams(batches):
    waiting: dict[str | None, list[str]] = {}
    held: dict[str | None, list[tuple]] = {}
    sizes: dict[str | None, int] = {}

    def settle(lang):
        if waiting.get(lang):
            held.setdefault(lang, []).append(_tally(waiting.pop(lang)))
            sizes[lang] = 0
            held[lang] = [_merged(held[lang])]

    def out():
        for lang, parts in held.items():
            _, n, grams = parts[0]
            yield pa.RecordBatch.from_arrays([pa.array([lang] * len(n), pa.string()), _texts_of(grams), pa.array(n)], names=["lang", "gram", "n"])
        held.clear()

    for batch in batches:
        at = 0
        langs = batch.column(1).to_pylist()
        for chunk in text_chunks(batch.column(0)):
            for t in chunk:
                lang, at = langs[at], at + 1
                if t:
                    waiting.setdefault(lang, []).append(t)
                    sizes[lang] = sizes.get(lang, 0) + len(t)
                    if sizes[lang] >= GATHER:
                        settle(lang)
                        if sum(len(p[0][0]) for p in held.values()) >= HOLD:
                            yield from out()
    for lang in list(waiting):
        settle(lang)
    yield from out()
    trim()


def count_grams(docs: DataFrame, text: str = "text", lang: str = "lang") -> DataFrame:
    """(lang, gram, n) over all documents: a task sums its own before they are shuffled."""
    small_batches(docs.sparkSession)
    counts = docs.select(F.col(text).alias("text"), F.col(lang).alias("lang")).mapInArrow(_count_grams, "lang string, gram string, n bigint")
    return counts.groupBy("lang", "gram").agg(F.sum("n").alias("n"))


def discounted(table: DataFrame) -> DataFrame:
    """table (key, gram, n) with d, the discount of n: three for each language and order, by the counts of counts; half a
    count where these are too few to tell."""
    few = table.groupBy("key").agg(*(F.count_if(F.col("n") == k).alias(f"n{k}") for k in (1, 2, 3, 4)))
    n1, n2, n3, n4 = (F.col(f"n{k}").cast("double") for k in (1, 2, 3, 4))
    y = n1 / (n1 + 2 * n2)
    whole = (n1 > 0) & (n2 > 0) & (n3 > 0)
    near = lambda k, x: F.when(whole, F.least(F.greatest(x, F.lit(0.05)), F.lit(float(k)))).otherwise(0.5)
    zero = lambda x: F.nullif(x, F.lit(0.0))
    rates = few.select(F.col("key").alias("d_key"), near(1, 1 - 2 * y * n2 / zero(n1)).alias("d1"), near(2, 2 - 3 * y * n3 / zero(n2)).alias("d2"), near(3, 3 - 4 * y * n4 / zero(n3)).alias("d3"))
    d = F.when(F.col("n") == 1, F.col("d1")).when(F.col("n") == 2, F.col("d2")).otherwise(F.col("d3"))
    return table.join(rates, F.col("key") == F.col("d_key")).select("key", "gram", "n", d.alias("d"))


def _rates(n1: int, n2: int, n3: int, n4: int) -> list[float]:
    """discounted() for one language and order: the discounts of a count of 1, of 2, and of more."""
    if not (n1 and n2 and n3):
        return [0.5] * 3
    y = n1 / (n1 + 2 * n2)
    return [min(max(x, 0.05), float(k)) for k, x in ((1, 1 - 2 * y * n2 / n1), (2, 2 - 3 * y * n3 / n2), (3, 3 - 4 * y * n4 / n3))]


def _counts_of_counts(n: np.ndarray) -> list[int]:
    return np.bincount(np.minimum(n, 5), minlength=6)[1:5].tolist()


def _part_orders(t: pa.Table) -> tuple[list[tuple], np.ndarray, np.ndarray]:
    """Of a part's n-grams, (order, n-grams, counts, contexts, place among these, place in the order below) from the highest
    order to the second; single code points with their counts."""
    grams = np.frombuffer("".join(t["gram"].to_pylist()).encode("utf-32-le", "surrogatepass"), np.uint32).reshape(-1, ORDER)
    n, out = t["n"].to_numpy(), []
    for k in range(ORDER, 1, -1):
        _, first, context = np.unique(_row_hashes(grams[:, :-1]), return_index=True, return_inverse=True)
        _, ends, rest, below = np.unique(_row_hashes(grams[:, 1:]), return_index=True, return_inverse=True, return_counts=True)
        out.append((k, grams, n, grams[first, :-1], context, rest))
        grams, n = grams[ends, 1:], below
    return out, grams[:, 0], n


def _part_counts(t: pa.Table) -> pa.Table:
    """(key, k, point, n1 to n4): the counts of counts of every order from the second on; of every code point its count, as n1."""
    orders, points, n = _part_orders(t)
    rows = [(k, 0, *_counts_of_counts(m)) for k, _, m, *_ in orders] + [(1, int(x), int(c), 0, 0, 0) for x, c in zip(points, n, strict=True)]
    columns = [pa.array(c, pa.int64()) for c in zip(*rows, strict=True)]
    trim()
    return pa.table([pa.array([t["key"][0].as_py()] * len(rows), pa.string()), *columns], names=["key", "k", "point", "n1", "n2", "n3", "n4"])


def _part_model(known):
    """Rows (key, gram, logp, logb) of a part: its n-grams from the second order on, then their contexts."""

    def run(t: pa.Table) -> pa.Table:
        key = t["key"][0].as_py()
        points, p, rates = known()[key]
        orders, own, _ = _part_orders(t)
        p, out = p[np.searchsorted(points, own)], []
        for k, grams, n, contexts, context, rest in reversed(orders):
            d = np.array(rates[k])[np.minimum(n, 3) - 1]
            all_ = np.bincount(context, n)
            weight = np.bincount(context, d) / all_
            p = (n - d) / all_[context] + weight[context] * p[rest]
            for rows, logp, logb in ((grams, np.log(p), None), (contexts, None, np.log(weight))):
                logs = [pa.nulls(len(rows), pa.float64()) if x is None else pa.array(x) for x in (logp, logb)]
                out.append(pa.table([pa.array([key] * len(rows), pa.string()), _texts_of(rows), *logs], names=["key", "gram", "logp", "logb"]))
        trim()
        return pa.concat_tables(out)

    return run


def kneser_ney(counts: DataFrame, most: int = MAX_MODEL) -> DataFrame:
    """(key, gram, logp, logb) of every n-gram of every order: the log probability of its last code point after the others, and
    the log of the weight that it gives lower orders as a context (null where it is none; pads are contexts only, so that their
    logp is null). counts: (lang, gram, n) of the
    highest order; key: the language behind a mark, so that none is null. One row of each language has an empty gram: logp is
    that of a code point never seen, logb the weight of the order below all. More than `most` n-grams are joined."""
    key = F.coalesce(F.concat(F.lit("="), F.col("lang")), F.lit("null"))
    grams = staged(counts.select(key.alias("key"), "gram", "n"), "grams")
    if grams.count() > most:
        return joined_kneser_ney(grams)
    parts = grams.groupBy("key", F.pmod(F.ascii(F.substring("gram", ORDER - 1, 1)), F.lit(PARTS)).alias("part"))
    few = parts.applyInArrow(_part_counts, "key string, k bigint, point bigint, n1 bigint, n2 bigint, n3 bigint, n4 bigint")
    few = few.groupBy("key", "k", "point").agg(*(F.sum(c).alias(c) for c in ("n1", "n2", "n3", "n4"))).orderBy("key", "k", "point").toArrow()
    known, low = {}, []
    keys = few["key"].to_numpy()
    few = np.stack([few[c].to_numpy() for c in few.column_names[1:]]) if len(few) else np.empty((6, 0), np.int64)
    for name, at in zip(*np.unique(keys.astype(str), return_index=True), strict=True):
        own = few[:, at : at + int((keys == name).sum())]
        points, n = own[1:3, own[0] == 1]
        d = np.array(_rates(*_counts_of_counts(n)))[np.minimum(n, 3) - 1]
        lower, weight = 1 / (len(points) + 1), d.sum() / n.sum()  # one more for all that never came
        p = (n - d) / n.sum() + weight * lower
        known[str(name)] = points, p, {int(k): _rates(*m) for k, _, *m in own[:, own[0] > 1].T.tolist()}
        low.append((str(name), "", float(np.log(lower)), float(np.log(weight))))
        low += [(str(name), chr(x), x_log, None) for x, x_log in zip(points.tolist(), np.log(p).tolist(), strict=True)]
    spark, schema = counts.sparkSession, "key string, gram string, logp double, logb double"
    high = parts.applyInArrow(_part_model(sent(spark.sparkContext, known)), schema)
    out = high.union(spark.createDataFrame(low, schema)).groupBy("key", "gram")
    return staged(out.agg(F.max("logp").alias("logp"), F.max("logb").alias("logb")), "model")


def joined_kneser_ney(grams: DataFrame) -> DataFrame:
    """kneser_ney() of staged (key, gram, n) by joins of the orders."""
    tables = {ORDER: grams}
    for k in range(ORDER - 1, 0, -1):
        shorter = tables[k + 1].select("key", F.substring("gram", 2, k).alias("gram"))
        tables[k] = shorter.groupBy("key", "gram").agg(F.count(F.lit(1)).alias("n"))
    points = tables[1].groupBy("key").agg((F.count(F.lit(1)) + 1).alias("points"))  # one more for all that never came
    below = points.select("key", F.lit("").alias("gram"), (1.0 / F.col("points")).alias("p"))
    out = below.select("key", "gram", F.ln("p").alias("logp"))
    weights = None
    for k in range(1, ORDER + 1):
        own = discounted(tables[k]).withColumn("context", F.substring("gram", 1, k - 1)).withColumn("rest", F.substring("gram", 2, k - 1))
        sums = own.groupBy("key", "context").agg(F.sum("n").alias("all"), F.sum("d").alias("freed"))
        sums = staged(sums.select("key", "context", "all", (F.col("freed") / F.col("all")).alias("weight")), f"contexts-{k}")
        lower = below.select("key", F.col("gram").alias("rest"), F.col("p").alias("lower"))
        p = (F.col("n") - F.col("d")) / F.col("all") + F.col("weight") * F.col("lower")
        below = staged(own.join(sums, ["key", "context"]).join(lower, ["key", "rest"]).select("key", "gram", p.alias("p")), f"order-{k}")
        out = out.union(below.select("key", "gram", F.ln("p").alias("logp")))
        weight = sums.select("key", F.col("context").alias("gram"), F.ln("weight").alias("logb"))
        weights = weight if weights is None else weights.union(weight)
    return staged(out.join(weights, ["key", "gram"], "full").select("key", "gram", "logp", "logb"), "model")


def _hasher(k: int):
    """(key, h, logp, logb) of rows (key, gram, logp, logb) with n-grams of k code points."""

    def run(batches):
        for b in batches:
            points = np.frombuffer("".join(b.column(1).to_pylist()).encode("utf-32-le", "surrogatepass"), np.uint32)
            h = gram_hashes(points, k)[::k] if k else np.zeros(len(b), np.uint64)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(h.view(np.int64)), b.column(2), b.column(3)], names=["key", "h", "logp", "logb"])

    return run


def in_piece(table: DataFrame, k: int, piece: int, pieces: int) -> DataFrame:
    """The n-grams of order k that those with a context ending in this piece's code points look up: probabilities by the last but
    one, weights by the last. The two lowest orders are in every piece."""
    own = table.where(F.length("gram") == k)
    if pieces == 1 or k < 2:
        return own
    ends = [k - 1] if k == ORDER else [k - 1, k]
    return own.where(reduce(Column.__or__, (F.ascii(F.substring("gram", at, 1)) % pieces == piece for at in ends)))


class GramModel:
    """Of each language and order sorted hashes with log probabilities and back-off weights: all, or a piece of them."""

    def __init__(self, table: DataFrame, piece: int = 0, pieces: int = 1) -> None:
        """An order at a time, hashed in tasks, so that the driver holds little beside the arrays."""
        none = (np.empty(0, np.uint64), np.empty(0, np.float32), np.empty(0, np.float32))
        self.tables: dict[str, list] = {}
        for k in range(ORDER + 1):
            rows = in_piece(table, k, piece, pieces).select("key", "gram", F.col("logp").cast("float"), F.col("logb").cast("float"))
            rows = rows.mapInArrow(_hasher(k), "key string, h bigint, logp float, logb float").toArrow().combine_chunks()
            keys = rows["key"].combine_chunks().dictionary_encode()
            names = keys.dictionary.to_pylist()
            for at, key in enumerate(names):
                here = rows.filter(pa.compute.equal(keys.indices, at)).combine_chunks()
                h = here["h"].to_numpy().view(np.uint64)
                order = np.argsort(h)
                values = (here[c].combine_chunks().fill_null(null).to_numpy(zero_copy_only=False)[order] for c, null in (("logp", np.nan), ("logb", 0.0)))
                self.tables.setdefault(key, [none] * (ORDER + 1))[k] = (h[order], *values)
            del rows, keys
            trim()

    @property
    def pieces(self) -> list:
        return [lambda: self]

    def find(self, key: str, k: int, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(place, whether it is there) of each hash in an order."""
        own, starts = self.tables[key][k][0], self.__dict__.setdefault("starts", {})
        if (key, k) not in starts:
            starts[key, k] = starts_of(own)
        return find(own, starts[key, k], h)

    def sums(self, key: str, texts: list[str]) -> np.ndarray:
        """Log probability of each text."""
        return text_sums(self.pieces, {key: texts})[key]

    def logs(self, key: str, grams: np.ndarray) -> np.ndarray:
        """Log probability of each row of ORDER code points: by the longest end that is known, with the weights of all longer
        contexts that are. A language never seen has no code points: zero."""
        out = np.zeros(len(grams))
        if key not in self.tables:
            return out
        open_ = np.arange(len(grams))
        for k in range(ORDER, -1, -1):
            _, logp, logb = self.tables[key][k]
            at, found = self.find(key, k, _row_hashes(grams[open_, ORDER - k :]))
            if len(logp):
                found &= ~np.isnan(logp[at])
            out[open_[found]] += logp[at[found]]
            open_ = open_[~found]
            if k and len(open_):
                at, known = self.find(key, k - 1, _row_hashes(grams[open_, ORDER - k : -1]))
                out[open_[known]] += self.tables[key][k - 1][2][at[known]]
        return out

    def window_logs(self, key: str, points: np.ndarray, own: np.ndarray, h: np.ndarray) -> np.ndarray:
        """logs() of the windows that start at own, with their hashes: few but the unseen need more than the highest order."""
        if key not in self.tables:
            return np.zeros(len(own))
        logp = self.tables[key][ORDER][1]
        at, found = self.find(key, ORDER, h)
        out = logp[at].astype(np.float64) if len(logp) else np.full(len(own), np.nan)
        left = np.flatnonzero(~found | np.isnan(out))
        out[left] = self.logs(key, points[own[left][:, None] + np.arange(ORDER)])
        return out


def text_sums(pieces: list, texts: dict[str, list[str]]) -> dict[str, np.ndarray]:
    """Log probability of each text of each key; each n-gram is looked up in its piece."""
    held = []
    for key, own_texts in texts.items():
        points, sizes = padded(own_texts)
        own = _own(sizes)
        held.append((key, sizes, points, own, gram_hashes(points, ORDER)[own], np.zeros(len(own))))
    for piece, get in enumerate(pieces):
        model = get()
        for key, _, points, own, h, logs in held:
            mine = np.flatnonzero(points[own + ORDER - 2] % len(pieces) == piece) if len(pieces) > 1 else slice(None)
            logs[mine] = model.window_logs(key, points, own[mine], h[mine])
        del model
    out = {}
    for key, sizes, *_, logs in held:
        upto, ends = np.concatenate([[0.0], np.cumsum(logs)]), np.cumsum(sizes)
        out[key] = upto[ends] - upto[ends - sizes]
    return out


class SentModel:
    """A model on its way to the workers, once for all uses; its pieces are built and sent one after the other."""

    def __init__(self, table: DataFrame, pieces: int) -> None:
        sc = table.sparkSession.sparkContext
        self.pieces = [sent(sc, GramModel(table, p, pieces), keep=pieces == 1) for p in range(pieces)]


def fit_grams(docs: DataFrame, text: str = "text", lang: str = "lang", max_model: int = MAX_MODEL, piece: int = PIECE) -> SentModel | DataFrame:
    """The model of all documents: arrays where its counted rows are within the bound, else its table. An entry is in two
    pieces at most."""
    model = kneser_ney(count_grams(docs, text, lang), max_model)
    n = model.count()
    return model if n > max_model else SentModel(model, 1 if n <= piece else -(-2 * n // piece))


def _hashes(words: list[bytes]) -> np.ndarray:
    return np.fromiter(map(hash, words), np.int64, len(words)).view(np.uint64)


def repeats(texts: list[np.ndarray]) -> np.ndarray:
    """Of each text, given as hashes of its words, the words that lie in a window of three found at least twice in it."""
    sizes = np.fromiter(map(len, texts), np.int64, len(texts))
    ends, n = np.cumsum(sizes), int(sizes.sum())
    h = np.concatenate([np.empty(0, np.uint64), *texts])
    covered, doc = np.zeros(n, bool), np.repeat(np.arange(len(texts)), sizes)
    starts = np.flatnonzero(doc[2:] == doc[:-2]) if n > 2 else np.empty(0, np.int64)
    w = mix64(h[starts] * np.uint64(0x9E3779B97F4A7C15) + h[starts + 1]) * np.uint64(0xC2B2AE3D27D4EB4F) + h[starts + 2]
    w = mix64(w) + doc[starts].astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    order = np.argsort(w)
    same = np.flatnonzero(w[order[1:]] == w[order[:-1]])
    twice = starts[np.concatenate([order[same], order[same + 1]])]
    for k in range(3):
        covered[twice + k] = True
    upto = np.concatenate([[0], np.cumsum(covered)])
    return upto[ends] - upto[ends - sizes]


def repeat_words(words: list[bytes]) -> int:
    return int(repeats([_hashes(words)])[0])


def measured(texts: list[bytes]) -> list[tuple[int, int, int, int, int]]:
    """(n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words) of each text."""
    out, hashes = [], []
    for text in texts:
        words = text.split()
        hashes.append(_hashes(words))
        lines = [x for x in text.split(b"\n") if x.strip()]
        out.append((len(words), len(text.translate(None, BLANKS + TAIL_BYTES)), sum(map(text.count, _SYMBOLS)), len(lines) - len(set(lines))))
    return [(*row, n) for row, n in zip(out, repeats(hashes).tolist(), strict=True)]


def measures(text: bytes | None) -> tuple[int, int, int, int, int]:
    return measured([text or b""])[0]


def fails_base(n_words: int, n_repeat: int) -> bool:
    return n_words < MIN_WORDS or 100 * n_repeat > MAX_REPEAT_PERCENT * n_words


QUALITY = "struct<n_words:bigint,word_chars:bigint,n_symbols:bigint,n_dup_lines:bigint,n_repeat_words:bigint,base_failed:boolean,level:int,n_chars:bigint>"


def _levels(model: SentModel | GramModel, langs: list[str | None], texts: list[str]) -> np.ndarray:
    sums, kinds = np.zeros(len(texts)), {}
    for i, lang in enumerate(langs):
        kinds.setdefault("null" if lang is None else f"={lang}", []).append(i)
    for key, found in text_sums(model.pieces, {key: [texts[i] for i in places] for key, places in kinds.items()}).items():
        sums[kinds[key]] = found
    return np.floor(-sums / np.maximum([len(t) for t in texts], 1) * STEPS + 1e-6).astype(np.int32)


def _judge(model: SentModel | None):
    names = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]

    @F.arrow_udf(QUALITY)
    def judge(text: pa.Array, lang: pa.Array) -> pa.Array:
        rows, levels, at, waiting = [], [], 0, []
        langs = lang.to_pylist()

        def settle():
            nonlocal at
            levels.append(_levels(model, langs[at : at + len(waiting)], waiting))
            at += len(waiting)
            waiting.clear()

        for chunk in byte_chunks(text):
            chunk = [t or b"" for t in chunk]
            rows += measured(chunk)
            if model is not None:
                waiting += [t.decode(errors="replace") for t in chunk]
                if len(model.pieces) == 1 or sum(map(len, waiting)) >= WAIT:
                    settle()
        if waiting:
            settle()
        columns = np.array(rows, np.int64).reshape(len(rows), 5)
        arrays = [pa.array(columns[:, i]) for i in range(5)]
        arrays += [pa.array([fails_base(r[0], r[4]) for r in rows], pa.bool_()), pa.array(np.concatenate(levels) if levels else np.zeros(len(rows), np.int32), pa.int32())]
        trim()
        arrays.append(pa.compute.cast(pa.compute.fill_null(pa.compute.utf8_length(text), 0), pa.int64()))
        return pa.StructArray.from_arrays(arrays, names=[*names, "base_failed", "level", "n_chars"])

    return judge


def _explode(batches):
    """(row, key, gram, n, size) of each different n-gram of a document; one row without a gram for an empty text."""
    for batch in batches:
        ids, langs, at = batch.column(0), batch.column(2).to_pylist(), 0
        for chunk in text_chunks(batch.column(1), 16):
            out = []
            for t in chunk:
                row, key = ids[at].as_py(), "null" if langs[at] is None else f"={langs[at]}"
                at += 1
                if t:
                    _, n, grams = _tally([t])
                    text = grams.tobytes().decode("utf-32-le", "surrogatepass")
                    out += [(row, key, text[i : i + ORDER], int(c), len(t)) for i, c in zip(range(0, len(text), ORDER), n, strict=True)]
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*out, strict=True)], names=["row", "key", "gram", "n", "size"])


def joined_levels(rows: DataFrame, model: DataFrame) -> DataFrame:
    """(row, level) of rows (row, text, lang) under a model that is a table: different n-grams meet it by hash partition, first
    whole, then what is not found by its shorter ends, with the weights of the contexts passed."""
    grams = staged(rows.select("row", "text", "lang").mapInArrow(_explode, "row string, key string, gram string, n bigint, size bigint"), "exploded")
    open_ = grams.select("key", "gram").distinct().select("key", "gram", F.col("gram").alias("end"), F.lit(0.0).alias("spent"))
    settled = []
    for k in range(ORDER, -1, -1):
        own = model.where(F.length("gram") == k).select("key", F.col("gram").alias("end"), F.col("logp").cast("float").cast("double").alias("logp"))
        met = staged(open_.join(own, ["key", "end"], "left"), f"met-{k}")
        settled.append(met.where("logp is not null").select("key", "gram", (F.col("logp") + F.col("spent")).alias("log")))
        if k:
            context = model.where(F.length("gram") == k - 1).select("key", F.col("gram").alias("context"), F.col("logb").cast("float").cast("double").alias("logb"))
            left = met.where("logp is null").withColumn("context", F.substring("end", 1, k - 1)).join(context, ["key", "context"], "left")
            open_ = left.select("key", "gram", F.substring("end", 2, k - 1).alias("end"), (F.col("spent") + F.coalesce("logb", F.lit(0.0))).alias("spent"))
    logs = settled[0]
    for part in settled[1:]:
        logs = logs.union(part)
    sums = grams.join(logs, ["key", "gram"], "left").groupBy("row").agg(F.sum(F.col("n") * F.coalesce("log", F.lit(0.0))).alias("log"), F.max("size").alias("size"))
    level = F.floor(-F.col("log") / F.col("size") * STEPS + 1e-6).cast("int")
    return sums.select("row", level.alias("level"))


def score_quality(docs: DataFrame, model: SentModel | DataFrame, text: str = "text", name: str = "quality", lang: str = "lang") -> DataFrame:
    """docs with a struct of measures and the perplexity level. Map-only where the model is arrays; where it is a table, levels
    are joined by language and the md5 of the text."""
    spark = docs.sparkSession
    small_batches(spark)
    if isinstance(model, SentModel):
        return docs.withColumn(name, _judge(model)(F.col(text), F.col(lang)))
    row = F.concat_ws(":", F.md5(F.coalesce(F.col(text), F.lit(""))), F.length(text), F.coalesce(F.concat(F.lit("="), F.col(lang)), F.lit("null")))
    levels = joined_levels(docs.select(row.alias("row"), F.col(text).alias("text"), F.col(lang).alias("lang")).dropDuplicates(["row"]), model).withColumnsRenamed({"row": "__mp_of", "level": "__mp_level"})
    measured = docs.withColumn(name, _judge(None)(F.col(text), F.col(lang))).withColumn("__mp_row", row)
    out = measured.join(levels, F.col("__mp_row") == F.col("__mp_of"), "left")
    return out.withColumn(name, F.col(name).withField("level", F.coalesce("__mp_level", F.lit(0)))).drop("__mp_row", "__mp_of", "__mp_level")


def _quantiles(levels: DataFrame, cuts: dict[str, float]) -> DataFrame:
    """(lang, n, the cuts) from (lang, level) rows: a histogram by language and level, then weighted quantiles of it."""
    by_level = levels.groupBy("lang", "level").agg(F.count(F.lit(1)).alias("n"))
    upto = Window.partitionBy("lang").orderBy("level").rowsBetween(Window.unboundedPreceding, 0)
    ranked = by_level.select("lang", "level", F.sum("n").over(upto).alias("upto"), F.sum("n").over(Window.partitionBy("lang")).alias("all"))
    at = lambda share: F.min(F.when(F.col("upto") >= F.col("all") * share, F.col("level")))
    return ranked.groupBy("lang").agg(F.max("all").alias("n"), *(at(share).alias(c) for c, share in cuts.items()))


def distance(level: Column, mid: Column, n_chars: Column) -> Column:
    """Steps from the median, fewer for short texts."""
    return F.floor((level - mid) * F.sqrt(n_chars / (n_chars + SHORT)) + 0.5).cast("int")


def bands(levels: DataFrame) -> DataFrame:
    """(lang, mid, low, high) from (lang, level, n_chars, good) rows; good is true for documents that a rater found good, else
    false or null. Documents pass whose distance from mid lies between low and high."""
    mids = staged(_quantiles(levels, {"mid": 0.5}).withColumnRenamed("lang", "of"), "mids")
    near = levels.join(F.broadcast(mids) if mids.count() <= MAX_BROADCAST_LANGS else mids, F.col("lang").eqNullSafe(F.col("of"))).select("lang", distance(F.col("level"), F.col("mid"), F.col("n_chars")).alias("level"), "good")
    every = _quantiles(near, {"p5": 0.05, "p95": 0.95}).select(F.col("lang").alias("in"), (F.greatest(F.col("p95") - F.col("p5"), F.lit(MIN_SPREAD)) * WIDE).alias("reach"))
    good = _quantiles(near.where("good"), {"least": LOW_SHARE, "most": HIGH_SHARE}).withColumnRenamed("n", "n_good")
    both = mids.join(every, F.col("of").eqNullSafe(F.col("in"))).join(good, F.col("of").eqNullSafe(F.col("lang")), "left")
    enough, margin = F.coalesce(F.col("n_good") >= LEAST_GOOD, F.lit(False)), (F.col("most") - F.col("least")) * MARGIN
    low = F.when(enough, F.least(F.col("least") - margin, F.lit(-MIN_SPREAD))).otherwise(-F.col("reach"))
    high = F.when(enough, F.greatest(F.col("most") + margin, F.lit(MIN_SPREAD))).otherwise(F.col("reach"))
    return both.select(F.col("of").alias("lang"), F.col("mid").cast("double").alias("mid"), low.cast("double").alias("low"), high.cast("double").alias("high"))


#: Languages whose bands are broadcast; with more, texts are joined with them by a shuffle.
MAX_BROADCAST_LANGS = 10_000


def band_table(levels: DataFrame) -> DataFrame:
    """bands(), computed once, under the name __mp_lang; broadcast where its counted size is within the bound."""
    out = staged(bands(levels).withColumnsRenamed({c: f"__mp_{c}" for c in ("lang", "mid", "low", "high")}), "bands")
    return F.broadcast(out) if out.count() <= MAX_BROADCAST_LANGS else out


def within(q: str) -> Column:
    """Whether a document with these fields passes, beside its language's band."""
    at = distance(F.col(f"{q}level"), F.col("__mp_mid"), F.col(f"{q}n_chars"))
    return F.coalesce(~F.col(f"{q}base_failed") & (at >= F.col("__mp_low")) & (at <= F.col("__mp_high")), F.lit(False))


def rated_good(docs: DataFrame, labels: DataFrame | None, doc_id: str) -> DataFrame:
    """(id, good): ids that labels (doc_id, quality) call good; the bands need no more of the labels."""
    ids = labels.where("quality = 1").select(F.col("doc_id").alias("__mp_id")) if labels is not None else docs.select(F.col(doc_id).alias("__mp_id")).limit(0)
    return ids.where("__mp_id is not null").distinct().withColumn("__mp_good", F.lit(True))


def quality_report(docs: DataFrame, labels: DataFrame | None = None, doc_id: str = "doc_id", max_model: int = MAX_MODEL) -> DataFrame:
    """One row a document: the base measures, base_failed, kept, and the level with its band."""
    scored = score_quality(docs.select(F.col(doc_id).alias("doc_id"), "text", "lang"), fit_grams(docs, max_model=max_model)).select("doc_id", "lang", "quality.*")
    scored = staged(scored, "quality")
    good = rated_good(docs, labels, doc_id)
    levels = scored.where(~F.col("base_failed")).join(good, F.col("doc_id") == F.col("__mp_id"), "left").select("lang", "level", "n_chars", F.col("__mp_good").alias("good"))
    judged = scored.join(band_table(levels), F.col("lang").eqNullSafe(F.col("__mp_lang")), "left")
    return judged.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", within("").alias("kept"), "level", "n_chars", *(F.col(f"__mp_{c}").alias(c) for c in ("mid", "low", "high")))


def keep_quality(docs: DataFrame, labels: DataFrame | None = None, max_model: int = MAX_MODEL) -> DataFrame:
    """The documents that pass, with their own columns. Texts are scored twice rather than written in between."""
    own, model = docs.columns, fit_grams(docs, max_model=max_model)
    levels = score_quality(docs.select("doc_id", "text", "lang"), model, name="__mp_quality").where("not __mp_quality.base_failed")
    levels = levels.join(rated_good(docs, labels, "doc_id"), F.col("doc_id") == F.col("__mp_id"), "left").select("lang", "__mp_quality.level", "__mp_quality.n_chars", F.col("__mp_good").alias("good"))
    levels = staged(levels, "levels")  # bands read them three times
    per_lang = band_table(levels)
    scored = score_quality(docs.select(F.struct("*").alias("__mp_row"), "text", "lang"), model, name="__mp_quality")
    judged = scored.join(per_lang, F.col("lang").eqNullSafe(F.col("__mp_lang")), "left")
    return judged.where(within("__mp_quality.")).select(*(F.col("__mp_row")[c].alias(c) for c in own))

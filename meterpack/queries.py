"""The query catalogue: each query with its twin in SQL, where SQL can say it."""

from __future__ import annotations

import uuid
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from meterpack.functions import sql as functions
from meterpack.kernels.arith import ac_decode, ac_encode, adaptive_decode, adaptive_encode, gaussian_decode, gaussian_encode
from meterpack.kernels.bwt import bwt, bwt_inverse
from meterpack.kernels.codec import Config
from meterpack.kernels.huffman import huffman_decode, huffman_encode
from meterpack.kernels.lz import lz77_decode, lz77_encode, lz78_decode, lz78_encode, lzw_decode, lzw_encode
from meterpack.kernels.mtf import mtf, mtf_inverse
from meterpack.kernels.rle import THRESHOLDS, ideal_bits, rle_classes, rle_classes_inverse, rle_dynamic, rle_dynamic_inverse, rle_static, rle_static_inverse, rle_tokens, rle_tokens_inverse
from meterpack.operators import cluster, measures, transform
from meterpack.operators.baselines import single
from meterpack.operators.firststage import first_stage_inverse, rows_of
from meterpack.operators.ranks import dense_ranks, shared_dir
from meterpack.plans import experiments
from meterpack.plans.recompress import batch_by_rank, compression_ratio, md5_draw, recompress, recover_readings, recover_streams
from meterpack.sources import carriers as C
from meterpack.sources import container

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def query(f=None, *, sql: str | None = None, name: str | None = None):
    def add(f):
        QUERIES[name or f.__name__] = f
        if sql is not None:
            SQL[name or f.__name__] = sql
        return f

    return add(f) if f else add


def integers(df: DataFrame, *names: str) -> DataFrame:
    return df.withColumns({n: F.col(n).cast("int") for n in names})


# ---------------------------------------------------------------- streams


def _numbered_sql(table: str, stream: str, order: str, sym: str) -> str:
    return f"SELECT CAST({stream} AS BIGINT) AS stream_id, CAST(row_number() OVER (PARTITION BY {stream} ORDER BY {order}) - 1 AS INTEGER) AS pos, CAST({sym} AS BIGINT) AS sym FROM {table}"


def _words_sql(inner: str) -> str:
    return f"SELECT stream_id, CAST(pos * 2 + h AS INTEGER) AS pos, CASE WHEN h = 0 THEN sym >> 16 ELSE sym & 65535 END AS sym FROM ({inner}) CROSS JOIN (VALUES (0), (1)) t(h)"


LINES = "l_shipdate, l_orderkey, l_linenumber, l_partkey, l_extendedprice"
CENTS = "CAST(round(value * 100) AS BIGINT)"
SLOT = "CAST(floor((epoch(ts) - epoch(TIMESTAMP '2024-01-01')) / 1800) AS INTEGER)"
S1 = _numbered_sql("events", "user_id", "ts, event_id", "round(value * 100)")
S2 = f"""SELECT u.user_id AS stream_id, CAST(g.i AS INTEGER) AS pos, coalesce(e.sym, 0) AS sym FROM (SELECT DISTINCT user_id FROM events) u
CROSS JOIN (SELECT unnest(range(1440)) AS i) g LEFT JOIN (SELECT user_id, {SLOT} AS slot, CAST(sum({CENTS}) AS BIGINT) AS sym FROM events GROUP BY ALL) e ON e.user_id = u.user_id AND e.slot = g.i"""
S3 = _numbered_sql("lineitem", "l_suppkey", LINES, "l_quantity")
S4 = _words_sql(_numbered_sql("lineitem", "l_suppkey", LINES, "round(l_extendedprice * 100)"))
S5 = """SELECT s.l_suppkey AS stream_id, CAST(g.i AS INTEGER) AS pos, coalesce(e.sym, 0) AS sym FROM (SELECT DISTINCT l_suppkey FROM lineitem) s
CROSS JOIN (SELECT unnest(range(CAST(date_diff('day', min(CAST(l_shipdate AS DATE)), max(CAST(l_shipdate AS DATE))) AS BIGINT) + 1)) AS i FROM lineitem) g
LEFT JOIN (SELECT l_suppkey, date_diff('day', (SELECT min(CAST(l_shipdate AS DATE)) FROM lineitem), CAST(l_shipdate AS DATE)) AS slot, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS sym FROM lineitem GROUP BY ALL) e
ON e.l_suppkey = s.l_suppkey AND e.slot = g.i"""
S6 = _words_sql(_numbered_sql("orders", "o_custkey", "o_orderdate, o_orderkey", "round(o_totalprice * 100)"))
S7 = "SELECT vec_id AS stream_id, CAST(i AS INTEGER) AS pos, CAST(round(CAST(embedding[i + 1] AS DOUBLE) * 1000) AS BIGINT) + 600 AS sym FROM embeddings, (SELECT unnest(range(64)) AS i)"
S9 = " UNION ALL ".join(_numbered_sql(f"(SELECT {i} AS s, {k} AS k, {v} AS v FROM {t})", "s", "k", "v") for i, (t, k, v) in enumerate((("part", "p_partkey", "p_size"), ("customer", "c_custkey", "c_nationkey"), ("supplier", "s_suppkey", "s_nationkey"))))
STREAM_SQL = {"meter_value": S1, "meter_grid": S2, "supplier_qty": S3, "supplier_price": S4, "supplier_day": S5, "customer_orders": S6, "vector_int": S7, "dim_codes": S9}
STREAM_NAMES = {"meter_value": "meter_value_stream", "meter_grid": "meter_grid_stream", "supplier_qty": "supplier_qty_stream", "supplier_price": "supplier_price_words", "supplier_day": "supplier_day_stream", "customer_orders": "customer_orders_stream", "vector_int": "vector_int_stream", "dim_codes": "dim_codes_stream"}
for _carrier, _name in STREAM_NAMES.items():
    query(lambda s, d, c=_carrier: integers(C.carrier(s, d, c), "pos"), sql=STREAM_SQL[_carrier], name=_name)


@query(sql=f"SELECT stream_id, pos, sym FROM ({S2}) WHERE stream_id IN (SELECT DISTINCT user_id FROM events ORDER BY 1 LIMIT 3)")
def three_houses(s, d):
    return integers(C.three_houses(s, d), "pos")


@query(sql=f"SELECT stream_id, count(*) AS n, CAST(sum(sym) AS BIGINT) AS total FROM ({S2}) WHERE stream_id IN (SELECT DISTINCT user_id FROM events ORDER BY 1 LIMIT 400) GROUP BY 1")
def premises_400(s, d):
    return C.premises(s, d).groupBy("stream_id").agg(F.count(F.lit(1)).alias("n"), F.sum("sym").alias("total"))


# ---------------------------------------------------------------- entropy


def _entropy_sql(rows: str, group: str) -> str:
    keys = f"{group}, " if group else ""
    return f"WITH c AS (SELECT {keys}sym, count(*) AS c FROM ({rows}) GROUP BY ALL) SELECT {keys}CAST(sum(c) AS BIGINT) AS n, count(*) AS n_distinct, round(abs(log2(sum(c)) - sum(c * log2(c)) / sum(c)), 6) AS h, round(log2(count(*)), 6) AS h_max FROM c {'GROUP BY ' + group if group else ''}"


@query(sql=_entropy_sql(S2, "stream_id"))
def entropy_per_stream(s, d):
    return measures.entropy(C.meter_grid(s, d), "stream_id")


_POOL = " UNION ALL ".join(f"SELECT '{c}' AS carrier, sym FROM ({q})" for c, q in STREAM_SQL.items())


@query(sql=_entropy_sql(_POOL, "carrier"))
def entropy_pooled(s, d):
    return measures.entropy(experiments._all([C.carrier(s, d, c).select(F.lit(c).alias("carrier"), "sym") for c in STREAM_SQL]), "carrier")


@query(sql=f"SELECT stream_id, h >= 0 AND h <= h_max + 1e-6 AND h_max <= round(log2(n), 6) AS within FROM ({_entropy_sql(S1, 'stream_id')})")
def entropy_bounds(s, d):
    return measures.entropy(C.meter_value(s, d), "stream_id").select("stream_id", ((F.col("h") >= 0) & (F.col("h") <= F.col("h_max") + 1e-6) & (F.col("h_max") <= F.round(F.log2("n"), 6))).alias("within"))


@query(sql="WITH h AS MATERIALIZED (SELECT doc_id AS stream_id, hex(encode(text)) AS h FROM documents), b AS (SELECT stream_id, unnest(regexp_extract_all(h, '..')) AS sym FROM h) " + _entropy_sql("SELECT * FROM b", "stream_id").replace("WITH c AS", ", c AS", 1))
def text_bytes_entropy(s, d):
    return measures.entropy(C.text_bytes(s, d), "stream_id")


@query(sql="WITH h AS MATERIALIZED (SELECT source, hex(encode(text)) AS h FROM documents), b AS (SELECT source, unnest(regexp_extract_all(h, '..')) AS sym FROM h) " + _entropy_sql("SELECT * FROM b", "source").replace("WITH c AS", ", c AS", 1))
def documents_by_source_entropy(s, d):
    return measures.entropy(C.text_bytes(s, d).join(C.table(s, d, "documents").select(F.col("doc_id").alias("stream_id"), "source"), "stream_id"), "source")


# ---------------------------------------------------------------- grouping and layout

SEED, K = 42, 8
DRAW = f"CAST(CAST('0x' || substr(md5(stream_id || ':{SEED}'), 1, 8) AS BIGINT) % {{k}} AS INTEGER)"


def _drawn(rows: DataFrame, k: int = K) -> DataFrame:
    return rows.withColumn("cluster_id", md5_draw(F.col("stream_id"), SEED, k).cast("int"))


@query(sql=f"SELECT DISTINCT stream_id, {DRAW.format(k=K)} AS cluster_id FROM ({S1})")
def random_grouping(s, d):
    return _drawn(C.meter_value(s, d).select("stream_id").distinct())


def _laid(rows: str, group: str, order: str = "pos, stream_id") -> str:
    return f"SELECT *, CAST(row_number() OVER (PARTITION BY {group} ORDER BY {order}) - 1 AS INTEGER) AS gpos FROM ({rows})"


G1 = _laid(f"SELECT {DRAW.format(k=K)} AS cluster_id, stream_id, pos, sym FROM ({S1})", "cluster_id")
BATCHED = f"SELECT CAST((dense_rank() OVER (ORDER BY stream_id) - 1) // 56 AS BIGINT) AS batch_id, stream_id, pos, sym FROM ({S1})"


def _groups(s, d, name: str = "meter_value") -> DataFrame:
    """(cluster_id, stream_id, pos, sym, gpos): random groups, interleaved."""
    return transform.interleave(_drawn(C.carrier(s, d, name)), "cluster_id")


@query(sql=f"SELECT cluster_id, gpos, stream_id, pos, sym FROM ({G1})")
def interleave_random_groups(s, d):
    return integers(_groups(s, d), "gpos", "pos").select("cluster_id", "gpos", "stream_id", "pos", "sym")


@query(sql=f"SELECT batch_id, gpos, stream_id, pos, sym FROM ({_laid(BATCHED, 'batch_id')})")
def interleave_56(s, d):
    rows = batch_by_rank(C.meter_value(s, d))
    return integers(transform.interleave(rows, "batch_id"), "gpos", "pos").select("batch_id", "gpos", "stream_id", "pos", "sym")


@query(sql=f"SELECT batch_id, gpos, stream_id, pos, sym FROM ({_laid(BATCHED, 'batch_id', 'stream_id, pos')})")
def concatenate_56(s, d):
    rows = batch_by_rank(C.meter_value(s, d))
    return integers(transform.concatenate(rows, "batch_id"), "gpos", "pos").select("batch_id", "gpos", "stream_id", "pos", "sym")


def _delta_sql(rows: str, group: str, order: str = "gpos") -> str:
    return f"SELECT {group}, {order}, CAST(sym - coalesce(lag(sym) OVER (PARTITION BY {group} ORDER BY {order}), 0) AS BIGINT) AS sym FROM ({rows})"


@query(sql=_delta_sql(G1, "cluster_id"))
def delta_interleaved(s, d):
    return integers(transform.delta(_groups(s, d), "cluster_id"), "gpos").select("cluster_id", "gpos", "sym")


@query(sql=_delta_sql(S3, "stream_id", "pos"))
def delta_per_stream(s, d):
    return integers(transform.delta(C.supplier_qty(s, d), "stream_id", order="pos"), "pos").select("stream_id", "pos", "sym")


@query(sql=_delta_sql(_delta_sql(S3, "stream_id", "pos"), "stream_id", "pos"))
def delta_second_order(s, d):
    return integers(transform.delta(C.supplier_qty(s, d), "stream_id", order="pos", times=2), "pos").select("stream_id", "pos", "sym")


@query(sql=S3)
def undelta_roundtrip(s, d):
    there = transform.delta(C.supplier_qty(s, d), "stream_id", order="pos", times=2)
    return integers(transform.undelta(there, "stream_id", order="pos", times=2), "pos").select("stream_id", "pos", "sym")


# ---------------------------------------------------------------- block transforms


def _cells(rows: DataFrame, group: str, order: str) -> DataFrame:
    """(group, x): the symbols of a group in order."""
    return rows.groupBy(group).agg(F.array_sort(F.collect_list(F.struct(order, "sym"))).alias("x")).select(group, F.col("x.sym").alias("x"))


def _through(kernel) -> Callable:
    """An Arrow function that sends each cell forth and back by a kernel."""

    @F.arrow_udf("array<bigint>")
    def run(column: pa.Array) -> pa.Array:
        return pa.array([np.asarray(kernel(x), np.int64) for x in rows_of(column)], pa.list_(pa.int64()))

    return run


ROUND_TRIPS = {
    "bwt": lambda x: bwt_inverse(*bwt(x)),
    "bwt_sentinel": lambda x: bwt_inverse(*bwt(x, "high"), "high"),
    "mtf": lambda x: mtf_inverse(*mtf(x)),
    "rle": lambda x: rle_dynamic_inverse(*rle_dynamic(x)),
    "rle_static": lambda x: rle_static_inverse(*rle_static(x)),
    "rle_token": lambda x: rle_tokens_inverse(*rle_tokens(x)),
    "rle_rank_class": lambda x: (lambda r: mtf_inverse(rle_classes_inverse(*rle_classes(r[0])), r[1]))(mtf(x)),
    "ac": lambda x: ac_decode(*ac_encode(x))[0],
    "ac_adaptive": lambda x: adaptive_decode(*adaptive_encode(x))[0],
    "ac_gaussian": lambda x: gaussian_decode(*gaussian_encode(x), len(x)),
    "huffman": lambda x: huffman_decode(*huffman_encode(x)[:2])[0],
    "lz": lambda x: lz77_decode(lz77_encode(x)),
    "lz78": lambda x: lz78_decode(lz78_encode(x)),
    "lzw": lambda x: np.frombuffer(lzw_decode(lzw_encode(x.astype(">u2").tobytes())), ">u2"),
}
for _name, _kernel in ROUND_TRIPS.items():

    def _trip(s, d, kernel=_kernel):
        cells = _cells(C.supplier_qty(s, d), "stream_id", "pos")
        return cells.select("stream_id", F.posexplode(_through(kernel)("x")).alias("pos", "sym"))

    query(_trip, sql=S3, name=f"{_name}_roundtrip")

ROTATIONS = f"""WITH cells AS (SELECT stream_id, list(sym ORDER BY pos) AS x FROM ({S3}) GROUP BY 1),
r AS (SELECT stream_id, i, list_concat(x[i:], x[:i - 1]) AS rot FROM cells, unnest(range(1, len(x) + 1)) t(i))
SELECT stream_id, CAST(row_number() OVER (PARTITION BY stream_id ORDER BY rot, i) - 1 AS INTEGER) AS row, rot[-1] AS last"""


@query(sql=f"{ROTATIONS}, i = 1 AS is_primary FROM r")
def bwt_last_column(s, d):
    """Every stream, by the kernel."""
    functions.register(s)
    cells = _cells(C.supplier_qty(s, d), "stream_id", "pos").select("stream_id", F.call_function("mp_bwt", "x").alias("b"))
    return cells.select("stream_id", F.col("b.primary").alias("p"), F.posexplode("b.last").alias("row", "last")).select("stream_id", "row", "last", (F.col("row") == F.col("p")).alias("is_primary"))


@query(sql=f"{ROTATIONS} FROM r")
def bwt_relational(s, d):
    """Every stream, by its sorted rotations in expressions."""
    return transform.rotations(_cells(C.supplier_qty(s, d), "stream_id", "pos")).select("stream_id", F.posexplode("last").alias("row", "last"))


def _doubling_sql(rounds: int = 20) -> str:
    """Ranks of all rotations of the pooled symbols by 1, 2, 4 ... symbols: whole for up to 2**rounds of them."""
    ctes = [f"p AS MATERIALIZED (SELECT CAST(row_number() OVER (ORDER BY stream_id, pos) - 1 AS BIGINT) AS gpos, sym FROM ({S3}))", "n AS (SELECT count(*) AS n FROM p)", "r0 AS MATERIALIZED (SELECT gpos, dense_rank() OVER (ORDER BY sym) AS r FROM p)"]
    for j in range(rounds):
        ctes.append(f"r{j + 1} AS MATERIALIZED (SELECT a.gpos, dense_rank() OVER (ORDER BY a.r, b.r) AS r FROM r{j} a JOIN (SELECT (gpos + n - {1 << j} % n) % n AS gpos, r FROM r{j}, n) b ON b.gpos = a.gpos)")
    return f"WITH {', '.join(ctes)} SELECT row_number() OVER (ORDER BY r, a.gpos) - 1 AS row, p.sym AS last FROM r{rounds} a JOIN (SELECT (gpos + 1) % n AS gpos, sym FROM p, n) p ON p.gpos = a.gpos"


@query(sql=_doubling_sql())
def bwt_distributed(s, d):
    """All streams end to end as one sequence, ranked by the whole cluster."""
    rows = dense_ranks(C.supplier_qty(s, d), "stream_id", "pos").select(F.col("rank").alias("gpos"), "sym")
    return transform.bwt_distributed(rows)[0]


@query(sql=f"""WITH x AS ({S3}), a AS (SELECT stream_id, sym AS a, -row_number() OVER (PARTITION BY stream_id ORDER BY sym) AS start FROM (SELECT DISTINCT stream_id, sym FROM x)),
g AS (SELECT x.stream_id, x.pos, x.sym, a.a, coalesce(max(CASE WHEN x.sym = a.a THEN x.pos END) OVER (PARTITION BY x.stream_id, a.a ORDER BY x.pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), a.start) AS at FROM x JOIN a ON a.stream_id = x.stream_id)
SELECT o.stream_id, o.pos, o.sym, count(*) FILTER (WHERE g.at > o.at) AS rank FROM g JOIN g o ON o.stream_id = g.stream_id AND o.pos = g.pos AND o.a = o.sym GROUP BY ALL""")
def mtf_ranks(s, d):
    """Every stream, by expressions alone; the oracle counts the symbols that came later than the own one."""
    return transform.mtf_ranks(_cells(C.supplier_qty(s, d), "stream_id", "pos")).select("stream_id", F.posexplode(F.arrays_zip("x", "ranks")).alias("pos", "z")).select("stream_id", "pos", F.col("z.x").alias("sym"), F.col("z.ranks").alias("rank"))


@query(sql=f"""WITH x AS (SELECT stream_id, pos, sym, lag(sym) OVER (PARTITION BY stream_id ORDER BY pos) AS before, min(sym) OVER (PARTITION BY stream_id) AS least FROM ({S3}))
SELECT stream_id, count(*) FILTER (WHERE sym = before OR (before IS NULL AND sym = least)) AS zeros FROM x GROUP BY 1""")
def mtf_zero_count(s, d):
    functions.register(s)
    ranks = _cells(C.supplier_qty(s, d), "stream_id", "pos").select("stream_id", F.call_function("mp_mtf", "x")["ranks"].alias("r"))
    return ranks.select("stream_id", F.size(F.filter("r", lambda r: r == 0)).cast("bigint").alias("zeros"))


RUNS2 = f"""SELECT stream_id, run_no, any_value(sym) AS sym, count(*) AS len FROM (SELECT stream_id, sym, CAST(sum(head) OVER (PARTITION BY stream_id ORDER BY pos ROWS UNBOUNDED PRECEDING) AS BIGINT) AS run_no
FROM (SELECT stream_id, pos, sym, CASE WHEN sym IS DISTINCT FROM lag(sym) OVER (PARTITION BY stream_id ORDER BY pos) OR pos = 0 THEN 1 ELSE 0 END AS head FROM ({S2}))) GROUP BY stream_id, run_no"""


@query(sql=RUNS2)
def rle_static_runs(s, d):
    return transform.runs(C.meter_grid(s, d), "stream_id", order="pos")


@query(sql=f"SELECT stream_id, count(*) AS n_runs, CAST(sum(len) AS BIGINT) AS n, max(len) AS longest FROM ({RUNS2}) GROUP BY 1")
def rle_static_size(s, d):
    return transform.runs(C.meter_grid(s, d), "stream_id", order="pos").groupBy("stream_id").agg(F.count(F.lit(1)).alias("n_runs"), F.sum("len").alias("n"), F.max("len").alias("longest"))


@query(sql=f"""WITH r AS ({RUNS2}), b AS (SELECT stream_id, greatest(1, length(bin(max(sym)))) AS b, sum(len) AS n FROM r GROUP BY 1),
o AS (SELECT r.stream_id, t, sum(least(len, t)) AS s, count(*) FILTER (WHERE len >= t) AS k, greatest(1, length(bin(coalesce(max(CASE WHEN len >= t THEN len - t END), 0)))) AS c FROM r, (VALUES {", ".join(f"({t})" for t in THRESHOLDS)}) v(t) GROUP BY ALL),
p AS (SELECT o.stream_id, CAST(n * b AS BIGINT) AS off_bits, CAST(s * b + k * c AS BIGINT) AS bits, t FROM o JOIN b ON b.stream_id = o.stream_id)
SELECT stream_id, any_value(off_bits) AS off_bits, least(min(bits), any_value(off_bits)) AS bits, CAST(CASE WHEN min(bits) < any_value(off_bits) THEN arg_min(t, bits * 100 + t) ELSE 0 END AS INTEGER) AS t FROM p GROUP BY 1""")
def rle_dynamic_choice(s, d):
    return transform.dynamic_choice(transform.runs(C.meter_grid(s, d), "stream_id", order="pos"), THRESHOLDS, "stream_id")


@query(sql=f"""WITH c AS (SELECT stream_id, sym, count(*) AS freq FROM ({S3}) GROUP BY ALL)
SELECT stream_id, sym, freq, CAST(sum(freq) OVER (PARTITION BY stream_id ORDER BY sym) - freq AS BIGINT) AS cum, CAST(sum(freq) OVER (PARTITION BY stream_id) AS BIGINT) AS total FROM c""")
def ac_cumulative_ranges(s, d):
    return transform.cumulative(C.supplier_qty(s, d), "stream_id")


@query(sql=f"WITH c AS (SELECT stream_id, sym, count(*) AS c FROM ({S3}) GROUP BY ALL) SELECT stream_id, round(abs(sum(c) * log2(sum(c)) - sum(c * log2(c))), 4) AS bits FROM c GROUP BY 1")
def ac_ideal_bits(s, d):
    return measures.ideal_bits(C.supplier_qty(s, d), "stream_id")


def _holds(kernel) -> Callable:
    @F.arrow_udf("boolean")
    def run(column: pa.Array) -> pa.Array:
        return pa.array([bool(kernel(x)) for x in rows_of(column)], pa.bool_())

    return run


EACH_TRUE = f"SELECT DISTINCT stream_id, true AS holds FROM ({S3})"


@query(sql=EACH_TRUE)
def ac_payload_bounds(s, d):
    """The payload has between the ideal bits less one and those plus 34 and one in 2,048 symbols."""

    def within(x):
        bits, ideal = 8 * len(ac_encode(x)[0]), ideal_bits(x)
        return ideal - 1 <= bits <= ideal + 34 + len(x) / 2048

    return _cells(C.supplier_qty(s, d), "stream_id", "pos").select("stream_id", _holds(within)("x").alias("holds"))


@query(sql=EACH_TRUE)
def huffman_bounds(s, d):
    """Entropy <= mean bits < entropy + 1."""
    return _cells(C.supplier_qty(s, d), "stream_id", "pos").select("stream_id", _holds(lambda x: ideal_bits(x) - 1e-6 <= huffman_encode(x)[2] < ideal_bits(x) + len(x))("x").alias("holds"))


# ---------------------------------------------------------------- k-means

KM = 4
D2 = "CAST(list_sum(list_transform(list_zip({a}, {b}), lambda p: (p[1] - p[2]) * (p[1] - p[2]))) AS {t})"
VECTORS = f"SELECT stream_id, list(sym ORDER BY pos) AS vec FROM ({S7}) GROUP BY 1"


def _seed_ctes(k: int = KM, seed: int = SEED) -> str:
    out = [f"v AS ({VECTORS})", f"s0 AS (SELECT 0 AS cluster_id, stream_id, vec FROM v ORDER BY md5(stream_id || ':{seed}:0') LIMIT 1)"]
    for r in range(1, k):
        near = f"SELECT v.stream_id, any_value(v.vec) AS vec, min({D2.format(a='v.vec', b='c.vec', t='BIGINT')}) AS w FROM v, s{r - 1} c GROUP BY v.stream_id"
        run = f"SELECT *, sum(w) OVER (ORDER BY stream_id) AS upto, sum(w) OVER () AS total FROM ({near})"
        hit = f"(SELECT {r}, stream_id, vec FROM ({run}) WHERE upto > CAST('0x' || substr(md5('0:{seed}:{r}'), 1, 12) AS BIGINT) % total ORDER BY stream_id LIMIT 1)"
        out.append(f"s{r} AS (SELECT * FROM s{r - 1} UNION ALL {hit})")
    return ",\n".join(out) + f",\nc0 AS (SELECT cluster_id, list_transform(vec, lambda x: CAST(x AS DOUBLE)) AS centroid FROM s{k - 1})"


def _assign_cte(i: int) -> str:
    d = D2.format(a="v.vec", b="c.centroid", t="DOUBLE")
    return f"a{i} AS (SELECT stream_id, CAST(cluster_id AS INTEGER) AS cluster_id, dist2, vec FROM (SELECT v.stream_id, v.vec, c.cluster_id, {d} AS dist2, row_number() OVER (PARTITION BY v.stream_id ORDER BY {d}, c.cluster_id) AS rn FROM v, c{i} c) WHERE rn = 1)"


def _update_cte(i: int) -> str:
    return f"c{i + 1} AS (SELECT cluster_id, list(m ORDER BY dim) AS centroid FROM (SELECT cluster_id, dim, CAST(sum(vec[dim]) AS DOUBLE) / count(*) AS m FROM a{i}, unnest(range(1, 65)) t(dim) GROUP BY ALL) GROUP BY 1)"


def _vectors(s, d) -> DataFrame:
    return cluster.padded(C.vector_int(s, d))


@query(sql=f"WITH {_seed_ctes()} SELECT CAST(cluster_id AS INTEGER) AS cluster_id, stream_id FROM s{KM - 1}")
def kmeans_seeds(s, d):
    return cluster.seed_rows(_vectors(s, d), KM, SEED).select("cluster_id", "stream_id")


def _first_centers(s, d):
    return cluster.as_centers(cluster.seed_rows(_vectors(s, d), KM, SEED))


@query(sql=f"WITH {_seed_ctes()}, {_assign_cte(0)} SELECT stream_id, cluster_id, dist2 FROM a0")
def kmeans_assign_step(s, d):
    return cluster.assign(_vectors(s, d), _first_centers(s, d)).drop("vec")


@query(sql=f"WITH {_seed_ctes()}, {_assign_cte(0)}, {_update_cte(0)} SELECT CAST(cluster_id AS INTEGER) AS cluster_id, CAST(i - 1 AS INTEGER) AS dim, round(centroid[i], 6) AS x FROM c1, unnest(range(1, 65)) t(i)")
def kmeans_update_step(s, d):
    return cluster.update(cluster.assign(_vectors(s, d), _first_centers(s, d))).select("cluster_id", F.posexplode("centroid").alias("dim", "x")).withColumn("x", F.round("x", 6))


ROUNDS = 3


@query(sql=f"WITH {_seed_ctes()}, {', '.join(_assign_cte(i) + (', ' + _update_cte(i) if i < ROUNDS - 1 else '') for i in range(ROUNDS))} " + " UNION ALL ".join(f"SELECT {i} AS iter, round(sum(dist2), 3) AS wcss FROM a{i}" for i in range(ROUNDS)))
def kmeans_wcss_trace(s, d):
    v = _vectors(s, d)
    *_, trace = cluster.lloyd(v, _first_centers(s, d), ROUNDS)
    return s.createDataFrame([(i, round(w, 3)) for i, w in enumerate(trace)], "iter int, wcss double")


@query(sql=f"WITH {_seed_ctes()}, {_assign_cte(0)} SELECT cluster_id, label, count(*) AS n FROM a0 JOIN embeddings ON vec_id = stream_id GROUP BY ALL")
def kmeans_labels_purity(s, d):
    labels = C.table(s, d, "embeddings").select(F.col("vec_id").alias("stream_id"), "label")
    return measures.purity(cluster.assign(_vectors(s, d), _first_centers(s, d)).join(labels, "stream_id"))


@query
def kmeans_global(s, d):
    """Driver loop to convergence from race seeds, with the adjusted Rand index of the result against the true labels."""
    v = _vectors(s, d)
    assigned, _, trace = cluster.lloyd(v, cluster.as_centers(cluster.race_seeds(v, 10, SEED)))
    labels = C.table(s, d, "embeddings").select(F.col("vec_id").alias("stream_id"), "label")
    return measures.adjusted_rand(assigned.join(labels, "stream_id")).select("ari", F.lit(len(trace)).alias("rounds"), F.lit(round(trace[-1], 3)).alias("wcss"))


@query
def kmeans_mllib(s, d):
    labels = C.table(s, d, "embeddings").select(F.col("vec_id").alias("stream_id"), "label")
    return measures.adjusted_rand(cluster.mllib(_vectors(s, d), 10).join(labels, "stream_id"))


# ---------------------------------------------------------------- Silhouette


def _silhouette_ctes(draw: str) -> str:
    longest = f"(SELECT max(len) FROM (SELECT count(*) AS len FROM ({S3}) GROUP BY stream_id))"
    return f"""x AS (SELECT stream_id, list(sym ORDER BY pos) AS x FROM ({S3}) GROUP BY 1), v AS (SELECT stream_id, list_resize(x, {longest}, 0) AS vec FROM x), g AS (SELECT stream_id, {draw} FROM v CROSS JOIN ks),
d AS (SELECT a.stream_id AS i, b.stream_id AS j, sqrt({D2.format(a="a.vec", b="b.vec", t="DOUBLE")}) AS d FROM v a JOIN v b ON a.stream_id <> b.stream_id),
m AS (SELECT gi.k, i, gi.cluster_id, gj.cluster_id AS other, avg(d) AS m FROM d JOIN g gi ON gi.stream_id = i JOIN g gj ON gj.stream_id = j AND gj.k = gi.k GROUP BY ALL),
xy AS (SELECT k, i AS stream_id, cluster_id, max(m) FILTER (WHERE other = cluster_id) AS x, min(m) FILTER (WHERE other <> cluster_id) AS y FROM m GROUP BY ALL),
s AS (SELECT *, CASE WHEN y IS NULL THEN NULL WHEN x IS NULL THEN 0.0 ELSE round(CAST((y - x) / greatest(x, y) AS DOUBLE), 6) END AS s FROM xy)"""


_S8 = f"WITH ks AS (SELECT {K} AS k), {_silhouette_ctes(DRAW.format(k='k') + ' AS cluster_id, k')}"


def _grouped_vectors(s, d, k: int = K) -> DataFrame:
    return _drawn(cluster.padded(C.supplier_qty(s, d)), k)


@query(sql=f"{_S8} SELECT stream_id, cluster_id, s FROM s")
def silhouette_exact(s, d):
    return measures.silhouette(_grouped_vectors(s, d)).select("stream_id", "cluster_id", "s")


@query(sql=f"SELECT DISTINCT stream_id, true AS agree FROM ({S3})")
def silhouette_forms_agree(s, d):
    return measures.silhouette(_grouped_vectors(s, d)).select("stream_id", (F.abs(F.col("s") - F.col("s_piecewise")) <= 2e-6).alias("agree"))


@query(sql=f"WITH ks AS (SELECT unnest([2, 4, 6, 8, 10, 12]) AS k), {_silhouette_ctes(DRAW.format(k='k') + ' AS cluster_id, k')} SELECT k, round(avg(s), 4) AS silhouette, count(*) AS n FROM s GROUP BY 1")
def silhouette_by_k(s, d):
    """Random groups, which another engine can repeat; with k-means beside them: table_silhouette."""
    names = {f"k{k}": k for k in experiments.KS}
    v = cluster.padded(C.supplier_qty(s, d)).select("stream_id", "vec", *(md5_draw(F.col("stream_id"), SEED, k).cast("int").alias(name) for name, k in names.items()))
    k = F.substring("labelling", 2, 9).cast("int").alias("k")
    return measures.silhouette(v, *names).groupBy(k).agg(F.round(F.avg("s"), 4).alias("silhouette"), F.count(F.lit(1)).alias("n"))


# ---------------------------------------------------------------- experiments


@query
def table_silhouette(s, d):
    """Every carrier, as compressed streams."""
    return experiments.over(experiments.silhouette_by_k, s, d)


@query
def baseline_single_cr(s, d):
    return experiments.single_cr(s, d)


@query
def baseline_collection_cr(s, d):
    return experiments.collection_cr(s, d)


@query
def table_cr_records(s, d):
    """Every carrier, as compressed streams."""
    return experiments.over(experiments.grid, s, d)


@query
def table_cr_means(s, d):
    return experiments.grid_means(experiments.grid(s, d))


@query
def table_cr_means_by_case(s, d):
    """The means of every carrier and first stage."""
    return experiments.over(lambda *a: experiments.grid_means(experiments.grid(*a)), s, d, experiments.CASES[1:])


@query
def table_cr_pivot(s, d):
    """The records as printed: one row each, a column for each configuration."""
    rows = experiments.grid(s, d).withColumn("config", F.concat_ws("_", "rle", "grouping"))
    return rows.groupBy("record", "k").pivot("config", [f"{r}_{g}" for r in ("static", "dynamic") for g in ("random", "kmeans")]).agg(F.first("cr_total"))


@query
def entropy_by_stage(s, d):
    """Every carrier, as compressed streams."""
    return experiments.over(experiments.entropy_by_stage, s, d)


#: A batch's words are what the streams hold, whatever the step; these are counted by the source alone.
@query(sql=f"WITH x AS ({S3}), b AS (SELECT stream_id, (dense_rank() OVER (ORDER BY stream_id) - 1) // 56 AS batch_id, sym FROM x), c AS (SELECT batch_id, sym, count(*) AS c FROM b GROUP BY ALL) SELECT CAST(batch_id AS BIGINT) AS batch_id, CAST(sum(c) AS BIGINT) AS n, round(abs(log2(sum(c)) - sum(c * log2(c)) / sum(c)), 4) AS h FROM c GROUP BY 1")
def entropy_raw_batches(s, d):
    """The first stage of the chain, measured in the batch tasks with all streams of a batch as one group."""
    rows = experiments.entropy_by_stage(s, d, "supplier_qty", "identity", Config(k=1)).where("stage = 'raw' and grouping = 'random'")
    return rows.select("batch_id", "n", F.round("h", 4).alias("h"))


@query
def entropy_means_by_stage(s, d):
    return experiments.entropy_means(experiments.entropy_by_stage(s, d))


@query
def throughput_by_step(s, d):
    return experiments.throughput_by_step(experiments.throughput(s, d))


@query
def stage_ablation(s, d):
    return experiments.ablation(s, d)


@query
def scaling_batch_and_block(s, d):
    return experiments.scaling(s, d)


@query
def four_homes(s, d):
    return experiments.four_homes(s, d)


@query
def pages_lz_cr(s, d):
    """Raw page bytes under the dictionary coders: bits before and after."""
    rows = C.text_bytes(s, d, "pages", "page_id", "html")
    return single(experiments.first_stage(C.blocks(rows, 1 << 16), "identity").withColumn("n_bits", F.col("n_bits") / 2).withColumn("n_bits", F.col("n_bits").cast("bigint")), ("lz77", "lz78", "huffman"))


# ---------------------------------------------------------------- recovery


def _packed(s, d, name: str = "meter_value", coder: str = "gaussian_ac", cfg: Config = Config(grouping="random", k=4)) -> DataFrame:
    return recompress(batch_by_rank(experiments.streams_of(s, d, name, coder)), cfg)


@query(sql=S1)
def recover_readings_meter_value(s, d):
    return recover_readings(_packed(s, d), C.BLOCK)


@query(sql=S2)
def recover_readings_meter_grid(s, d):
    return recover_readings(_packed(s, d, "meter_grid", "delta_gaussian_ac", Config(k=4)), C.SLOTS)


@query(sql=S5)
def recover_readings_supplier_day(s, d):
    return recover_readings(_packed(s, d, "supplier_day", "delta_varint", Config(k=2, rle="rank_class", coder="adaptive")), C.BLOCK)


@query(sql=S4)
def recover_readings_supplier_price(s, d):
    return recover_readings(_packed(s, d, "supplier_price", "delta_huffman", Config(grouping="none", bwt="high", delta_scope="stream")), C.BLOCK)


@query(sql=S6)
def recover_readings_customer_orders(s, d):
    return recover_readings(_packed(s, d, "customer_orders", "identity", Config(k=4, rle="token")), C.BLOCK)


@query(sql=S7)
def recover_readings_vector_int(s, d):
    return recover_readings(_packed(s, d, "vector_int", "gaussian_ac", Config(k=8, seed_scope="region")), C.BLOCK)


@query(sql="WITH h AS MATERIALIZED (SELECT item_id, hex(encode(text)) AS h FROM benchmark) SELECT item_id AS stream_id, CAST(i - 1 AS INTEGER) AS pos, CAST('0x' || h[2 * i - 1:2 * i] AS BIGINT) AS sym FROM h, unnest(range(1, length(h) // 2 + 1)) t(i)")
def recover_readings_text_bytes(s, d):
    return recover_readings(recompress(batch_by_rank(experiments.first_stage(C.blocks(C.text_bytes(s, d, "benchmark", "item_id")), "delta_huffman")), Config(k=2, grouping="random")), C.BLOCK)


@query(sql=S9)
def recover_readings_dim_codes(s, d):
    return recover_readings(_packed(s, d, "dim_codes", "identity", Config(grouping="each", bwt="low")), C.BLOCK)


@query(sql=S3)
def recover_streams_supplier_qty(s, d):
    """Streams first, readings of these second."""
    return first_stage_inverse(recover_streams(_packed(s, d, "supplier_qty", "identity", Config(k=4, coder="huffman"))), C.BLOCK)


SOME = [1, 2, 5]


@query(sql=f"SELECT * FROM ({S1}) WHERE stream_id IN (1, 2, 5)")
def recover_subset(s, d):
    return recover_readings(_packed(s, d), C.BLOCK, SOME)


@query(sql=f"SELECT stream_id, pos, sym, 'x' AS side FROM ({S1}) WHERE false")
def lossless_difference(s, d):
    """Empty: what either side of a round trip lacks."""
    source = integers(C.meter_value(s, d), "pos")
    return measures.lossless(source, recover_readings(_packed(s, d), C.BLOCK))


def _recovered_grid(s, d) -> DataFrame:
    return recover_readings(_packed(s, d, "meter_grid", "delta_varint", Config(grouping="random", k=4)), C.SLOTS)


@query(sql=f"SELECT stream_id, CAST(pos // 48 AS INTEGER) AS day, CAST(sum(sym) AS BIGINT) AS cents, CAST(sum(sym) AS DECIMAL(18, 2)) / 100 >= 100 AS large FROM ({S2}) GROUP BY ALL")
def billing_rollup_on_recovered(s, d):
    days = _recovered_grid(s, d).groupBy("stream_id", F.floor(F.col("pos") / 48).cast("int").alias("day")).agg(F.sum("sym").alias("cents"))
    return days.withColumn("large", F.col("cents").cast("decimal(18,2)") / 100 >= 100)


@query(sql=f"SELECT stream_id, pos, CAST(sum(sym) OVER (PARTITION BY stream_id ORDER BY pos ROWS 3 PRECEDING) AS BIGINT) AS trailing, sym - lag(sym, 48) OVER (PARTITION BY stream_id ORDER BY pos) AS vs_yesterday FROM ({S2})")
def load_window_on_recovered(s, d):
    w = Window.partitionBy("stream_id").orderBy("pos")
    return _recovered_grid(s, d).select("stream_id", "pos", F.sum("sym").over(w.rowsBetween(-3, 0)).alias("trailing"), (F.col("sym") - F.lag("sym", 48).over(w)).alias("vs_yesterday"))


@query(sql=f"""SELECT r_name, n_name, CAST(sum(sym) AS BIGINT) AS load, count(*) AS n FROM ({S2}) JOIN customer ON c_custkey = stream_id JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY CUBE (r_name, n_name)""")
def nation_cube_on_recovered(s, d):
    t = lambda n: C.table(s, d, n)
    rows = _recovered_grid(s, d).groupBy("stream_id").agg(F.sum("sym").alias("load"), F.count(F.lit(1)).alias("n"))
    named = rows.join(t("customer"), F.col("c_custkey") == F.col("stream_id")).join(F.broadcast(t("nation")), F.col("n_nationkey") == F.col("c_nationkey")).join(F.broadcast(t("region")), F.col("r_regionkey") == F.col("n_regionkey"))
    return named.cube("r_name", "n_name").agg(F.sum("load").alias("load"), F.sum("n").alias("n"))


# ---------------------------------------------------------------- relational operators

MANIFEST = f"(SELECT DISTINCT stream_id FROM ({S1}) WHERE {DRAW.format(k=2)} = 0)"


def _manifest(s, d) -> DataFrame:
    """Streams packed so far: half of the meters, by a random draw."""
    half = _drawn(experiments.streams_of(s, d, "meter_value", "identity"), 2).where("cluster_id = 0").drop("cluster_id")
    return recompress(batch_by_rank(half), Config(grouping="none")).select(F.explode("stream_ids").alias("stream_id"))


USERS = "(SELECT user_id AS stream_id, count(*) AS n FROM events GROUP BY 1)"


def _users(s, d) -> DataFrame:
    return C.table(s, d, "events").groupBy(F.col("user_id").alias("stream_id")).agg(F.count(F.lit(1)).alias("n"))


@query(sql=f"SELECT * FROM {USERS} WHERE stream_id IN {MANIFEST}")
def op_semi_packed_streams(s, d):
    return _users(s, d).join(_manifest(s, d), "stream_id", "left_semi")


@query(sql=f"SELECT * FROM {USERS} WHERE stream_id NOT IN {MANIFEST}")
def op_anti_unpacked(s, d):
    return _users(s, d).join(_manifest(s, d), "stream_id", "left_anti")


@query(sql=f"SELECT stream_id, n, m.stream_id IS NOT NULL AS packed FROM {USERS} FULL OUTER JOIN {MANIFEST} m USING (stream_id)")
def op_full_outer_diff(s, d):
    m = _manifest(s, d).withColumn("packed", F.lit(True))
    return _users(s, d).join(m, "stream_id", "full_outer").select("stream_id", "n", F.coalesce("packed", F.lit(False)).alias("packed"))


@query(sql=f"""SELECT b.day, count(*) AS n, CAST(sum({CENTS}) AS BIGINT) AS cents FROM events JOIN (SELECT CAST(i AS INTEGER) AS day, TIMESTAMP '2024-01-01' + to_days(CAST(i AS INTEGER)) AS lo, TIMESTAMP '2024-01-01' + to_days(CAST(i + 1 AS INTEGER)) AS hi FROM (SELECT unnest(range(30)) AS i)) b ON ts >= lo AND ts < hi GROUP BY 1""")
def op_range_billing(s, d):
    """Readings in billing windows: the window is a function of the time, so a range join becomes an equi-join, and the
    range stays as a check."""
    start = F.lit(C.ORIGIN).cast("timestamp_ntz")
    days = s.range(30).select(F.col("id").cast("int").alias("day"), F.timestamp_add("DAY", F.col("id").cast("int"), start).alias("lo"), F.timestamp_add("DAY", (F.col("id") + 1).cast("int"), start).alias("hi"))
    events = C.table(s, d, "events").select("ts", C.cents("value").alias("c"), F.floor(F.timestamp_diff("SECOND", start, F.col("ts")) / 86400).cast("int").alias("day"))
    return events.join(F.broadcast(days), "day").where("ts >= lo AND ts < hi").groupBy("day").agg(F.count(F.lit(1)).alias("n"), F.sum("c").alias("cents"))


@query(sql=f"SELECT o_orderkey, user_id AS stream_id, e.event_id FROM (SELECT o_orderkey, o_custkey, TIMESTAMP '2024-01-01' + to_seconds(CAST(o_orderkey % 2592000 AS INTEGER)) AS t FROM orders) o ASOF JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events GROUP BY ALL) e ON e.user_id = o.o_custkey AND e.ts <= o.t")
def op_asof_reading(s, d):
    """The last reading of a meter at or before a moment: both sides go through one window by meter and time."""
    start = F.lit(C.ORIGIN).cast("timestamp_ntz")
    moments = C.table(s, d, "orders").select(F.col("o_custkey").alias("stream_id"), F.timestamp_add("SECOND", (F.col("o_orderkey") % 2592000).cast("int"), start).alias("ts"), F.lit(None).cast("bigint").alias("event_id"), "o_orderkey")
    events = C.table(s, d, "events").select(F.col("user_id").alias("stream_id"), "ts", "event_id", F.lit(None).cast("bigint").alias("o_orderkey"))
    w = Window.partitionBy("stream_id").orderBy("ts", F.col("o_orderkey").asc_nulls_first(), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    found = events.unionByName(moments).withColumn("event_id", F.last("event_id", ignorenulls=True).over(w))
    return found.where("o_orderkey is not null and event_id is not null").select("o_orderkey", "stream_id", "event_id")


BUSY = """(SELECT user_id AS stream_id, min(ts) AS lo, max(ts) AS hi FROM (SELECT user_id, ts, sum(head) OVER (PARTITION BY user_id ORDER BY ts) AS n FROM
(SELECT user_id, ts, CASE WHEN ts <= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 2 HOUR THEN 0 ELSE 1 END AS head FROM events)) GROUP BY user_id, n HAVING min(ts) < max(ts))"""


def _busy(s, d) -> DataFrame:
    """(stream_id, lo, hi) of the stretches in which a meter is never silent for more than two hours."""
    w = Window.partitionBy("stream_id").orderBy("ts")
    events = C.table(s, d, "events").select(F.col("user_id").alias("stream_id"), "ts")
    marked = events.withColumn("head", F.when(F.col("ts") <= F.lag("ts").over(w) + F.expr("interval 2 hours"), 0).otherwise(1))
    numbered = marked.withColumn("n", F.sum("head").over(w))
    return numbered.groupBy("stream_id", "n").agg(F.min("ts").alias("lo"), F.max("ts").alias("hi")).where("lo < hi").drop("n")


@query(sql=f"SELECT a.stream_id AS a, b.stream_id AS b, CAST(floor(epoch(greatest(a.lo, b.lo))) AS BIGINT) AS since, CAST(floor(epoch(least(a.hi, b.hi)) - epoch(greatest(a.lo, b.lo))) AS BIGINT) AS seconds FROM {BUSY} a JOIN {BUSY} b ON a.stream_id < b.stream_id AND a.lo < b.hi AND b.lo < a.hi")
def op_theta_overlap(s, d):
    """Busy stretches of two meters that overlap. Stretches are dealt to the hours they touch, so that the overlap join is an
    equi-join by hour; a pair counts in the first hour that both touch."""
    since = lambda ts: F.timestamp_diff("SECOND", F.lit("1970-01-01").cast("timestamp_ntz"), F.col(ts))
    hour = lambda ts: F.floor(since(ts) / 3600)
    by_hour = _busy(s, d).withColumn("hour", F.explode(F.sequence(hour("lo"), hour("hi"))))
    a, b = (by_hour.select("hour", *(F.col(c).alias(f"{c}_{x}") for c in ("stream_id", "lo", "hi"))) for x in "ab")
    met = a.join(b, "hour").where("stream_id_a < stream_id_b AND lo_a < hi_b AND lo_b < hi_a").withColumns({"lo": F.greatest("lo_a", "lo_b"), "hi": F.least("hi_a", "hi_b")})
    seconds = F.floor(F.timestamp_diff("MICROSECOND", F.col("lo"), F.col("hi")) / 1_000_000)
    return met.where(F.col("hour") == hour("lo")).select(F.col("stream_id_a").alias("a"), F.col("stream_id_b").alias("b"), since("lo").alias("since"), seconds.alias("seconds"))


@query(sql=f"SELECT stream_id, pos, sym, {DRAW.format(k=K)} AS cluster_id FROM ({S1})")
def op_broadcast_assign(s, d):
    rows = integers(C.meter_value(s, d), "pos")
    return rows.join(_drawn(rows.select("stream_id").distinct()), "stream_id").select("stream_id", "pos", "sym", "cluster_id")


@query(sql=f"WITH v AS ({VECTORS}) SELECT v.stream_id, c.stream_id AS seed, {D2.format(a='v.vec', b='c.vec', t='BIGINT')} AS dist2 FROM v, (SELECT * FROM v ORDER BY stream_id LIMIT 4) c")
def op_cross_dist2(s, d):
    functions.register(s)
    v = _vectors(s, d)
    seeds = v.orderBy("stream_id").limit(4).select(F.col("stream_id").alias("seed"), F.col("vec").alias("c"))
    return v.crossJoin(F.broadcast(seeds)).select("stream_id", "seed", F.call_function("mp_dist2", "vec", "c").alias("dist2"))


_HIGH = f"(SELECT stream_id FROM ({_entropy_sql(S1, 'stream_id')}) WHERE h > 6)"


@query(sql=f"SELECT 'both' AS kind, stream_id FROM (SELECT stream_id FROM {USERS} INTERSECT SELECT stream_id FROM {_HIGH}) UNION ALL SELECT 'low', stream_id FROM (SELECT stream_id FROM {USERS} EXCEPT SELECT stream_id FROM {_HIGH}) UNION ALL SELECT 'any', stream_id FROM (SELECT stream_id FROM {USERS} UNION SELECT stream_id FROM {_HIGH})")
def op_sets_streams(s, d):
    users = _users(s, d).select("stream_id")
    high = measures.entropy(C.meter_value(s, d), "stream_id").where("h > 6").select("stream_id")
    named = lambda df, kind: df.select(F.lit(kind).alias("kind"), "stream_id")
    return named(users.intersect(high), "both").union(named(users.exceptAll(high), "low")).union(named(users.union(high).distinct(), "any"))


_LOADS = f"(SELECT event_type, {SLOT} // 48 AS day, {CENTS} AS c FROM events)"


def _loads(s, d) -> DataFrame:
    return C.table(s, d, "events").select("event_type", F.floor(C.slot_of("ts") / 48).cast("int").alias("day"), C.cents("value").alias("c"))


@query(sql=f"SELECT event_type, day, CAST(sum(c) AS BIGINT) AS cents FROM {_LOADS} GROUP BY GROUPING SETS ((event_type), (day), ())")
def op_grouping_sets(s, d):
    _loads(s, d).createOrReplaceTempView("mp_loads")
    return s.sql("SELECT event_type, day, sum(c) AS cents FROM mp_loads GROUP BY GROUPING SETS ((event_type), (day), ())")


@query(sql="SELECT r_name, c_mktsegment, count(*) AS n FROM customer JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY CUBE (r_name, c_mktsegment)")
def op_cube_region(s, d):
    t = lambda n: C.table(s, d, n)
    named = t("customer").join(F.broadcast(t("nation")), F.col("n_nationkey") == F.col("c_nationkey")).join(F.broadcast(t("region")), F.col("r_regionkey") == F.col("n_regionkey"))
    return named.cube("r_name", "c_mktsegment").agg(F.count(F.lit(1)).alias("n"))


@query(sql=f"SELECT event_type, day, CAST(sum(c) AS BIGINT) AS cents, count(*) AS n FROM {_LOADS} GROUP BY ROLLUP (event_type, day)")
def op_rollup_load(s, d):
    return _loads(s, d).rollup("event_type", "day").agg(F.sum("c").alias("cents"), F.count(F.lit(1)).alias("n"))


_STATUS = ("F", "O", "P")


@query(sql="SELECT o_orderpriority, " + ", ".join(f"count(*) FILTER (WHERE o_orderstatus = '{x}') AS n_{x.lower()}" for x in _STATUS) + " FROM orders GROUP BY 1")
def op_pivot_grid(s, d):
    counts = C.table(s, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", list(_STATUS)).count()
    return counts.select("o_orderpriority", *(F.coalesce(x, F.lit(0)).cast("bigint").alias(f"n_{x.lower()}") for x in _STATUS))


@query(sql=f"SELECT stream_id, count(DISTINCT sym) AS n_distinct, min(sym) AS least, max(sym) AS most, bool_and(sym > 0) AS positive FROM ({S1}) GROUP BY 1")
def op_distinct_symbols(s, d):
    return C.meter_value(s, d).groupBy("stream_id").agg(F.count_distinct("sym").alias("n_distinct"), F.min("sym").alias("least"), F.max("sym").alias("most"), F.bool_and(F.col("sym") > 0).alias("positive"))


@query(sql=f"SELECT stream_id, h FROM ({_entropy_sql(S1, 'stream_id')}) ORDER BY h DESC, stream_id LIMIT 10")
def op_topk_entropy(s, d):
    return measures.entropy(C.meter_value(s, d), "stream_id").select("stream_id", "h").orderBy(F.desc("h"), "stream_id").limit(10)


@query(sql=f"SELECT stream_id, pos, sym, rank() OVER (PARTITION BY stream_id ORDER BY sym DESC) AS r FROM ({S1}) QUALIFY row_number() OVER (PARTITION BY stream_id ORDER BY sym DESC, pos) <= 3")
def op_rank_streams(s, d):
    w = Window.partitionBy("stream_id").orderBy(F.desc("sym"))
    rows = integers(C.meter_value(s, d), "pos").withColumn("r", F.rank().over(w).cast("bigint")).withColumn("n", F.row_number().over(Window.partitionBy("stream_id").orderBy(F.desc("sym"), "pos")))
    return rows.where("n <= 3").drop("n")


@query(sql=f"SELECT stream_id, pos, CAST(sum(sym) OVER (PARTITION BY stream_id ORDER BY pos RANGE BETWEEN 5 PRECEDING AND CURRENT ROW) AS BIGINT) AS load FROM ({S3})")
def op_sliding_load(s, d):
    rows = integers(C.supplier_qty(s, d), "pos")
    return rows.select("stream_id", "pos", F.sum("sym").over(Window.partitionBy("stream_id").orderBy("pos").rangeBetween(-5, 0)).alias("load"))


@query(sql=f"SELECT stream_id, pos, last_value(nullif(sym, 0) IGNORE NULLS) OVER (PARTITION BY stream_id ORDER BY pos ROWS UNBOUNDED PRECEDING) AS sym FROM ({S2})")
def op_ffill_grid(s, d):
    w = Window.partitionBy("stream_id").orderBy("pos").rowsBetween(Window.unboundedPreceding, 0)
    return integers(C.meter_grid(s, d), "pos").select("stream_id", "pos", F.last(F.nullif("sym", F.lit(0)), ignorenulls=True).over(w).alias("sym"))


@query(sql=f"SELECT stream_id, CAST(ntile(4) OVER (ORDER BY md5(stream_id || ':{SEED}')) AS INTEGER) AS record FROM {USERS}")
def op_ntile_records(s, d):
    return experiments.records(_users(s, d)).select("stream_id", "record")


def _utc(df: DataFrame) -> DataFrame:
    return df.select(F.col("user_id").alias("stream_id"), F.col("ts").cast("timestamp").alias("ts"), C.cents("value").alias("sym"))


@query(sql=f"SELECT user_id AS stream_id, {SLOT} AS slot, CAST(sum({CENTS}) AS BIGINT) AS sym FROM events GROUP BY ALL")
def op_tumbling(s, d):
    from meterpack.streaming.front import slot_sums

    slot = ((F.unix_seconds("slot_start") - F.unix_seconds(F.lit(C.ORIGIN).cast("timestamp"))) / C.SLOT_SECONDS).cast("int")
    return slot_sums(_utc(C.table(s, d, "events"))).select("stream_id", slot.alias("slot"), "sym")


@query(sql=f"SELECT CAST(slot + o AS INTEGER) AS start, CAST(sum(c) AS BIGINT) AS load, count(*) AS n FROM (SELECT {SLOT} AS slot, {CENTS} AS c FROM events), (VALUES (0), (-1)) t(o) GROUP BY 1")
def op_sliding_window(s, d):
    from meterpack.streaming.front import sliding_load

    start = ((F.unix_seconds("start") - F.unix_seconds(F.lit(C.ORIGIN).cast("timestamp"))) / C.SLOT_SECONDS).cast("int")
    return sliding_load(_utc(C.table(s, d, "events"))).select(start.alias("start"), "load", "n")


@query(sql="""WITH g AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 2 HOUR OR lag(ts) OVER (PARTITION BY user_id ORDER BY ts) IS NULL THEN 1 ELSE 0 END AS head FROM events),
n AS (SELECT user_id, ts, sum(head) OVER (PARTITION BY user_id ORDER BY ts) AS session FROM g) SELECT user_id AS stream_id, CAST(floor(epoch(min(ts))) AS BIGINT) AS start, count(*) AS n FROM n GROUP BY user_id, session""")
def op_session_window(s, d):
    from meterpack.streaming.front import sessions

    return sessions(_utc(C.table(s, d, "events"))).select("stream_id", F.unix_seconds("start").alias("start"), "n")


@query(sql="SELECT event_type, count(*) AS n, CAST(sum(CAST(json_extract(props, '$.k') AS BIGINT)) AS BIGINT) AS k FROM events GROUP BY 1")
def op_json_props(s, d):
    return C.table(s, d, "events").groupBy("event_type").agg(F.count(F.lit(1)).alias("n"), F.sum(F.from_json("props", "k bigint")["k"]).alias("k"))


@query(sql=f"SELECT stream_id, sym, count(*) AS freq FROM ({S9}) GROUP BY ALL")
def op_map_model(s, d):
    """Symbol counts as a map in one cell, and out of it again."""
    counts = C.dim_codes(s, d).groupBy("stream_id", "sym").agg(F.count(F.lit(1)).alias("freq"))
    models = counts.groupBy("stream_id").agg(F.map_from_entries(F.collect_list(F.struct("sym", "freq"))).alias("model"))
    return models.select("stream_id", F.explode("model").alias("sym", "freq"))


@query(sql="SELECT doc_id, upper(md5(text)) AS digest, length(text) AS n_points, CAST(strlen(text) AS BIGINT) AS n_bytes, substr(text, 1, 8) AS head FROM documents")
def op_string_bytes(s, d):
    return C.table(s, d, "documents").select("doc_id", F.upper(F.md5("text")).alias("digest"), F.length("text").cast("bigint").alias("n_points"), F.octet_length("text").cast("bigint").alias("n_bytes"), F.substring("text", 1, 8).alias("head"))


@query(sql="SELECT l_suppkey AS stream_id, CAST(sum(CAST(round(l_extendedprice * 100) AS BIGINT)) AS DECIMAL(18, 0)) AS cents FROM lineitem GROUP BY 1")
def op_decimal_bill(s, d):
    return C.table(s, d, "lineitem").groupBy(F.col("l_suppkey").alias("stream_id")).agg(F.sum(C.cents("l_extendedprice")).cast("decimal(18,0)").alias("cents"))


@query(sql="SELECT CAST(date_trunc('month', o_orderdate) AS DATE) AS month, count(*) AS n, CAST(date_diff('day', DATE '1992-01-01', CAST(min(o_orderdate) AS DATE)) AS INTEGER) AS first_day FROM orders GROUP BY 1")
def op_date_slots(s, d):
    return C.table(s, d, "orders").groupBy(F.date_trunc("month", F.col("o_orderdate")).cast("date").alias("month")).agg(F.count(F.lit(1)).alias("n"), F.datediff(F.min(F.to_date("o_orderdate")), F.lit("1992-01-01").cast("date")).alias("first_day"))


@query(sql=f"WITH v AS ({VECTORS}) SELECT stream_id, CAST(list_sum(vec) AS BIGINT) AS total, len(list_filter(vec, lambda x: x > 600)) AS above, list_max(vec) AS most, CAST(list_position(vec, list_max(vec)) AS BIGINT) AS at FROM v")
def op_array_hof(s, d):
    v = _vectors(s, d)
    return v.select("stream_id", F.aggregate("vec", F.lit(0).cast("bigint"), lambda a, x: a + x).alias("total"), F.size(F.filter("vec", lambda x: x > 600)).cast("bigint").alias("above"), F.array_max("vec").alias("most"), F.expr("array_position(vec, array_max(vec))").cast("bigint").alias("at"))


@query(sql=f"SELECT stream_id, 0 AS block_no, pos, sym AS word FROM ({S3})")
def op_udtf_unpack(s, d):
    functions.register_unpack(s)
    _packed(s, d, "supplier_qty", "identity", Config(grouping="random", k=4)).createOrReplaceTempView("mp_packed")
    return s.sql("SELECT u.* FROM mp_unpack(TABLE(mp_packed)) u")


@query(sql=f"SELECT stream_id, h FROM ({_entropy_sql(S1, 'stream_id')})")
def op_udaf_entropy(s, d):
    functions.register_entropy(s)
    return C.meter_value(s, d).groupBy("stream_id").agg(F.round(F.call_function("mp_entropy", "sym"), 6).alias("h"))


@query(sql=S3)
def op_sql_functions(s, d):
    """The chain and its inverse, said in SQL."""
    functions.register(s)
    _cells(C.supplier_qty(s, d), "stream_id", "pos").createOrReplaceTempView("mp_cells")
    return s.sql("""WITH b AS (SELECT stream_id, mp_bwt(mp_delta(x)) AS b FROM mp_cells), m AS (SELECT stream_id, b.primary AS p, mp_mtf(b.last) AS m FROM b), r AS (SELECT stream_id, p, m.alphabet AS a, mp_rle(m.ranks) AS r FROM m),
        back AS (SELECT stream_id, p, mp_imtf(named_struct('ranks', mp_irle(r), 'alphabet', a)) AS last FROM r),
        x AS (SELECT stream_id, mp_undelta(mp_ibwt(named_struct('last', last, 'primary', p))) AS x FROM back)
        SELECT stream_id, t.pos, t.sym FROM x, LATERAL posexplode(x) AS t(pos, sym)""")


# ---------------------------------------------------------------- sinks, sources, streaming


def _folder(s) -> str:
    return f"{shared_dir(s)}/run-{uuid.uuid4().hex}"


@query(sql=f"SELECT * FROM ({S5}) WHERE stream_id IN (1, 2, 5)")
def op_packed_sink_roundtrip(s, d):
    """Written by window with a manifest; three streams are found and recovered."""
    path = _folder(s)
    container.write_packed(_packed(s, d, "supplier_day", "delta_varint", Config(grouping="random", k=4)), path)
    return recover_readings(container.find_streams(s, path, SOME), C.BLOCK, SOME)


@query(sql=f"SELECT * FROM ({S1}) WHERE stream_id = 2")
def op_datasource_read(s, d):
    from meterpack.sources.datasource import PackedSource

    s.dataSource.register(PackedSource)
    path = _folder(s)
    container.write_packed(_packed(s, d), path)
    return s.read.format("meterpack").option("path", f"{path}/blocks").option("block_len", C.BLOCK).option("stream_ids", "2").load()


@query(sql=f"SELECT stream_id, pos, sym FROM ({S1})")
def op_stream_replay(s, d):
    """The events as a stream: deduplicated behind a watermark, assembled to blocks of 16, packed in each micro-batch,
    recovered. A second run, after an end-of-input mark, flushes the short last blocks."""
    from meterpack.streaming import front

    path = _folder(s)
    for last in (False, True):
        if last:
            front.close_input(s, f"{path}/marks")
        events = front.read_events(s, d).union(front.marks(s, f"{path}/marks"))
        blocks = front.assemble(front.readings(events), 16)
        blocks.writeStream.foreachBatch(front.pack_sink(f"{path}/packed", "identity")).option("checkpointLocation", f"{path}/state").outputMode("append").trigger(availableNow=True).start().awaitTermination()
    return recover_readings(s.read.parquet(f"{path}/packed").drop("epoch"), 16)


@query(sql=f"""WITH r AS (SELECT event_id, {CENTS} AS sym FROM events), i AS (SELECT event_id, CASE event_id % 50 WHEN 0 THEN NULL WHEN 1 THEN -1 WHEN 2 THEN 65536 ELSE sym END AS sym FROM r)
SELECT CASE WHEN sym BETWEEN 0 AND 65535 THEN 'fit' ELSE 'unfit' END AS side, count(*) AS n, CAST(sum(coalesce(sym, 0)) AS BIGINT) AS total FROM i GROUP BY 1""")
def late_and_bad_readings(s, d):
    """Bad readings are injected (null, negative, too large): they go aside whole."""
    r = C.table(s, d, "events").select("event_id", C.cents("value").alias("sym"))
    kind = F.col("event_id") % 50
    injected = r.withColumn("sym", F.when(kind == 0, None).when(kind == 1, -1).when(kind == 2, 65536).otherwise(F.col("sym")))
    ok, bad = C.fit(injected)
    total = lambda df, side: df.agg(F.lit(side).alias("side"), F.count(F.lit(1)).alias("n"), F.coalesce(F.sum(F.coalesce("sym", F.lit(0).cast("bigint"))), F.lit(0).cast("bigint")).alias("total")).where("n > 0")
    return total(ok, "fit").union(total(bad, "unfit"))


def flagship(s: SparkSession, sf_dir: str) -> DataFrame:
    """Compression ratio of every group of the meter grid under the best published configuration, two groups a batch."""
    return compression_ratio(_packed(s, sf_dir, "meter_grid", "identity", Config(k=2)), "batch_id", "cluster_id")


query(flagship, name="recompress_meter_grid")


@query
def recompress_first_stages(s, d):
    """Ratios by carrier and first stage, under k-means and the adaptive run length."""
    parts = []
    for name in ("meter_grid", "meter_value", "supplier_qty"):
        for coder in ("identity", "gaussian_ac", "delta_varint"):
            packed = _packed(s, d, name, coder, Config(k=4))
            parts.append(compression_ratio(packed).select(F.lit(name).alias("carrier"), F.lit(coder).alias("first_stage"), "*"))
    return experiments._all(parts)

"""SQL twins of the operators that SQL can say: the same rows from the plain definition, with no hashing, sketch or trie."""

from __future__ import annotations

from meterpack.llm.common import LOWER, UPPER
from meterpack.llm.lm_score import HALF, MICRO, STEP

OP1 = f"""
WITH u AS (SELECT page_id, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages),
h AS (SELECT page_id, translate(regexp_extract(rest, '^[^/?#]*'), '{UPPER}', '{LOWER}') AS host, regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM u),
r(verdict, host, path) AS (VALUES ('block', 'com', '/en/'), ('allow', 'example.com', '/en/7'), ('allow', 'net', '/de/'), ('block', 'example.net', '/de/8'), ('block', 'org', '/es/')),
m AS (SELECT page_id, r.host || r.path AS rule, r.verdict, row_number() OVER (PARTITION BY page_id ORDER BY length(r.host || r.path) DESC) AS n
      FROM h JOIN r ON (h.host = r.host OR ends_with(h.host, '.' || r.host)) AND starts_with(h.path, r.path))
SELECT h.page_id, h.host, h.path, m.rule, coalesce(m.verdict, 'allow') AS verdict FROM h LEFT JOIN m ON m.page_id = h.page_id AND m.n = 1
"""

OP2 = """
WITH RECURSIVE t AS (SELECT list(v ORDER BY i) AS tbl FROM (SELECT i, list_reduce(list_prepend(i, range(8)), lambda c, k: CASE WHEN c & 1 = 1 THEN xor(c >> 1, 3988292384) ELSE c >> 1 END) AS v FROM range(256) r(i))),
b AS (SELECT doc_id, coalesce(text, '') AS text, list_transform(regexp_extract_all(hex(encode(coalesce(text, ''))), '..'), lambda x: CAST('0x' || x AS BIGINT)) AS bytes FROM documents),
c AS (SELECT doc_id, CAST(strlen(text) + 8 AS BIGINT) AS size, xor(list_reduce(list_prepend(4294967295, bytes), lambda c, x: xor(c >> 8, tbl[CAST(xor(c, x) & 255 AS INTEGER) + 1])), 4294967295) AS text_crc32 FROM b, t),
j(doc_id, key, shard, grown) AS (
  SELECT DISTINCT doc_id, CAST(CAST('0x' || substr(md5(CAST(doc_id AS VARCHAR)), 1, 8) AS BIGINT) AS HUGEINT) * 4294967296 + CAST('0x' || substr(md5(CAST(doc_id AS VARCHAR)), 9, 8) AS BIGINT), CAST(-1 AS BIGINT), CAST(-1 AS BIGINT) FROM documents
  UNION ALL
  SELECT doc_id, (key * 2862933555777941757 + 1) % 18446744073709551616, CASE WHEN a < 24 THEN a ELSE shard END, a
  FROM (SELECT *, CAST(floor(CAST(grown + 1 AS DOUBLE) * (2147483648.0::DOUBLE / CAST((key // 8589934592) + 1 AS DOUBLE))) AS BIGINT) AS a FROM j) WHERE a <= 24),
s AS (SELECT doc_id, arg_max(shard, grown) AS shard, max(grown) AS grown FROM j GROUP BY 1),
p AS (SELECT c.*, s.shard, s.grown, CAST('0x' || substr(md5(c.doc_id || ':' || size || ':' || text_crc32), 1, 8) AS BIGINT) % 256 AS part FROM c JOIN s ON s.doc_id = c.doc_id)
SELECT doc_id, size, CAST(text_crc32 AS BIGINT) AS text_crc32, 'key' AS law, CAST(shard AS INTEGER) AS shard, row_number() OVER (PARTITION BY shard ORDER BY part, doc_id, size, text_crc32) - 1 AS slot, CAST(grown AS INTEGER) AS grown_shard FROM p
"""

WORDS = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def _words(text: str) -> str:
    return f"regexp_extract_all(translate(coalesce({text}, ''), '{UPPER}', '{LOWER}'), '{WORDS}')"


def _log(n: str) -> str:
    return f"CAST(round(ln(CAST({n} AS DOUBLE)) * {MICRO}) AS BIGINT)"


OP5 = f"""
WITH i AS (SELECT item_id, {_words("text")} AS w FROM benchmark),
k AS (SELECT item_id, least(10, len(w)) AS n, w[p:p + least(10, len(w)) - 1] AS win FROM (SELECT *, unnest(range(1, len(w) - least(10, len(w)) + 2)) AS p FROM i WHERE len(w) > 0)),
d AS (SELECT doc_id, {_words("text")} AS w FROM documents),
x AS (SELECT doc_id, n, p, w[p:p + n - 1] AS win FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS p FROM d, (SELECT DISTINCT n FROM k) WHERE len(w) >= n)),
h AS (SELECT x.doc_id, x.p, x.n, k.item_id FROM x JOIN k ON k.n = x.n AND k.win = x.win),
q AS (SELECT doc_id, count(DISTINCT w) AS n_hit FROM (SELECT doc_id, unnest(range(p, p + n)) AS w FROM h) GROUP BY 1),
m AS (SELECT doc_id, count(DISTINCT item_id) AS n_items, string_agg(DISTINCT CAST(item_id AS VARCHAR), ',' ORDER BY CAST(item_id AS VARCHAR)) AS ids FROM h GROUP BY 1)
SELECT d.doc_id, len(w) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(ids, '')) AS items_sha256, n_hit IS NOT NULL AS contaminated
FROM d LEFT JOIN q ON q.doc_id = d.doc_id LEFT JOIN m ON m.doc_id = d.doc_id
"""

OP6 = r"""
WITH d AS (SELECT * FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels WHERE toxic = 1)),
c AS (SELECT source, lang, 'words-1' AS tokenizer, len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')) AS n FROM d
      UNION ALL
      SELECT source, lang, 'pieces-1', len(regexp_extract_all(text, '[A-Za-z]+|[0-9]+|[^A-Za-z0-9\x20\x09-\x0D]')) FROM d)
SELECT source, lang, tokenizer, count(*) AS n_docs, CAST(sum(n) AS BIGINT) AS n_tokens FROM c GROUP BY ALL
"""

OP7 = f"""
WITH d AS (SELECT doc_id, CAST('0x' || substr(md5(coalesce(text, '')), 1, 1) AS INTEGER) % 2 AS fold, {_words("text")} AS w FROM documents),
b AS (SELECT doc_id, fold, p, w[p] AS w, CASE WHEN p > 1 THEN w[p - 1] ELSE ' ' END AS v, CASE WHEN p > 2 THEN w[p - 2] WHEN p = 2 THEN ' ' END AS u FROM (SELECT *, unnest(range(1, len(w) + 1)) AS p FROM d)),
ones AS (SELECT fold, w, count(*) AS n FROM b GROUP BY ALL UNION ALL SELECT fold, ' ', count(*) FILTER (WHERE len(w) > 0) FROM d GROUP BY 1), alls AS (SELECT fold, count(*) AS n FROM b GROUP BY 1),
twos AS (SELECT fold, v, w, count(*) AS n FROM b GROUP BY ALL), threes AS (SELECT fold, u, v, w, count(*) AS n FROM b WHERE u IS NOT NULL GROUP BY ALL),
x AS (SELECT b.doc_id, b.u IS NULL AS first, c.n AS cw, cv.n AS cv, vw.n AS vw, uv.n AS uv, uvw.n AS uvw, coalesce(a.n, 1) AS n FROM b
  LEFT JOIN alls a ON a.fold = 1 - b.fold LEFT JOIN ones c ON c.fold = 1 - b.fold AND c.w = b.w LEFT JOIN ones cv ON cv.fold = 1 - b.fold AND cv.w = b.v LEFT JOIN twos vw ON vw.fold = 1 - b.fold AND vw.v = b.v AND vw.w = b.w
  LEFT JOIN twos uv ON uv.fold = 1 - b.fold AND uv.v = b.u AND uv.w = b.v LEFT JOIN threes uvw ON uvw.fold = 1 - b.fold AND uvw.u = b.u AND uvw.v = b.v AND uvw.w = b.w),
y AS (SELECT doc_id, CAST(sum(CASE WHEN uvw IS NOT NULL THEN {_log("uv")} - {_log("uvw")} WHEN vw IS NOT NULL THEN CASE WHEN first THEN 0 ELSE {STEP} END + {_log("cv")} - {_log("vw")} ELSE CASE WHEN first THEN {STEP} ELSE {2 * STEP} END + {_log("n")} - coalesce({_log("cw")}, {HALF}) END) AS BIGINT) AS cost FROM x GROUP BY 1)
SELECT d.doc_id, d.fold, len(d.w) AS n_tokens, coalesce(cost, 0) AS cost, CASE WHEN len(d.w) > 0 THEN round(CAST(cost AS DOUBLE) / len(d.w) / {MICRO}, 6) END AS nats_per_token FROM d LEFT JOIN y ON y.doc_id = d.doc_id
"""

OP8 = rf"""
WITH RECURSIVE d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), '{UPPER}', '{LOWER}'), '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS (SELECT DISTINCT doc_id, w[p:p + 4] AS g FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 4, 1) + 1)) AS p FROM d WHERE len(w) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY 1),
o AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS shared FROM s a JOIN s b ON b.g = a.g AND a.doc_id <> b.doc_id GROUP BY ALL),
e AS (SELECT a, b FROM o JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * shared >= 85 * (x.n + y.n - shared)),
r(a, b) AS (SELECT doc_id, doc_id FROM d UNION SELECT r.a, e.b FROM r JOIN e ON e.a = r.b),
c AS (SELECT a AS doc_id, min(b) AS component_id FROM r GROUP BY 1)
SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles, component_id, d.doc_id = component_id AS kept FROM d JOIN c ON c.doc_id = d.doc_id LEFT JOIN n ON n.doc_id = d.doc_id
"""

SQL = {"op1_url_filter": OP1, "op2_sharding": OP2, "op5_decontamination": OP5, "op6_token_counts": OP6, "op7_lm_scores": OP7, "op8_near_duplicates": OP8}

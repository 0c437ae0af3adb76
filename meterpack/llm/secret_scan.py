"""Secret scan in DataFrame functions only: candidates by pattern, then how many owners and repositories share each one.

A candidate that many owners have copied is an example; one that a single owner has, and that looks random, may be live.
Contract for odd input: a null text is empty; null owners and repositories count as one of their own; repeated rows each
get their row; on an empty table the result is empty; columns beyond those named are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from meterpack.llm.common import staged

KINDS = ("assign", "access", "hex", "generic", "pem")
WORDS = "password|passwd|secret|token|api_?key"
ASSIGN = rf"""(?i:({WORDS}))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
#: Runs of one class of characters: these match where the plain pattern does and the length suffices, and nowhere else.
ACCESS = r"AKIA[A-Z0-9]{12,}+"
HEX = r"(?<![0-9a-f])[0-9a-f]{32,}+"
GENERIC = r"(?<![A-Za-z0-9+/_-])[A-Za-z0-9+/_-]{24,}+={0,2}"
PEM_HEAD = r"-----BEGIN [A-Z ]{0,40}PRIVATE KEY-----"
#: A key goes on to its END line or, where that is missing, over the runs of base64 that follow; lines may be ended by escapes.
PEM = PEM_HEAD + r"([^-]*+(?:-(?!----)[^-]*+){0,64}+-----END [A-Z ]{0,40}PRIVATE KEY-----|(?:(?:\s|\\[nr])*+[A-Za-z0-9+/=]{16,}+){0,400}+)"
MIN_ASSIGNED = 8
#: Values that are copied from manuals (fixed values).
SAMPLE = r"(?i)example|sample|changeme|placeholder|dummy|your[_-]|x{6,}|0{8,}|12345678"
#: A candidate that so many owners share is an example.
WIDE_OWNERS = 3


def _positions(text: Column, pattern: str, value_group: int, kind: int, sign: str | None = None) -> Column:
    """array<struct<start,end,kind,value>> of all matches: what lies between them gives the places, in code points."""
    # split() and regexp_extract_all() step through the same matches
    here = text.rlike(sign or pattern)
    none = F.array().cast("array<string>")
    gaps = F.when(here, F.split(text, pattern, -1)).otherwise(none)
    whole = F.when(here, F.regexp_extract_all(text, F.lit(pattern), F.lit(0))).otherwise(none)
    value = whole if not value_group else F.when(here, F.regexp_extract_all(text, F.lit(pattern), F.lit(value_group))).otherwise(none)
    return F.arrays_zip(F.slice(gaps, 1, F.size(whole)).alias("gap"), whole.alias("whole"), value.alias("value"))


SPANS = "array<struct<start:int,end:int,kind:int,value:string>>"


def _placed(found: Column, kind: int) -> Column:
    def add(acc: Column, x: Column) -> Column:
        start = acc["at"] + F.length(x["gap"])
        end = start + F.length(x["whole"])
        span = F.struct(start.cast("int").alias("start"), end.cast("int").alias("end"), F.lit(kind).alias("kind"), x["value"].alias("value"))
        return F.struct(end.cast("int").alias("at"), F.concat(acc["spans"], F.array(span)).alias("spans"))

    start = F.struct(F.lit(0).cast("int").alias("at"), F.array().cast(SPANS).alias("spans"))
    return F.aggregate(found, start, add, lambda acc: acc["spans"])


def candidates(docs: DataFrame, text: str = "text") -> DataFrame:
    """docs with `base` and `more`: the spans of the base patterns, and wider ones: runs that overlap none of these, and
    private keys, whatever lies within. Map-only."""
    body = F.coalesce(F.col(text), F.lit(""))
    out = docs.withColumn("__mp_text", body)
    t = F.col("__mp_text")
    found = {0: (ASSIGN, 2, f"(?i:{WORDS})"), 1: (ACCESS, 0, None), 2: (HEX, 0, None), 3: (GENERIC, 0, None), 4: (PEM, 1, "-----BEGIN ")}
    out = out.withColumns({f"__mp_found_{k}": _positions(t, p, g, k, sign) for k, (p, g, sign) in found.items()})
    out = out.withColumns({f"__mp_spans_{k}": _placed(F.col(f"__mp_found_{k}"), k) for k in found})
    spans = {k: F.col(f"__mp_spans_{k}") for k in found}
    base = F.concat(F.filter(spans[0], lambda x: F.length(x["value"]) >= MIN_ASSIGNED), spans[1], spans[2])
    out = out.withColumn("base", F.array_sort(base))
    mixed = lambda v: v.rlike("[a-z]") & v.rlike("[A-Z]") & v.rlike("[0-9]")
    apart = lambda x, these: ~F.exists(these, lambda b: (b["start"] < x["end"]) & (x["start"] < b["end"]))
    runs = F.filter(spans[3], lambda x: mixed(x["value"]) & apart(x, F.col("base")) & apart(x, spans[4]))
    # a key is its body, however its lines are cut; a bare header is itself
    key = lambda v: F.regexp_replace(v, r"\s|\\[nr]|-----END [A-Z ]{0,40}PRIVATE KEY-----", "")
    keys = F.transform(spans[4], lambda x: F.struct(x["start"].alias("start"), x["end"].alias("end"), x["kind"].alias("kind"), F.when(key(x["value"]) == "", "PRIVATE KEY").otherwise(key(x["value"])).alias("value")))
    return out.withColumn("more", F.concat(runs, keys)).drop("__mp_text", *(f"__mp_found_{k}" for k in found), *(f"__mp_spans_{k}" for k in found))


def ownership(found: DataFrame) -> DataFrame:
    """(secret, owners, repositories) from (secret, owner, repository) rows; a value copied into every document shrinks
    to one row a repository before the shuffle, and to one row an owner before the next."""
    by_repo = found.groupBy("secret", "owner", "repository").agg(F.count(F.lit(1)).alias("copies"))
    by_owner = by_repo.groupBy("secret", "owner").agg(F.count(F.lit(1)).alias("repositories"), F.sum("copies").alias("copies"))
    return by_owner.groupBy("secret").agg(F.count(F.lit(1)).alias("owners"), F.sum("repositories").alias("repositories"), F.sum("copies").alias("copies"))


#: Bits a character that a random value has at least, and classes of characters (lower, upper, digits, others).
LEAST_BITS, LEAST_CLASSES = 2.5, 2
#: Kinds whose pattern does not tell that the value is random.
LOOSE = (0, 3)


def bits_a_character(value: Column) -> Column:
    """Zero-order entropy of the characters of a value."""
    n = F.length(value).cast("double")
    share = lambda c: (n - F.length(F.replace(value, c, F.lit("")))) / n
    return F.aggregate(F.array_distinct(F.split(value, "")), F.lit(0.0), lambda acc, c: acc + F.when(F.length(c) > 0, -share(c) * F.log2(share(c))).otherwise(0.0))


def looks_random(value: Column) -> Column:
    classes = sum((value.rlike(p).cast("int") for p in ("[a-z]", "[A-Z]", "[0-9]", "[^A-Za-z0-9]")), F.lit(0))
    return (bits_a_character(value) >= LEAST_BITS) & (classes >= LEAST_CLASSES)


def standing(value: Column, owners: Column, kind: Column) -> Column:
    """example (many owners, or a value from a manual), live (one owner, and random by its kind's form or by its characters),
    plain (one owner, not random) or shared."""
    random = ~kind.isin(*LOOSE) | looks_random(value)
    return F.when((owners >= WIDE_OWNERS) | value.rlike(SAMPLE), "example").when((owners == 1) & random, "live").when(owners == 1, "plain").otherwise("shared")


def _string(spans: Column) -> Column:
    names = F.array(*(F.lit(k) for k in KINDS))
    ordered = F.array_sort(F.transform(spans, lambda x: F.struct(x["start"].alias("start"), x["kind"].alias("kind"), x["end"].alias("end"))))
    return F.array_join(F.transform(ordered, lambda x: F.concat_ws(":", names[x["kind"]], x["start"], x["end"])), ",")


def scan_secrets(docs: DataFrame, owner: str = "source", repository: Column | None = None, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """One row a document: n_assign, n_access, n_hex, base_sha256, spans, n_live, n_example, n_shared, n_plain and the candidates
    with their standing. A wider candidate is a span only where it is live."""
    repository = F.col(owner) if repository is None else repository
    rows = docs.select(F.monotonically_increasing_id().alias("row"), F.col(doc_id).alias("doc_id"), F.col(owner).alias("owner"), repository.alias("repository"), F.col(text).alias("text"))
    rows = staged(candidates(rows).drop("text"), "secrets")
    every = F.concat("base", "more")
    each = rows.where((F.size("base") > 0) | (F.size("more") > 0)).select("row", "owner", "repository", F.explode(every).alias("span")).withColumn("secret", F.sha2("span.value", 256))
    # written, so that the join meets a plain table and adaptive execution can split a secret that all documents hold
    known = each.join(staged(ownership(each.select("secret", "owner", "repository")), "owners"), "secret")
    judged = known.select("row", F.struct("span.start", "span.end", "span.kind", "secret", "owners", "repositories", standing(F.col("span.value"), F.col("owners"), F.col("span.kind")).alias("standing")).alias("found"))
    per_row = judged.groupBy("row").agg(F.array_sort(F.collect_list("found")).alias("found"))
    out = rows.join(per_row, "row", "left").withColumn("found", F.coalesce("found", F.array().cast(per_row.schema["found"].dataType)))
    of_kind = lambda k: F.size(F.filter("base", lambda x: x["kind"] == k)).cast("long")
    of_standing = lambda s: F.size(F.filter("found", lambda x: x["standing"] == s)).cast("long")
    spans = F.filter("found", lambda x: (x["kind"] <= 2) | (x["standing"] == "live"))
    return out.select("doc_id", of_kind(0).alias("n_assign"), of_kind(1).alias("n_access"), of_kind(2).alias("n_hex"), F.sha2(_string(F.col("base")), 256).alias("base_sha256"), _string(spans).alias("spans"), *(of_standing(s).alias(f"n_{s}") for s in ("live", "example", "shared", "plain")), "found")

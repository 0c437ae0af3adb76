"""Personal data by weak supervision: labelers vote on candidate spans, expectation-maximisation weighs the labelers, and a
span classifier trained on its posteriors decides which candidates beyond the plain patterns are added.

Votes are counted over the whole corpus by (kind, votes, shape), a table of fixed size, so that fitting needs neither a
sample nor the texts. Contract for odd input: a null or empty text has no spans; equal rows get equal spans; on an empty
table the model accepts nothing beyond the plain patterns; extra columns pass through.
"""

from __future__ import annotations

import hashlib
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from meterpack.llm.common import sent, small_batches, text_chunks

KINDS = ("email", "ip", "card", "phone")
LOCAL = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-"
DOMAIN = re.compile(r"[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++")
IP = re.compile(r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++")
CARD = re.compile(r"[0-9](?:[ -]?[0-9])++")
PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")

#: Wider forms that only the classifier can admit.
WIDE = {
    "email": re.compile(r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]{1,64}+ ?(?:\[at\]|\(at\)| at ) ?[A-Za-z0-9-]{1,63}+(?: ?(?:\[dot\]|\(dot\)| dot ) ?[A-Za-z0-9-]{1,63}+)++"),
    "ip": re.compile(r"(?<![0-9A-Fa-f:])(?:[0-9A-Fa-f]{1,4}:){7}[0-9A-Fa-f]{1,4}(?![0-9A-Fa-f:])"),
    "card": re.compile(r"(?<![0-9])[0-9]{4}([./])[0-9]{4}\1[0-9]{4}\1[0-9]{1,7}(?![0-9])"),
    "phone": re.compile(r"(?<![0-9+])(?:\([0-9]{3}\) ?|[0-9]{3}[ .-])[0-9]{3}[ .-][0-9]{4}(?![0-9])"),
}
#: A text without any of these holds no wide form of the kind.
SIGNS = {"email": ("[dot]", "(dot)", " dot "), "ip": (":",), "card": (".", "/"), "phone": ("-", ".", " ")}

#: Gazetteers (fixed values): endings of mail domains, first digits of card issuers, calling codes.
MAIL_ENDINGS = frozenset("com org net edu gov io de fr es uk it nl eu info".split())
ISSUERS = ("34", "37", "4", "51", "52", "53", "54", "55", "6011", "62", "65", "2221", "2720", "30", "36", "38", "35")
CALLING = ("1", "7", "20", "27", "30", "31", "32", "33", "34", "39", "40", "41", "43", "44", "45", "46", "47", "48", "49", "52", "55", "61", "81", "82", "86", "90", "91")
CUES = {
    "email": re.compile(r"\b(?:e-?mail|contact|write|correo|courriel|mail)\b", re.I),
    "ip": re.compile(r"\b(?:ip|host|server|address|client|dirección|adresse)\b", re.I),
    "card": re.compile(r"\b(?:card|visa|credit|karte|carte|tarjeta|payment)\b", re.I),
    "phone": re.compile(r"\b(?:phone|call|tel|mobile|fax|telefon|téléphone|teléfono)\b", re.I),
}
COUNTER_CUES = re.compile(r"\b(?:version|isbn|issn|order|invoice|section|build|release|serial|doi)\b", re.I)
NEAR = 32

LABELERS = 5
ACCEPT = 0.9


def luhn(digits: str) -> bool:
    total = 0
    for i, d in enumerate(reversed(digits)):
        n = int(d) * (1 + i % 2)
        total += n - 9 * (n > 9)
    return total % 10 == 0


def octets(s: str) -> bool:
    return all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in s.split("."))


def digits_of(s: str) -> str:
    return "".join(c for c in s if "0" <= c <= "9")


def base_spans(t: str) -> list[tuple[int, int, int]]:
    """(kind number, start, end) of the plain patterns, by kind and start. Time grows with the text's length only."""
    out, end, at = [], 0, t.find("@")
    left = 0
    while at >= 0:
        run = t[left:at]
        start = left + len(run.rstrip(LOCAL))
        domain = DOMAIN.match(t, at + 1) if start < at else None
        left = at + 1
        if domain:
            out.append((0, start, domain.end()))
            left = domain.end()
        at = t.find("@", left)
    out += [(1, m.start(), m.end()) for m in IP.finditer(t) if octets(m.group())]
    for m in CARD.finditer(t):
        if 13 <= len(d := digits_of(m.group())) <= 19 and luhn(d):
            out.append((2, m.start(), m.end()))
    if "+" in t:
        out += [(3, m.start(), m.end()) for m in PHONE.finditer(t) if 9 <= len(digits_of(m.group())) <= 15]
    return out


def wide_spans(t: str, base: list[tuple[int, int, int]]) -> list[tuple[int, int, int]]:
    """Wider candidates that overlap neither a plain span nor an earlier candidate."""
    found = [(k, *m.span()) for k, kind in enumerate(KINDS) if any(sign in t for sign in SIGNS[kind]) for m in WIDE[kind].finditer(t)]
    if not found:
        return []
    taken, out = bytearray(len(t)), []
    for _, s, e in base:
        taken[s:e] = b"\1" * (e - s)
    for k, s, e in found:
        if not any(taken[s:e]):
            out.append((k, s, e))
            taken[s:e] = b"\1" * (e - s)
    return out


def votes(t: str, k: int, start: int, end: int, plain: bool) -> tuple[int, int]:
    """(votes, shape) of a candidate: each labeler says 0 (no), 1 (abstains) or 2 (yes), packed in base 3."""
    s, kind = t[start:end], KINDS[k]
    d = digits_of(s)
    regex = 2 if plain else 1
    if kind == "card":
        form = 2 if 13 <= len(d) <= 19 and luhn(d) else 0
    elif kind == "ip":
        form = (2 if octets(s) else 0) if "." in s else 1
    elif kind == "phone":
        form = 2 if 9 <= len(d) <= 15 and len(set(d)) > 2 else 0
    else:
        form = 2 if len(s) <= 254 and re.search(r"[A-Za-z]", s) else 0
    if kind == "email":
        known = 2 if re.split(r"[. ]|\[dot\]|\(dot\)", s)[-1].lower() in MAIL_ENDINGS else 1
    elif kind == "card":
        known = 2 if d.startswith(ISSUERS) else 0
    elif kind == "phone":
        known = (2 if d.startswith(CALLING) else 0) if s.startswith("+") else 1
    else:
        known = 1
    before = t[max(0, start - NEAR) : start]
    context = 0 if COUNTER_CUES.search(before) else 2 if CUES[kind].search(before) else 1
    around = (start and t[start - 1].isalnum()) or (end < len(t) and t[end].isalnum())
    packed = 0
    for v in (regex, form, known, context, 0 if around else 2):
        packed = packed * 3 + v
    return packed, min(3, len(s) // 12)


def _count_votes(batches):
    total: dict[tuple[int, int, int], int] = {}
    for batch in batches:
        for chunk in text_chunks(batch.column(0)):
            for t in chunk:
                if t:
                    base = base_spans(t)
                    for plain, spans in ((True, base), (False, wide_spans(t, base))):
                        for k, s, e in spans:
                            key = (k, *votes(t, k, s, e, plain))
                            total[key] = total.get(key, 0) + 1
    columns = list(zip(*((*key, n) for key, n in total.items()), strict=True)) or [(), (), (), ()]
    yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], names=["kind", "votes", "shape", "n"])


def count_votes(docs: DataFrame, text: str = "text") -> DataFrame:
    """(kind, votes, shape, n) over all documents: at most 4 * 3**LABELERS * 4 rows from each task."""
    small_batches(docs.sparkSession)
    return docs.select(text).mapInArrow(_count_votes, "kind bigint, votes bigint, shape bigint, n bigint").groupBy("kind", "votes", "shape").agg(F.sum("n").alias("n"))


def unpack(packed: np.ndarray) -> np.ndarray:
    return np.stack([packed // 3 ** (LABELERS - 1 - i) % 3 for i in range(LABELERS)], 1)


def estimate(v: np.ndarray, n: np.ndarray, rounds: int = 50) -> np.ndarray:
    """Posterior of "personal" for each row of votes, by expectation-maximisation over how often each labeler says what
    about spans of either truth. n: how many spans a row stands for. It starts from the majority vote."""
    said = np.stack([v == s for s in range(3)], 2).astype(float)
    p = np.clip(0.5 + (v - 1).sum(1) / (2 * LABELERS), 0.05, 0.95)
    for _ in range(rounds):
        mass = np.stack([(1 - p) * n, p * n])
        rates = (np.einsum("cr,rls->cls", mass, said) + 1) / (mass.sum(1)[:, None, None] + 3)
        share = (mass.sum(1) + 1) / (n.sum() + 2)
        logs = np.einsum("cls,rls->rc", np.log(rates), said) + np.log(share)
        new = 1 / (1 + np.exp(np.clip(logs[:, 0] - logs[:, 1], -50, 50)))
        if np.abs(new - p).max() < 1e-6:
            return new
        p = new
    return p


def fit(counts: list[tuple[int, int, int, int]]) -> dict[tuple[int, int, int], float]:
    """Probability by (kind, votes, shape): for each kind a logistic span classifier on votes and shape, trained on the
    posteriors of all candidates. Kinds without candidates get none."""
    out: dict[tuple[int, int, int], float] = {}
    for k in range(len(KINDS)):
        rows = np.array(sorted(c[1:] for c in counts if c[0] == k), np.int64)
        if not len(rows):
            continue
        v, n = unpack(rows[:, 0]), rows[:, 2].astype(float)
        target = estimate(v, n)
        x = np.concatenate([(v[:, :, None] == np.arange(3)).reshape(len(v), -1), rows[:, 1:2] == np.arange(4), np.ones((len(v), 1))], 1).astype(float)
        weight, w = n / n.sum(), np.zeros(x.shape[1])
        for _ in range(50):
            q = 1 / (1 + np.exp(-x @ w))
            slope = x.T @ (weight * (target - q)) - 1e-4 * w
            bend = (x * (weight * q * (1 - q))[:, None]).T @ x + 1e-4 * np.eye(len(w))
            step = np.linalg.solve(bend, slope)
            w += step
            if np.abs(step).max() < 1e-8:
                break
        for row, q in zip(rows, 1 / (1 + np.exp(-x @ w)), strict=True):
            out[k, int(row[0]), int(row[1])] = float(q)
    return out


def fit_spans(docs: DataFrame, text: str = "text") -> dict[tuple[int, int, int], float]:
    return fit([(r.kind, r.votes, r.shape, r.n) for r in count_votes(docs, text).collect()])


def all_spans(t: str | None, model: dict[tuple[int, int, int], float]) -> tuple[list[tuple[int, int, int]], list[tuple[int, int, int]]]:
    """(plain spans, plain and admitted spans), each by kind and start."""
    if not t:
        return [], []
    base = base_spans(t)
    more = [x for x in wide_spans(t, base) if model.get((x[0], *votes(t, *x, False)), 0.0) >= ACCEPT]
    return base, sorted(base + more)


def joined(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{s}:{e}" for k, s, e in spans)


FOUND = "struct<n_email:bigint,n_ip:bigint,n_card:bigint,n_phone:bigint,base_sha256:string,spans:string>"


def _finder(model):
    fields = [*((f"n_{k}", pa.int64()) for k in KINDS), ("base_sha256", pa.string()), ("spans", pa.string())]

    @F.arrow_udf(FOUND)
    def find(text: pa.Array) -> pa.Array:
        out = []
        for chunk in text_chunks(text):
            for t in chunk:
                base, every = all_spans(t, model())
                row = {f"n_{k}": sum(x[0] == i for x in base) for i, k in enumerate(KINDS)}
                out.append(row | {"base_sha256": hashlib.sha256(joined(base).encode()).hexdigest(), "spans": joined(every)})
        return pa.array(out, pa.struct(fields))

    return find


def find_personal(docs: DataFrame, model: dict, text: str = "text", name: str = "personal") -> DataFrame:
    """docs with the spans found. Map-only."""
    small_batches(docs.sparkSession)
    return docs.withColumn(name, _finder(sent(docs.sparkSession.sparkContext, model))(F.col(text)))


def personal_report(docs: DataFrame, doc_id: str = "doc_id") -> DataFrame:
    return find_personal(docs.select(F.col(doc_id).alias("doc_id"), "text"), fit_spans(docs)).select("doc_id", "personal.*")


def _masker(model):
    @F.arrow_udf("string")
    def mask(text: pa.Array) -> pa.Array:
        out = []
        for t in text.to_pylist():
            if t is not None:
                parts, last = [], 0
                for k, s, e in sorted(all_spans(t, model())[1], key=lambda x: x[1:]):
                    if s >= last:
                        parts += [t[last:s], f"[{KINDS[k]}]"]
                    last = max(last, e)  # of overlapping spans, all characters go
                t = "".join(parts) + t[last:]
            out.append(t)
        return pa.array(out, pa.string())

    return mask


def mask_personal(docs: DataFrame, model: dict, text: str = "text") -> DataFrame:
    """docs with every span found replaced by its kind in brackets."""
    small_batches(docs.sparkSession)
    return docs.withColumn(text, _masker(sent(docs.sparkSession.sparkContext, model))(F.col(text)))

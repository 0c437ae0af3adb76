"""URL filter: allow and block entries in a trie over reversed host labels and path segments; the longest entry decides.

Contract for odd input: a null url or one without "://" has an empty host and path and gets the default verdict; ties of
equal length go to the longer host, then to block; repeated rows are judged one by one; columns of any name pass through.
"""

from __future__ import annotations

from collections.abc import Iterable, Sequence

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from meterpack.llm.common import fold_ascii, sent

#: Entries that one broadcast trie may hold; longer lists are judged block by block, and the longest entry of all wins.
MAX_TRIE_RULES = 200_000

Rule = tuple[str, str]  # ("allow" | "block", "host/path")


class HostPathTrie:
    """Entries by reversed host label, then by whole path segment; what follows the last slash matches as a prefix."""

    def __init__(self, rules: Iterable[Rule]) -> None:
        self.root: dict = {"sub": {}, "paths": None}
        for verdict, rule in rules:
            if verdict not in ("allow", "block"):
                raise ValueError(f"verdict {verdict!r} is neither allow nor block")
            host, slash, path = rule.partition("/")
            node = self.root
            for label in reversed(host.split(".")):
                node = node["sub"].setdefault(label, {"sub": {}, "paths": None})
            if node["paths"] is None:
                node["paths"] = {"seg": {}, "tails": {}}
            at = node["paths"]
            *whole, tail = (slash + path).split("/") if slash else [""]
            for segment in whole[1:]:
                at = at["seg"].setdefault(segment, {"seg": {}, "tails": {}})
            key = (bool(slash), tail)
            if at["tails"].get(key, ("", ""))[0] != "block":
                at["tails"][key] = (verdict, rule)

    def find(self, host: str, path: str) -> tuple[str, str] | None:
        """(verdict, entry) of the longest entry that covers host and path."""
        best, best_key = None, (-1, -1)
        node = self.root
        segments = path.split("/")
        for label in reversed(host.split(".")):
            node = node["sub"].get(label)
            if node is None:
                break
            at, i = node["paths"], 1
            while at is not None:
                here = segments[i] if i < len(segments) else None
                # every beginning of the segment is looked up, so that a node may hold any number of tails
                for key in [(False, ""), *((True, here[:n]) for n in range(len(here) + 1))] if here is not None else [(False, "")]:
                    if key in at["tails"]:
                        verdict, rule = at["tails"][key]
                        size = (len(rule), len(rule.partition("/")[0]))
                        if size > best_key:
                            best, best_key = (verdict, rule), size
                at = at["seg"].get(segments[i]) if i + 1 < len(segments) else None
                i += 1
        return best


def host_and_path(url: Column) -> tuple[Column, Column]:
    at = F.locate("://", url)
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise("")
    rest = F.coalesce(rest, F.lit(""))
    return fold_ascii(F.regexp_extract(rest, r"^[^/?#]*", 0)), F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)


def judge_urls(pages: DataFrame, rules: Sequence[Rule], url: str = "url", default: str = "allow", max_trie_rules: int = MAX_TRIE_RULES) -> DataFrame:
    """pages with host, path, rule and verdict beside its columns (of the same name, ours replace them). Map-only.

    A list above max_trie_rules is cut into blocks with a trie each, so that no broadcast outgrows its bound."""
    sc = pages.sparkSession.sparkContext
    host, path = host_and_path(F.col(url))
    out = pages.withColumns({"host": host, "path": path})
    hits = []
    for at in range(0, max(1, len(rules)), max_trie_rules):
        trie = sent(sc, HostPathTrie(rules[at : at + max_trie_rules]))
        name = f"__mp_hit_{at}"
        out = out.withColumn(name, _finder(trie)(F.col("host"), F.col("path")))
        hits.append(name)
    best = F.greatest(*(F.col(h) for h in hits)) if len(hits) > 1 else F.col(hits[0])
    return out.withColumns({"rule": best["rule"], "verdict": F.coalesce(best["verdict"], F.lit(default))}).drop(*hits)


def _finder(trie):
    kind = pa.struct([("size", pa.int32()), ("host_size", pa.int32()), ("verdict", pa.string()), ("rule", pa.string())])

    @F.arrow_udf("struct<size:int,host_size:int,verdict:string,rule:string>")
    def find(host: pa.Array, path: pa.Array) -> pa.Array:
        out, walk = [], trie().find
        for h, p in zip(host.to_pylist(), path.to_pylist(), strict=True):
            hit = walk(h, p)
            out.append(hit and {"size": len(hit[1]), "host_size": len(hit[1].partition("/")[0]), "verdict": hit[0], "rule": hit[1]})
        return pa.array(out, kind)

    return find

"""The chain of transforms over one group of streams, forth and back."""

from __future__ import annotations

import json
import zlib
from collections.abc import Iterable, Iterator
from dataclasses import asdict, dataclass, replace

import numpy as np

from meterpack.kernels.arith import ac_decode, ac_encode, ac_encode_many, adaptive_decode, adaptive_encode, gaussian_decode, gaussian_encode
from meterpack.kernels.bits import get_sorted, get_varints, put_sorted, put_varints, unzigzag, zigzag
from meterpack.kernels.bwt import bwt, bwt_inverse
from meterpack.kernels.huffman import huffman_decode, huffman_encode
from meterpack.kernels.mtf import mtf, mtf_inverse, order_of
from meterpack.kernels.rle import THRESHOLDS, rle_classes, rle_classes_inverse, rle_dynamic, rle_dynamic_inverse, rle_static, rle_static_inverse, rle_tokens, rle_tokens_inverse


@dataclass(frozen=True)
class Config:
    """How a batch is grouped and coded; the defaults are the best published configuration."""

    grouping: str = "kmeans"  # kmeans | random | none | each
    k: int = 8
    seed: int = 42
    init: str = "kmeans++"  # kmeans++ | uniform
    seed_scope: str = "global"  # global | region
    vector: str = "pad"  # pad | truncate | resample | histogram
    layout: str = "interleave"  # interleave | concat
    delta_order: int = 1
    delta_scope: str = "group"  # group | stream
    bwt: str | None = "cyclic"  # cyclic | low | high | None
    mtf: bool = True
    rle: str | None = "dynamic"  # dynamic | entropy | static | token | rank_class | None
    coder: str = "arith"  # arith | adaptive | gaussian | huffman
    max_block: int = 1 << 18
    max_iter: int = 50

    def but(self, **changes) -> "Config":
        return replace(self, **changes)

    def text(self) -> str:
        return json.dumps(asdict(self), sort_keys=True)


def read_config(text: str) -> Config:
    return Config(**json.loads(text))


def column_order(lengths: np.ndarray, layout: str) -> np.ndarray:
    """Places of the joined streams in the order the layout reads them: position by position over all streams that still
    have one, or stream by stream."""
    if layout == "concat":
        return np.arange(int(np.sum(lengths)))
    pos = np.concatenate([np.arange(n) for n in lengths]) if len(lengths) else np.empty(0, np.int64)
    return order_of(pos)


def difference(x: np.ndarray, order: int) -> tuple[list[int], np.ndarray]:
    firsts = []
    for _ in range(order):
        if len(x):
            firsts.append(int(x[0]))
            x = np.diff(x)
    return firsts, x


def integrate(firsts: list[int], x: np.ndarray) -> np.ndarray:
    for f in reversed(firsts):
        x = np.concatenate([[f], f + np.cumsum(x)])
    return x


def code(x: np.ndarray, coder: str) -> tuple[bytes, bytes]:
    """(payload, side data) of one list of integers."""
    if coder == "arith":
        return ac_encode(x)
    if coder == "adaptive":
        return adaptive_encode(x)
    if coder == "huffman":
        payload, table, _ = huffman_encode(x)
        return payload, table
    if coder == "gaussian":
        payload, mu, sigma = gaussian_encode(x)
        return payload, put_varints([len(x), int(zigzag(np.array(mu))), sigma])
    raise ValueError(f"no coder {coder!r}")


def decode(payload: bytes, side: bytes, at: int, coder: str) -> tuple[np.ndarray, int]:
    if coder == "gaussian":
        (n, mu, sigma), at = get_varints(side, 3, at)
        return gaussian_decode(payload, int(unzigzag(np.array(mu))), sigma, n), at
    return {"arith": ac_decode, "adaptive": adaptive_decode, "huffman": huffman_decode}[coder](payload, side, at)


def transformed(streams: list[np.ndarray], cfg: Config) -> dict[str, np.ndarray | list]:
    """The forms of a group before its run lengths."""
    lengths = np.array([len(s) for s in streams], np.int64)
    joined = np.concatenate(streams).astype(np.int64) if len(streams) else np.empty(0, np.int64)
    order = column_order(lengths, cfg.layout)
    out: dict = {"raw": joined, "interleaved": joined[order]}
    if cfg.delta_scope == "stream" and cfg.delta_order:
        parts = [difference(np.asarray(s, np.int64), cfg.delta_order) for s in streams]
        firsts = [f for p, _ in parts for f in p]
        joined = np.concatenate([p for _, p in parts]) if parts else joined
        x = joined[column_order(np.array([len(p) for _, p in parts]), cfg.layout)]
    else:
        firsts, x = difference(out["interleaved"], cfg.delta_order)
    out |= {"firsts": firsts, "delta": x}
    primary, alphabet = 0, np.empty(0, np.int64)
    if cfg.bwt:
        x, primary = bwt(x, None if cfg.bwt == "cyclic" else cfg.bwt)
    out |= {"bwt": x, "primary": primary}
    if cfg.mtf:
        x, alphabet = mtf(x)
    return out | {"mtf": x, "alphabet": alphabet}


def stages(streams: list[np.ndarray], cfg: Config, before: dict | None = None) -> dict[str, np.ndarray | list]:
    """Every intermediate form of a group; what encode() codes and what entropy by stage is measured on. before: transformed()
    of the same, where it is known."""
    out = before or transformed(streams, cfg)
    x = out["mtf"]
    applied, t = False, 0
    if cfg.rle in ("dynamic", "entropy"):
        applied, t, syms, counts = rle_dynamic(x, THRESHOLDS, "bits" if cfg.rle == "dynamic" else "entropy")
        lists = [syms, counts] if applied else [syms]
    elif cfg.rle == "static":
        lists = list(rle_static(x))
    elif cfg.rle == "token":
        lists = list(rle_tokens(x))
    elif cfg.rle == "rank_class":
        chosen, syms, counts = rle_classes(x)
        t, lists = chosen[0] | chosen[1] << 8 | chosen[2] << 16, [syms, counts]
        applied = t > 0
    else:
        lists = [x]
    return out | {"applied": applied, "t": t, "lists": lists}


def encode(streams: list[np.ndarray], cfg: Config, before: dict | None = None) -> dict:
    """applied, t, alphabet, model, payload of one group; the model holds first values, block index and code tables."""
    return encode_many([(streams, cfg, before)])[0]


def encode_many(groups: Iterable[tuple[list[np.ndarray], Config, dict | None]]) -> list[dict]:
    """encode() of each; of a group only its lists are held until all are coded, in step where the coder has it so."""
    out, coded = [], []

    def lists() -> Iterator[np.ndarray]:
        """Of groups whose coder goes in step, and all else of each group on the way."""
        n = 0
        for streams, cfg, before in groups:
            s = stages(streams, cfg, before)
            firsts = [len(s["firsts"]), *(int(v) for v in zigzag(np.array(s["firsts"], np.int64))), s["primary"]]
            crc = zlib.crc32(s["raw"].astype("<i8").tobytes())
            out.append({"applied": s["applied"], "t": s["t"], "alphabet": put_sorted(s["alphabet"]) if cfg.mtf else b"", "model": firsts, "payload": b"", "crc": crc})
            if cfg.coder == "arith":
                coded.append(range(n, n := n + len(s["lists"])))
                yield from s["lists"]
            else:
                coded.append([code(x, cfg.coder) for x in s["lists"]])

    done = ac_encode_many(lists())
    for e, parts in zip(out, coded, strict=True):
        parts = [done[p] if isinstance(p, int) else p for p in parts]
        e["model"] = put_varints([*e["model"], len(parts), *(len(p) for p, _ in parts)]) + b"".join(m for _, m in parts)
        e["payload"] = b"".join(p for p, _ in parts)
    return out


def decode_group(row: dict, lengths: list[int], cfg: Config) -> list[np.ndarray]:
    (n,), at = get_varints(row["model"], 1)
    head, at = get_varints(row["model"], n + 2, at)
    firsts = [int(v) for v in unzigzag(np.array(head[:n], np.int64))]
    primary, n_parts = head[n], head[n + 1]
    sizes, at = get_varints(row["model"], n_parts, at)
    lists, start = [], 0
    for size in sizes:
        x, at = decode(row["payload"][start : start + size], row["model"], at, cfg.coder)
        lists.append(x)
        start += size
    applied, t = row["applied"], row["t"]
    if cfg.rle in ("dynamic", "entropy"):
        x = rle_dynamic_inverse(applied, t, lists[0], lists[1] if applied else np.empty(0))
    elif cfg.rle == "static":
        x = rle_static_inverse(*lists)
    elif cfg.rle == "token":
        x = rle_tokens_inverse(*lists)
    elif cfg.rle == "rank_class":
        x = rle_classes_inverse({0: t & 255, 1: t >> 8 & 255, 2: t >> 16}, *lists)
    else:
        x = lists[0]
    if cfg.mtf:
        x = mtf_inverse(x, np.array(get_sorted(row["alphabet"])[0], np.int64))
    if cfg.bwt:
        x = bwt_inverse(x, primary, None if cfg.bwt == "cyclic" else cfg.bwt)
    lengths = np.array(lengths, np.int64)
    if cfg.delta_scope == "stream" and cfg.delta_order:
        cuts = np.minimum(lengths, cfg.delta_order)
        short = lengths - cuts
        joined = np.empty(int(short.sum()), np.int64)
        joined[column_order(short, cfg.layout)] = x
        parts, left = np.split(joined, np.cumsum(short)[:-1]) if len(short) else [], iter(firsts)
        out = [integrate([next(left) for _ in range(c)], p) for c, p in zip(cuts.tolist(), parts, strict=True)]
    else:
        x = integrate(firsts, x)
        joined = np.empty(len(x), np.int64)
        joined[column_order(lengths, cfg.layout)] = x
        out = np.split(joined, np.cumsum(lengths)[:-1]) if len(lengths) else []
    if zlib.crc32(np.concatenate(out).astype("<i8").tobytes() if out else b"") != row["crc"]:
        raise ValueError("a packed block does not decode to what was packed")
    return out

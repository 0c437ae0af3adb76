"""Run lengths: of every run, of marked runs, and adaptive ones that a block (or a class of ranks) uses where they pay."""

from __future__ import annotations

import numpy as np

THRESHOLDS = (2, 3, 4, 6, 8, 16)


def runs(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(symbol, length) of the maximal runs."""
    x = np.asarray(x, np.int64)
    if not len(x):
        return x, x
    starts = np.flatnonzero(np.concatenate([[True], x[1:] != x[:-1]]))
    return x[starts], np.diff(np.append(starts, len(x)))


def rle_static(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    return runs(x)


def rle_static_inverse(syms: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    return np.repeat(np.asarray(syms, np.int64), np.asarray(lengths, np.int64))


def rle_marked(x: np.ndarray) -> list[tuple[int, int | None]]:
    """Runs of two or more carry their length, others stand bare."""
    return [(int(s), int(n) if n > 1 else None) for s, n in zip(*runs(x), strict=True)]


def rle_marked_inverse(tokens: list[tuple[int, int | None]]) -> np.ndarray:
    return np.array([s for s, n in tokens for _ in range(n or 1)], np.int64)


def width(x: np.ndarray) -> int:
    """Bits of the largest value, one at least."""
    return max(1, int(np.max(x)).bit_length()) if len(x) else 1


def cut(x: np.ndarray, t: int) -> tuple[np.ndarray, np.ndarray]:
    """Runs cut to t copies; each run of t or more adds the rest of its length to the counts."""
    syms, lengths = runs(x)
    return np.repeat(syms, np.minimum(lengths, t)), lengths[lengths >= t] - t


def rle_dynamic(x: np.ndarray, thresholds: tuple[int, ...] = THRESHOLDS, cost: str = "bits") -> tuple[bool, int, np.ndarray, np.ndarray]:
    """(applied, threshold, symbols, counts): the cheapest threshold, or off where none beats the plain block; ties to
    off, then to the smaller threshold. cost "entropy" compares zero-order bits instead of fixed widths."""
    x = np.asarray(x, np.int64)
    lengths, wide = runs(x)[1], width(x)

    def bits(t: int) -> int:
        counts = lengths[lengths >= t] - t
        return int(np.minimum(lengths, t).sum()) * wide + len(counts) * width(counts)

    price = bits if cost == "bits" else (lambda t: sum(map(ideal_bits, cut(x, t))))
    off = len(x) * wide if cost == "bits" else ideal_bits(x)
    best, t = min(((price(t), t) for t in thresholds), default=(off, 0))
    if best >= off:
        return False, 0, x, np.empty(0, np.int64)
    return True, t, *cut(x, t)


def rle_dynamic_inverse(applied: bool, t: int, syms: np.ndarray, counts: np.ndarray) -> np.ndarray:
    syms = np.asarray(syms, np.int64)
    if not applied:
        return syms
    values, lengths = runs_upto(syms, t, iter(np.asarray(counts).tolist()))
    return np.repeat(np.array(values, np.int64), np.array(lengths, np.int64))


def runs_upto(syms: np.ndarray, t: int, counts) -> tuple[list[int], list[int]]:
    """Runs of a cut block: wherever t copies stand together, the next count tells how many more there were."""
    values, lengths = [], []
    for s, n in zip(*(a.tolist() for a in runs(syms)), strict=True):
        values.append(s)
        lengths.append(n + next(counts) if n >= t else n)
    return values, lengths


def rle_tokens(x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """One bit a token: 0 a literal, 1 a run with its length. (bits, symbols, lengths of runs)"""
    syms, lengths = runs(x)
    flags = lengths > 1
    return flags.astype(np.int64), syms, lengths[flags]


def rle_tokens_inverse(flags: np.ndarray, syms: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    n = np.ones(len(syms), np.int64)
    n[np.asarray(flags, bool)] = lengths
    return np.repeat(np.asarray(syms, np.int64), n)


def rle_classes(x: np.ndarray, thresholds: tuple[int, ...] = THRESHOLDS) -> tuple[dict[int, int], np.ndarray, np.ndarray]:
    """A threshold for each class of ranks (0 zero, 1 one, 2 others; 0 as threshold: off), the symbols, the counts."""
    syms, lengths = runs(x)
    kind = np.minimum(syms, 2)
    w, chosen = width(x), {}
    for c in range(3):
        own = lengths[kind == c]
        off = int(own.sum()) * w
        price = lambda t, own=own: int(np.minimum(own, t).sum()) * w + int((own >= t).sum()) * width(own[own >= t] - t)
        best, t = min(((price(t), t) for t in thresholds), default=(off, 0))
        chosen[c] = t if len(own) and best < off else 0
    t = np.array([chosen[c] or np.iinfo(np.int64).max for c in range(3)])[kind]
    return chosen, np.repeat(syms, np.minimum(lengths, t)), (lengths - t)[lengths >= t]


def rle_classes_inverse(chosen: dict[int, int], syms: np.ndarray, counts: np.ndarray) -> np.ndarray:
    values, lengths, left = [], [], iter(np.asarray(counts).tolist())
    for s, n in zip(*(a.tolist() for a in runs(syms)), strict=True):
        t = chosen[min(s, 2)]
        values.append(s)
        lengths.append(n + next(left) if t and n >= t else n)
    return np.repeat(np.array(values, np.int64), np.array(lengths, np.int64))


def ideal_bits(x: np.ndarray) -> float:
    """Zero-order bits of a block: its length times its entropy."""
    if not len(x):
        return 0.0
    _, n = np.unique(x, return_counts=True)
    return float(-(n * np.log2(n / len(x))).sum())

"""Block-sorting transform of integer blocks by prefix doubling: O(n) memory, no matrix of rotations."""

from __future__ import annotations

import numpy as np

from meterpack.kernels.arith import counted


def rotation_order(x: np.ndarray) -> np.ndarray:
    """Starts of the cyclic rotations of x in ascending order; equal rotations by start. After the first two symbols only rotations
    that are still alike are sorted on: a rank is the place of the first of those alike."""
    n = len(x)
    kinds, symbol, counts = counted(x)
    if n < 2 or len(kinds) == n:
        return np.argsort(symbol, kind="stable")
    key = symbol * len(kinds) + np.append(symbol[1:], symbol[:1])
    order = np.argsort(key)
    rank, alike = np.empty(n, np.int64), order
    place, step = np.arange(n), 2
    value = key[order]
    while True:
        head = np.concatenate([[True], value[1:] != value[:-1]])
        first = place[np.maximum.accumulate(np.where(head, np.arange(len(alike)), 0))]
        rank[alike] = first
        tied = ~(head & np.append(head[1:], True))
        alike, place = alike[tied], place[tied]
        if step >= n:  # equal rotations by start
            order[place] = alike[np.lexsort((alike, first[tied]))]
        if not len(alike) or step >= n:
            return order
        value = first[tied] * n + rank[(alike + step) % n]
        by = np.argsort(value)
        alike, value = alike[by], value[by]
        order[place] = alike
        step *= 2


def bwt(x: np.ndarray, sentinel: str | None = None) -> tuple[np.ndarray, int]:
    """(last column, row of the original block, from 0). sentinel "low" or "high" first appends a symbol of its own,
    below or above all others, and the column then has one symbol more."""
    x = np.asarray(x, np.int64)
    if sentinel:
        edge = (x.min() - 1 if sentinel == "low" else x.max() + 1) if len(x) else 0
        x = np.append(x, edge)
    if not len(x):
        return x, 0
    order = rotation_order(x)
    return x[order - 1], int(np.flatnonzero(order == 0)[0])


def bwt_inverse(last: np.ndarray, primary: int, sentinel: str | None = None) -> np.ndarray:
    """The block whose transform this is: each symbol's row follows from a stable sort of the last column."""
    last = np.asarray(last, np.int64)
    n = len(last)
    if not n:
        return last
    follow = np.argsort(last, kind="stable").tolist()
    rows, at = [0] * n, primary
    for i in range(n):
        at = follow[at]
        rows[i] = at
    out = last[rows]
    return out[:-1] if sentinel else out

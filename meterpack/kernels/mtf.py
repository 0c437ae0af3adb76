"""Move-to-front ranks over a sorted alphabet."""

from __future__ import annotations

import numpy as np

from meterpack.kernels.arith import counted


#: Alphabets above this do not go through a list: ranks are counted by bits, and found back by a tree of recency.
LARGE = 512


class Recency:
    """Marks on a line of slots, one a symbol, the front symbol on the highest; a Fenwick tree counts and finds them."""

    def __init__(self, size: int, moves: int) -> None:
        self.n = size + moves
        self.tree = [0] * (self.n + 1)
        for i in range(1, self.n + 1):
            self.tree[i] += i <= size
            up = i + (i & -i)
            if up <= self.n:
                self.tree[up] += self.tree[i]
        self.size, self.next, self.top = size, size, 1 << (self.n.bit_length() - 1)

    def move(self, slot: int) -> int:
        """Takes the mark from this slot to a new one in front."""
        tree, n = self.tree, self.n
        for i, by in ((slot + 1, -1), (self.next + 1, 1)):
            while i <= n:
                tree[i] += by
                i += i & -i
        self.next += 1
        return self.next - 1

    def find(self, rank: int) -> int:
        """The slot of the mark that has `rank` marks in front of it."""
        want, i, step, tree, n = self.size - rank, 0, self.top, self.tree, self.n
        while step:
            if i + step <= n and tree[i + step] < want:
                i += step
                want -= tree[i]
            step >>= 1
        return i


#: Bits of a stretch that is counted by blocks, and most symbols of a block.
STRETCH_BITS, SIDE = 18, 256


def _larger_within(rank: np.ndarray) -> np.ndarray:
    """larger_before of a permutation of 0..n-1: places and ranks are cut into blocks. A larger one before is in the same block of
    places, or in one before and in the same block of ranks, or in one before and in a higher block of ranks, by a table."""
    n = len(rank)
    side = min(SIDE, 1 << (max(1, n - 1).bit_length() + 1) // 2)
    m = -(-n // side)
    rank = np.concatenate([rank, np.arange(n, m * side)])
    place = np.empty(m * side, np.int64)
    place[rank] = np.arange(m * side)
    cell = np.arange(m * side) // side * m + rank // side
    table = np.bincount(cell, minlength=m * m).reshape(m, m).astype(np.int32)
    higher = np.cumsum(table[:, ::-1], 1)[:, ::-1] - table
    out = (np.cumsum(higher, 0) - higher).reshape(-1)[cell].astype(np.int64)
    own, seen = np.ascontiguousarray(rank.reshape(m, side).T.astype(np.int32)), np.zeros((side, m), np.uint8)
    for j in range(side - 1):
        seen[j + 1 :] += (own[j] > own[j + 1 :]).view(np.uint8)
    out += seen.T.reshape(-1)
    block, seen = np.ascontiguousarray((place // side).reshape(m, side).T.astype(np.int32)), np.zeros((side, m), np.uint8)
    for j in range(1, side):
        seen[:j] += (block[j] < block[:j]).view(np.uint8)
    return (out + seen.T.reshape(-1)[rank])[:n]


def larger_before(x: np.ndarray) -> np.ndarray:
    """For each of some different integers how many before it are larger: by the bits of their ranks from the top, with all that
    share the bits above in one stretch, in the order in which they came; short stretches by blocks."""
    n = len(x)
    rank = np.empty(n, np.int64)
    rank[np.argsort(x, kind="stable")] = np.arange(n)
    out, here = np.zeros(n, np.int64), np.arange(n)
    for bit in range(max(0, n - 1).bit_length() - 1, STRETCH_BITS - 1, -1):
        r = rank[here]
        ones = r >> bit & 1
        start = r >> bit + 1 << bit + 1
        upto = np.concatenate([[0], np.cumsum(ones)])
        before = upto[:-1] - upto[start]
        low = ones == 0
        out[here[low]] += before[low]
        there = np.where(low, np.arange(n) - before, start + (1 << bit) + before)
        here[there] = here.copy()
    for start in range(0, n, 1 << STRETCH_BITS):
        own = here[start : start + (1 << STRETCH_BITS)]
        out[own] += _larger_within(rank[own] - start)
    return out


def order_of(x: np.ndarray) -> np.ndarray:
    """Places of small integers in ascending order, equal ones as they came: by 16 bits at a time."""
    order = np.argsort((x & 0xFFFF).astype(np.uint16), kind="stable")
    shift = 16
    while len(x) and int(x.max()) >> shift:
        order = order[np.argsort((x[order] >> shift & 0xFFFF).astype(np.uint16), kind="stable")]
        shift += 16
    return order


def _ranks(symbols: np.ndarray, size: int) -> np.ndarray:
    """How many different symbols came since the symbol's last place, where symbol s stood at -1 - s at first: the places between,
    less those whose symbol came there again."""
    at = np.concatenate([np.arange(-size, 0), np.arange(len(symbols))])
    every = np.concatenate([np.arange(size - 1, -1, -1), symbols])
    order = order_of(every)
    last = np.empty(len(every), np.int64)
    last[order[1:]] = at[order[:-1]]
    last = last[size:]  # a symbol's first place in the list is the one it stood at
    return at[size:] - last - 1 - larger_before(last)


def _symbols(ranks: list[int], size: int) -> list[int]:
    line, owner, out = Recency(size, len(ranks)), list(range(size - 1, -1, -1)) + [0] * len(ranks), []
    for r in ranks:
        slot = line.find(r)
        s = owner[slot]
        out.append(s)
        owner[line.move(slot)] = s
    return out


def mtf(x: np.ndarray, alphabet: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(ranks, alphabet). Runs are zeros but for their first symbol, so only run heads go through the list."""
    x = np.asarray(x, np.int64)
    if alphabet is None:
        alphabet, places, _ = counted(x)
    else:
        alphabet, places = np.asarray(alphabet, np.int64), None
    ranks = np.zeros(len(x), np.int64)
    if not len(x):
        return ranks, alphabet
    heads = np.flatnonzero(np.concatenate([[True], x[1:] != x[:-1]]))
    if len(alphabet) > LARGE:
        if places is None:
            place = {} if (np.diff(alphabet) > 0).all() else {int(a): i for i, a in enumerate(alphabet)}
            places = np.array([place[s] for s in x.tolist()]) if place else np.searchsorted(alphabet, x)
        ranks[heads] = _ranks(places[heads], len(alphabet))
        return ranks, alphabet
    table = alphabet.tolist()
    found = []
    for s in x[heads].tolist():
        r = table.index(s)
        found.append(r)
        if r:
            table.insert(0, table.pop(r))
    ranks[heads] = found
    return ranks, alphabet


def mtf_inverse(ranks: np.ndarray, alphabet: np.ndarray) -> np.ndarray:
    ranks, table = np.asarray(ranks, np.int64), np.asarray(alphabet, np.int64).tolist()
    out = np.empty(len(ranks), np.int64)
    moves = np.flatnonzero(ranks)
    if len(table) > LARGE:
        places = np.zeros(len(ranks), np.int64)
        places[moves] = np.arange(1, len(moves) + 1)
        chosen = np.array([0, *_symbols(ranks[moves].tolist(), len(table))])
        return np.array(table, np.int64)[chosen[np.maximum.accumulate(places)]]
    at = 0
    for i, r in zip(moves.tolist(), ranks[moves].tolist(), strict=True):
        out[at:i] = table[0] if i > at else 0
        table.insert(0, table.pop(r))
        out[i] = table[0]
        at = i + 1
    if at < len(out):
        out[at:] = table[0]
    return out

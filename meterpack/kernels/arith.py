"""Arithmetic coding: a 64-bit range coder over integer counts, with static, adaptive and Gaussian models, and the exact
form over fractions for worked examples."""

from __future__ import annotations

import math
from bisect import bisect_right
from collections.abc import Callable, Iterable
from fractions import Fraction
from statistics import NormalDist

import numpy as np

from meterpack.kernels.bits import get_sorted, get_varints, put_sorted, put_varints

MASK = (1 << 64) - 1
TOP, LEAST = 1 << 56, 1 << 48


class Encoder:
    """Bytes leave at the top as soon as the interval agrees on them; an interval that straddles a byte border for too
    long is cut at the border, so no carry ever runs back."""

    def __init__(self) -> None:
        self.low, self.range, self.out = 0, MASK, bytearray()

    def put(self, cum: int, freq: int, total: int) -> None:
        low, rng = self.low, self.range // total
        low = (low + rng * cum) & MASK
        rng *= freq
        while True:
            if (low ^ (low + rng)) >= TOP:
                if rng >= LEAST:
                    break
                rng = -low & (LEAST - 1)
            self.out.append(low >> 56)
            low, rng = (low << 8) & MASK, rng << 8
        self.low, self.range = low, min(rng, MASK)

    def end(self) -> bytes:
        """The fewest bytes of which every continuation lies in the last interval, so that they are no fewer than the
        interval's width asks for."""
        for n in range(9):
            unit = 1 << (64 - 8 * n)
            value = -(-self.low // unit) * unit
            if value + unit <= self.low + self.range:
                break
        return bytes(self.out) + value.to_bytes(9, "big")[1 : n + 1]


class Decoder:
    def __init__(self, data: bytes) -> None:
        self.data, self.at, self.low, self.range = data, 8, 0, MASK
        self.code = int.from_bytes(data[:8].ljust(8, b"\0"), "big")

    def where(self, total: int) -> int:
        self.range //= total
        return min(total - 1, ((self.code - self.low) & MASK) // self.range)

    def take(self, cum: int, freq: int) -> None:
        low, rng, code = (self.low + self.range * cum) & MASK, self.range * freq, self.code
        while True:
            if (low ^ (low + rng)) >= TOP:
                if rng >= LEAST:
                    break
                rng = -low & (LEAST - 1)
            b = self.data[self.at] if self.at < len(self.data) else 0
            self.at += 1
            code = (code << 8 | b) & MASK
            low, rng = (low << 8) & MASK, rng << 8
        self.low, self.range, self.code = low, min(rng, MASK), code


#: Lists that are coded in step: from FEW on (less are coded one by one), and so many at most. Symbols of a list that are laid out at once.
FEW, MOST, STRIDE = 12, 2048, 512


def put_lanes(lanes: list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray | int]]) -> list[bytes]:
    """What an Encoder of its own makes of each lane, all in step. A lane is the places of its symbols in a table of (cum, freq,
    total); total is one number where all have the same."""
    if len(lanes) < FEW:
        out = []
        for place, cums, freqs, totals in lanes:
            enc, cums, freqs = Encoder(), cums.tolist(), freqs.tolist()
            totals = [totals] * len(cums) if isinstance(totals, int) else totals.tolist()
            for i in place.tolist():
                enc.put(cums[i], freqs[i], totals[i])
            out.append(enc.end())
        return out
    order = sorted(range(len(lanes)), key=lambda i: -len(lanes[i][0]))
    if len(lanes) > MOST:
        found: list[bytes] = [b""] * len(lanes)
        for start in range(0, len(lanes), MOST):
            own = order[start : start + MOST]
            for i, data in zip(own, put_lanes([lanes[i] for i in own]), strict=True):
                found[i] = data
        return found
    lengths = np.array([len(lanes[i][0]) for i in order], np.int64)
    mixed = any(not isinstance(lane[3], int) for lane in lanes)
    tables = [lanes[i][1:] for i in order]
    low, rng = np.zeros(len(lanes), np.uint64), np.full(len(lanes), MASK, np.uint64)
    total = np.ones(len(lanes), np.uint64) if mixed else np.array([t[2] for t in tables], np.uint64)
    out = [bytearray() for _ in lanes]
    for start in range(0, int(lengths[0]), STRIDE):
        n = int(np.searchsorted(-lengths, -start, "left"))  # lanes that have symbols left
        steps = min(STRIDE, int(lengths[0]) - start)
        # behind its end a lane has the whole of its interval, which leaves it as it is
        cum, freq, of = np.zeros((n, steps), np.uint64), np.ones((n, steps), np.uint64), np.ones((n, steps), np.uint64) if mixed else None
        for lane in range(n):
            place = lanes[order[lane]][0][start : start + steps]
            cum[lane, : len(place)], freq[lane, : len(place)] = tables[lane][0][place], tables[lane][1][place]
            if mixed:
                of[lane, : len(place)] = tables[lane][2] if isinstance(tables[lane][2], int) else tables[lane][2][place]
        cum, freq, of = np.ascontiguousarray(cum.T), np.ascontiguousarray(freq.T), np.ascontiguousarray(of.T) if mixed else None
        ends: dict[int, list[int]] = {}
        for lane in np.flatnonzero(lengths[:n] < start + steps).tolist():
            ends.setdefault(int(lengths[lane]) - start, []).append(lane)
        _put_stretch(cum, freq, of, ends, low[:n], rng[:n], total[:n], out)
    done: list[bytes] = [b""] * len(lanes)
    for lane, i in enumerate(order):
        enc = Encoder()
        enc.low, enc.range, enc.out = int(low[lane]), int(rng[lane]), out[lane]
        done[i] = enc.end()
    return done


def _put_stretch(cum: np.ndarray, freq: np.ndarray, of: np.ndarray | None, ends: dict[int, list[int]], low: np.ndarray, rng: np.ndarray, total: np.ndarray, out: list[bytearray]) -> None:
    """One row of symbols after another, in all lanes at once; low and rng are changed in place."""
    n = len(low)
    # constants as arrays: numpy takes longer over a scalar
    least, eleven, exponent, most, whole = (np.full(n, v, np.uint64) for v in (LEAST, 11, 52, 1075, 56))
    x, y, f, small = np.empty(n, np.uint64), np.empty(n, np.uint64), np.empty(n), np.empty(n, bool)
    bits, whole_x = f.view(np.uint64), x.view(np.int64)
    tops, shifts = [], []
    for t in range(len(cum)):
        if of is not None:
            total = of[t]
        elif t in ends:
            total[ends[t]] = 1
        np.floor_divide(rng, total, out=y)
        np.multiply(y, freq[t], out=rng)
        np.multiply(y, cum[t], out=y)
        np.add(low, y, out=low)
        np.add(low, rng, out=x)
        np.bitwise_xor(low, x, out=x)
        # leading bytes on which both ends agree, in bits: the exponent tells the highest bit; 53 bits are not rounded, and an
        # interval is far above the rest
        np.right_shift(x, eleven, out=x)
        np.copyto(f, whole_x)
        shift = np.right_shift(bits, exponent)
        np.subtract(most, shift, out=shift)
        np.bitwise_and(shift, whole, out=shift)
        tops.append(low.copy())
        shifts.append(shift)
        np.left_shift(low, shift, out=low)
        np.left_shift(rng, shift, out=rng)
        np.less(rng, least, out=small)
        if np.count_nonzero(small):  # an interval that straddles a border is cut there; its bytes are the next of the same low end
            for lane in np.flatnonzero(small).tolist():
                lo, r, gone = int(low[lane]), int(rng[lane]), int(shift[lane])
                while True:
                    if (lo ^ (lo + r)) >= TOP:
                        if r >= LEAST:
                            break
                        r = -lo & (LEAST - 1)
                    lo, r, gone = (lo << 8) & MASK, r << 8, gone + 8
                shift[lane], low[lane], rng[lane] = gone, lo, min(r, MASK)
    s = np.stack(shifts, 1).astype(np.uint8)
    width = 4 if s.max() <= 32 else 8
    data = np.stack(tops, 1)
    data = (data >> np.uint64(32)).astype(">u4") if width == 4 else data.astype(">u8")
    data = data.view(np.uint8).reshape(n, -1, width)[np.arange(width, dtype=np.uint8) * 8 < s[:, :, None]].tobytes()
    cuts = np.cumsum(s.sum(1, dtype=np.int64) // 8).tolist()
    for lane, (a, z) in enumerate(zip([0, *cuts], cuts, strict=False)):
        out[lane] += data[a:z]


def counted(x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(symbols, place of each among them, counts), symbols rising: by a table over their span where that is not much larger than
    the block, else by sorting."""
    if len(x):
        least, most = int(x.min()), int(x.max())
        if most - least < 4 * len(x) + 1024:
            there = x - least
            counts = np.bincount(there)
            kinds = np.flatnonzero(counts)
            if len(kinds) == len(counts):
                return kinds + least, there, counts
            places = np.empty(len(counts), np.int64)
            places[kinds] = np.arange(len(kinds))
            return kinds + least, places[there], counts[kinds]
    return np.unique(x, return_inverse=True, return_counts=True)


def put_model(symbols: np.ndarray, freqs: np.ndarray) -> bytes:
    return put_sorted(symbols) + put_varints(freqs)


def get_model(data: bytes, at: int = 0) -> tuple[list[int], list[int], int]:
    symbols, at = get_sorted(data, at)
    freqs, at = get_varints(data, len(symbols), at)
    return symbols, freqs, at


def ac_encode(x: np.ndarray) -> tuple[bytes, bytes]:
    """(payload, model) with the block's own symbol counts as the model. A block of one symbol needs no payload."""
    return ac_encode_many([x])[0]


def ac_encode_many(blocks: Iterable[np.ndarray]) -> list[tuple[bytes, bytes]]:
    """ac_encode of each, coded in step; a block is held in half its bytes until then."""
    models, lanes, which = [], [], []
    for i, x in enumerate(blocks):
        symbols, place, freqs = counted(np.asarray(x, np.int64))
        models.append(put_model(symbols, freqs))
        if len(symbols) > 1:
            small = np.uint32 if len(x) < 1 << 32 else np.uint64
            lanes.append((place.astype(np.int32), (np.cumsum(freqs) - freqs).astype(small), freqs.astype(small), len(x)))
            which.append(i)
    payloads = dict(zip(which, put_lanes(lanes), strict=True))
    return [(payloads.get(i, b""), m) for i, m in enumerate(models)]


def ac_decode(payload: bytes, model: bytes, at: int = 0) -> tuple[np.ndarray, int]:
    """(block, place behind its model)."""
    symbols, freqs, at = get_model(model, at)
    total = sum(freqs)
    if len(symbols) < 2:
        return np.full(total, symbols[0] if symbols else 0, np.int64), at
    cums = np.cumsum([0, *freqs]).tolist()
    dec, out = Decoder(payload), []
    for _ in range(total):
        i = bisect_right(cums, dec.where(total)) - 1
        dec.take(cums[i], freqs[i])
        out.append(i)
    return np.array(symbols, np.int64)[out], at


class Fenwick:
    """Counts of n symbols, one each at first, with prefix sums and search in log(n) steps."""

    def __init__(self, n: int) -> None:
        self.n, self.total = n, n
        self.tree = [i & -i for i in range(n + 1)]
        self.top = 1 << (n.bit_length() - 1) if n else 0

    def before(self, i: int) -> int:
        out = 0
        while i:
            out += self.tree[i]
            i &= i - 1
        return out

    def add(self, i: int, by: int) -> None:
        self.total += by
        i += 1
        while i <= self.n:
            self.tree[i] += by
            i += i & -i

    def find(self, at: int) -> tuple[int, int]:
        """(symbol, count of all before it) at this place of the cumulated counts."""
        i, cum, step = 0, 0, self.top
        while step:
            if i + step <= self.n and cum + self.tree[i + step] <= at:
                i += step
                cum += self.tree[i]
            step >>= 1
        return i, cum


#: How much a symbol gains each time it comes.
GAIN = 32


def adaptive_encode(x: np.ndarray) -> tuple[bytes, bytes]:
    """(payload, side data): only the alphabet and the length travel, counts are learnt on both sides."""
    x = np.asarray(x, np.int64)
    symbols, place = np.unique(x, return_inverse=True)
    side = put_varints([len(x)]) + put_sorted(symbols)
    if len(symbols) < 2:
        return b"", side
    tree, enc = Fenwick(len(symbols)), Encoder()
    for i in place.tolist():
        cum = tree.before(i)
        enc.put(cum, tree.before(i + 1) - cum, tree.total)
        tree.add(i, GAIN)
    return enc.end(), side


def adaptive_decode(payload: bytes, side: bytes, at: int = 0) -> tuple[np.ndarray, int]:
    (n,), at = get_varints(side, 1, at)
    symbols, at = get_sorted(side, at)
    if len(symbols) < 2:
        return np.full(n, symbols[0] if symbols else 0, np.int64), at
    tree, dec, out = Fenwick(len(symbols)), Decoder(payload), []
    for _ in range(n):
        i, cum = tree.find(dec.where(tree.total))
        dec.take(cum, tree.before(i + 1) - cum)
        tree.add(i, GAIN)
        out.append(i)
    return np.array(symbols, np.int64)[out], at


#: The Gaussian model: parameters in 1/16, deviations to each side, counts in all, raw bits of an escaped symbol.
QUANTUM, REACH, COUNTS, RAW = 16, 8, 1 << 20, 34


#: The inverse of the normal distribution, for a first guess.
GUESS = NormalDist().inv_cdf


def gaussian_counts(mu16: int, sigma16: int) -> tuple[int, int, Callable[[int], int]]:
    """(first symbol, symbols within REACH deviations, cumulated counts of the first i of them). One more count, behind them,
    is the escape. Each symbol has a count of its own besides its share, so that none has nothing; no table is made."""
    mu, sigma = mu16 / QUANTUM, max(1, sigma16) / QUANTUM
    first = math.floor(mu - REACH * sigma)
    n = math.ceil(mu + REACH * sigma) - first + 1
    start, scale, half, erf = first - 0.5 - mu, 1 / (sigma * math.sqrt(2)), COUNTS // 2, math.erf
    return first, n, lambda i: int((1 + erf((start + i) * scale)) * half) + i


def gaussian_encode(x: np.ndarray) -> tuple[bytes, int, int]:
    """(payload, mean and deviation in 1/16): the two numbers are the whole model."""
    return gaussian_encode_many([x])[0]


def gaussian_encode_many(blocks: list[np.ndarray]) -> list[tuple[bytes, int, int]]:
    """gaussian_encode of each, coded in step."""
    out: list[tuple[bytes, int, int]] = [(b"", 0, 1)] * len(blocks)
    lanes, which = [], []
    for at, x in enumerate(blocks):
        x = np.asarray(x, np.int64)
        if not len(x):
            continue
        mu16, sigma16 = int(round(float(x.mean()) * QUANTUM)), max(1, int(round(float(x.std()) * QUANTUM)))
        first, n, cum = gaussian_counts(mu16, sigma16)
        escape = cum(n)
        symbols, place = np.unique(x, return_inverse=True)
        table, parts = [], []  # what is put, and the row of an escaped symbol's two parts
        for s in symbols.tolist():
            i = s - first
            if 0 <= i < n:
                table.append(((below := cum(i)), cum(i + 1) - below, escape + 1))
            else:
                parts.append((len(table), s + (1 << (RAW - 1))))
                table.append((escape, 1, escape + 1))
        if parts:
            more, follow = np.ones(len(symbols), np.int64), np.zeros(len(symbols), np.int64)
            for row, s in parts:
                more[row], follow[row] = 3, len(table)
                table += [(s >> 17, 1, 1 << (RAW - 17)), (s & 0x1FFFF, 1, 1 << 17)]
            heads = np.cumsum(more[place]) - more[place]
            long = np.empty(int(more[place].sum()), np.int64)
            long[heads] = place
            escaped = more[place] == 3
            long[heads[escaped] + 1], long[heads[escaped] + 2] = follow[place[escaped]], follow[place[escaped]] + 1
            place = long
        cums, freqs, totals = (np.array(c, np.int64) for c in zip(*table, strict=True))
        lanes.append((place, cums, freqs, totals if parts else escape + 1))
        which.append((at, mu16, sigma16))
    for (at, mu16, sigma16), payload in zip(which, put_lanes(lanes), strict=True):
        out[at] = payload, mu16, sigma16
    return out


def _place(at: int, n: int, cum: Callable[[int], int], guess: int) -> int:
    """The last of n symbols whose cumulated counts do not exceed `at`: a gallop from a guess, then halving."""
    low = high = max(0, min(n - 1, guess))
    step = 1
    if cum(low) <= at:
        while (high := low + step) < n and cum(high) <= at:
            low, step = high, 2 * step
        high = min(high, n)
    else:
        while (low := max(0, high - step)) and cum(low) > at:
            high, step = low, 2 * step
    while high - low > 1:
        middle = (low + high) // 2
        if cum(middle) <= at:
            low = middle
        else:
            high = middle
    return low


def gaussian_decode(payload: bytes, mu16: int, sigma16: int, n: int) -> np.ndarray:
    out, dec = [], Decoder(payload)
    if n:
        first, size, cum = gaussian_counts(mu16, sigma16)
        escape = cum(size)
        sigma, centre = max(1, sigma16) / QUANTUM, mu16 / QUANTUM - first
        i, below, above = 0, 0, 0
    for _ in range(n):
        at = dec.where(escape + 1)
        if at < escape:
            if not below <= at < above:  # not the symbol before
                i = _place(at, size, cum, int(centre + sigma * GUESS((at + 0.5) / escape)))
                below, above = cum(i), cum(i + 1)
            dec.take(below, above - below)
            out.append(first + i)
            continue
        dec.take(escape, 1)
        high = dec.where(1 << (RAW - 17))
        dec.take(high, 1)
        low = dec.where(1 << 17)
        dec.take(low, 1)
        out.append((high << 17 | low) - (1 << (RAW - 1)))
    return np.array(out, np.int64)


def exact_interval(message: Iterable, ranges: dict) -> tuple[Fraction, Fraction]:
    """The interval of a message under cumulative ranges, in exact fractions."""
    low, width = Fraction(0), Fraction(1)
    for s in message:
        a, b = ranges[s]
        low, width = low + width * a, width * (b - a)
    return low, low + width


def exact_message(tag: Fraction, ranges: dict, n: int) -> list:
    """The n symbols whose interval holds the tag."""
    out = []
    for _ in range(n):
        s, (a, b) = next((s, r) for s, r in ranges.items() if r[0] <= tag < r[1])
        out.append(s)
        tag = (tag - a) / (b - a)
    return out

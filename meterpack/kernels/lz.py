"""Dictionary coders over byte or word symbols: a sliding window, a growing phrase list, and its variant with codes only."""

from __future__ import annotations

import numpy as np

from meterpack.kernels.bits import get_varints, put_varints

WINDOW, SHORTEST, CHAIN = 1 << 15, 3, 16


def lz77_encode(x: np.ndarray) -> bytes:
    """Literal runs and (distance, length) copies from the last WINDOW symbols, found by chains of three-symbol keys."""
    s = np.asarray(x, np.int64).tolist()
    out, heads, literals, i, n = [len(s)], {}, [], 0, len(s)
    while i < n:
        best, dist = 0, 0
        if i + SHORTEST <= n:
            key = (s[i], s[i + 1], s[i + 2])
            chain = heads.setdefault(key, [])
            for j in reversed(chain[-CHAIN:]):
                if i - j > WINDOW:
                    break
                k = SHORTEST
                while i + k < n and s[j + k] == s[i + k]:
                    k += 1
                if k > best:
                    best, dist = k, i - j
            chain.append(i)
        if best >= SHORTEST:
            out += [len(literals), *literals, best, dist]
            literals = []
            for j in range(i + 1, min(i + best, n - SHORTEST + 1)):
                heads.setdefault((s[j], s[j + 1], s[j + 2]), []).append(j)
            i += best
        else:
            literals.append(s[i])
            i += 1
    return put_varints([*out, len(literals), *literals])


def lz77_decode(data: bytes) -> np.ndarray:
    v, _ = get_varints(data)
    n, at, out = v[0], 1, []
    while at < len(v):
        k = v[at]
        out += v[at + 1 : at + 1 + k]
        at += 1 + k
        if at < len(v):
            length, dist = v[at : at + 2]
            at += 2
            for _ in range(length):
                out.append(out[-dist])
    return np.array(out[:n], np.int64)


def lz78_encode(x: np.ndarray) -> bytes:
    """(phrase, next symbol) pairs; phrase 0 is empty. A last phrase without a symbol has no partner."""
    phrases: dict[tuple[int, int], int] = {}
    out, at = [], 0
    for s in np.asarray(x, np.int64).tolist():
        if (at, s) in phrases:
            at = phrases[at, s]
        else:
            out += [at, s]
            phrases[at, s] = len(phrases) + 1
            at = 0
    return put_varints(out + [at] * (at > 0))


def lz78_decode(data: bytes) -> np.ndarray:
    v, _ = get_varints(data)
    phrases: list[list[int]] = [[]]
    out: list[int] = []
    for i in range(0, len(v), 2):
        phrase = phrases[v[i]] + v[i + 1 : i + 2]
        phrases.append(phrase)
        out += phrase
    return np.array(out, np.int64)


#: Entries at which the dictionary starts anew; codes take 16 bits at most.
FULL = (1 << 16) - 1


def _width(n: int) -> int:
    return max(9, n.bit_length())


def _single() -> list[bytes]:
    return [bytes((i,)) for i in range(256)]


def lzw_encode(data: bytes) -> bytes:
    """Codes of 9 to 16 bits over bytes, as wide as the dictionary asks for."""
    table = {b: i for i, b in enumerate(_single())}
    bits, at = [], b""
    for i in range(len(data)):
        b = data[i : i + 1]
        if at + b in table:
            at += b
            continue
        bits.append(format(table[at], f"0{_width(len(table))}b"))
        if len(table) < FULL:
            table[at + b] = len(table)
        else:
            table = {b: i for i, b in enumerate(_single())}
        at = b
    if at:
        bits.append(format(table[at], f"0{_width(len(table))}b"))
    s = "".join(bits)
    return put_varints([len(data)]) + (int(s.ljust(-(-len(s) // 8) * 8, "0"), 2).to_bytes(-(-len(s) // 8), "big") if s else b"")


def lzw_decode(coded: bytes) -> bytes:
    (n,), at = get_varints(coded, 1)
    bits = format(int.from_bytes(coded[at:], "big"), f"0{8 * (len(coded) - at)}b") if len(coded) > at else ""
    table, last, entries, out, size, i = _single(), b"", 256, [], 0, 0
    while size < n:
        w = _width(entries)
        code = int(bits[i : i + w], 2)
        i += w
        entry = table[code] if code < len(table) else last + last[:1]
        if last:
            table.append(last + entry[:1])
        out.append(entry)
        size += len(entry)
        if entries < FULL:
            entries, last = entries + 1, entry
        else:
            table, entries, last = _single(), 256, b""
    return b"".join(out)

"""Canonical Huffman codes over integer symbols."""

from __future__ import annotations

import heapq

import numpy as np

from meterpack.kernels.bits import get_sorted, get_varints, put_sorted, put_varints


def code_lengths(freqs: list[int]) -> list[int]:
    """Bits of each symbol in an optimal prefix code; one bit where there is one symbol only."""
    if len(freqs) < 2:
        return [1] * len(freqs)
    heap = [(f, i) for i, f in enumerate(freqs)]
    heapq.heapify(heap)
    parent: dict[int, int] = {}
    new = len(freqs)
    while len(heap) > 1:
        (f, a), (g, b) = heapq.heappop(heap), heapq.heappop(heap)
        parent[a] = parent[b] = new
        heapq.heappush(heap, (f + g, new))
        new += 1
    depth = {new - 1: 0}
    for node in range(new - 2, -1, -1):
        depth[node] = depth[parent[node]] + 1
    return [depth[i] for i in range(len(freqs))]


def canonical(lengths: list[int]) -> list[int]:
    """Codes in order of length, then of symbol."""
    codes, code, last = [0] * len(lengths), 0, 0
    for i in sorted(range(len(lengths)), key=lambda i: (lengths[i], i)):
        code <<= lengths[i] - last
        last = lengths[i]
        codes[i] = code
        code += 1
    return codes


def huffman_encode(x: np.ndarray) -> tuple[bytes, bytes, int]:
    """(payload, table, payload bits)."""
    x = np.asarray(x, np.int64)
    symbols, place, freqs = np.unique(x, return_inverse=True, return_counts=True)
    lengths = code_lengths(freqs.tolist())
    table = put_varints([len(x)]) + put_sorted(symbols) + put_varints(lengths)
    codes = [format(c, f"0{n}b") for c, n in zip(canonical(lengths), lengths, strict=True)]
    bits = "".join([codes[i] for i in place.tolist()])
    payload = int(bits.ljust(-(-len(bits) // 8) * 8, "0"), 2).to_bytes(-(-len(bits) // 8), "big") if bits else b""
    return payload, table, len(bits)


def huffman_decode(payload: bytes, table: bytes, at: int = 0) -> tuple[np.ndarray, int]:
    (n,), at = get_varints(table, 1, at)
    symbols, at = get_sorted(table, at)
    lengths, at = get_varints(table, len(symbols), at)
    by_code = {(length, code): s for length, code, s in zip(lengths, canonical(lengths), symbols, strict=True)}
    bits = format(int.from_bytes(payload, "big"), f"0{8 * len(payload)}b") if payload else ""
    out, code, length, i = [], 0, 0, 0
    while len(out) < n:
        code, length, i = code << 1 | (bits[i] == "1"), length + 1, i + 1
        if (length, code) in by_code:
            out.append(by_code[length, code])
            code = length = 0
    return np.array(out, np.int64), at

"""Variable-length integers and 16-bit words."""

from __future__ import annotations

from collections.abc import Iterable

import numpy as np


def zigzag(x: np.ndarray) -> np.ndarray:
    """Signed to unsigned, small values small."""
    x = np.asarray(x, np.int64)
    return np.where(x >= 0, 2 * x, -2 * x - 1)


def unzigzag(u: np.ndarray) -> np.ndarray:
    u = np.asarray(u, np.int64)
    return np.where(u & 1, -(u + 1) // 2, u // 2)


def put_varints(values: Iterable[int]) -> bytes:
    """Seven bits a byte, low bits first, high bit set on all but the last byte of a value."""
    if isinstance(values, np.ndarray) and values.dtype == np.int64:
        if values.min(initial=0) < 0:
            raise ValueError("a negative number has no varint")
        shifts = np.arange(0, max(7, int(values.max(initial=0)).bit_length()), 7)
        left = values[:, None] >> shifts
        more = left > 127
        kept = np.concatenate([np.ones((len(values), 1), bool), more[:, :-1]], 1)
        return (left & 127 | more * 128).astype(np.uint8)[kept].tobytes()
    out = bytearray()
    for v in values:
        v = int(v)
        while v > 127:
            out.append(v & 127 | 128)
            v >>= 7
        out.append(v)
    return bytes(out)


def get_varints(data: bytes, n: int | None = None, at: int = 0) -> tuple[list[int], int]:
    """n values (or all), and the place behind them."""
    out: list[int] = []
    value = shift = 0
    while at < len(data) and (n is None or len(out) < n):
        b = data[at]
        at += 1
        value |= (b & 127) << shift
        shift += 7
        if b < 128:
            out.append(value)
            value = shift = 0
    return out, at


def put_sorted(values: Iterable[int]) -> bytes:
    """A rising list of integers as its length, its first value (signed) and gaps."""
    if isinstance(values, np.ndarray) and values.dtype == np.int64 and len(values) and int(values[-1]) - int(values[0]) < 1 << 63:
        return put_varints([len(values), int(zigzag(values[0]))]) + put_varints(np.diff(values))
    values = [int(v) for v in values]
    if not values:
        return put_varints([0])
    gaps = [b - a for a, b in zip(values, values[1:], strict=False)]
    return put_varints([len(values), int(zigzag(np.array(values[0]))), *gaps])


def get_sorted(data: bytes, at: int = 0) -> tuple[list[int], int]:
    (n,), at = get_varints(data, 1, at)
    if not n:
        return [], at
    (first, *gaps), at = get_varints(data, n, at)
    out = [int(unzigzag(np.array(first)))]
    for g in gaps:
        out.append(out[-1] + g)
    return out, at


def to_words(data: bytes) -> np.ndarray:
    """Bytes as 16-bit words, big end first; an odd last byte is padded with zeros."""
    return np.frombuffer(data + b"\0" * (len(data) % 2), ">u2").astype(np.int32)


def from_words(words: np.ndarray, n_bytes: int) -> bytes:
    return np.asarray(words).astype(">u2").tobytes()[:n_bytes]

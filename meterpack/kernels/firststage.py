"""First-stage coders: a block of readings becomes a compressed stream of 16-bit words, and back.

A coder takes readings of 0..65535. Its wide form takes any 64-bit integer and nulls: what does not fit goes aside with its
place, in words before the stream, and comes back on decoding."""

from __future__ import annotations

import numpy as np

from meterpack.kernels.arith import gaussian_decode, gaussian_encode_many
from meterpack.kernels.bits import from_words, get_sorted, get_varints, put_sorted, put_varints, to_words, unzigzag, zigzag
from meterpack.kernels.huffman import huffman_decode, huffman_encode

PLAIN = ("identity", "gaussian_ac", "delta_gaussian_ac", "delta_huffman", "delta_varint")
WIDE = "wide_"
#: Packed rows name a coder by its place here.
CODERS = (*PLAIN, *(WIDE + c for c in PLAIN))
LARGEST = 65535
#: Bits of the two model parameters, and of a first value.
PARAM_BITS, FIRST_BITS = 32, 16


def encode_block(readings: np.ndarray, coder: str) -> tuple[int, int, int, int, np.ndarray]:
    """(n_bits, mu, sigma, first, words); mu and sigma in 1/16. n_bits has parameters in, padding out."""
    return encode_blocks([readings], [coder])[0]


def encode_blocks(blocks: list[np.ndarray], coders: list[str]) -> list[tuple[int, int, int, int, np.ndarray]]:
    """encode_block of each with its coder; Gaussian ones are coded in step."""
    sides = [_side(x) if c.startswith(WIDE) else None for x, c in zip(blocks, coders, strict=True)]
    plain = [c.removeprefix(WIDE) for c in coders]
    blocks = [np.asarray(x, np.int64) if side is None else side[1] for x, side in zip(blocks, sides, strict=True)]
    steps = [i for i, c in enumerate(plain) if c.endswith("gaussian_ac")]
    known = dict(zip(steps, gaussian_encode_many([np.diff(blocks[i]) if plain[i].startswith("delta") else blocks[i] for i in steps]), strict=True))
    out = []
    for i, (x, c, side) in enumerate(zip(blocks, plain, sides, strict=True)):
        if i in known:
            data, mu, sigma = known[i]
            delta = c.startswith("delta")
            e = 8 * len(data) + PARAM_BITS + (FIRST_BITS if delta else 0), mu, sigma, int(x[0]) if len(x) and delta else 0, to_words(data)
        else:
            e = _encode_plain(x, c)
        out.append(e if side is None else (e[0] + 16 * len(side[0]), *e[1:4], np.concatenate([side[0], e[4]]).astype(np.int32)))
    return out


def _encode_plain(x: np.ndarray, coder: str) -> tuple[int, int, int, int, np.ndarray]:
    if coder == "identity":
        return 16 * len(x), 0, 0, 0, x.astype(np.int32)
    first = int(x[0]) if len(x) and coder.startswith("delta") else 0
    body = np.diff(x) if coder.startswith("delta") else x
    if coder == "delta_varint":
        data = put_varints(zigzag(body))
    elif coder == "delta_huffman":
        payload, table, _ = huffman_encode(body)
        data = put_varints([len(table)]) + table + payload
    else:
        raise ValueError(f"no first-stage coder {coder!r}; there are {', '.join(CODERS)}")
    return 8 * len(data) + FIRST_BITS, 0, 0, first, to_words(data)


def unfit(readings: np.ndarray) -> np.ndarray:
    """Where readings are null (masked) or beyond 16 bits."""
    x = np.ma.getdata(readings)
    return np.ma.getmaskarray(readings) | (x < 0) | (x > LARGEST)


def coder_for(readings: np.ndarray, coder: str) -> str:
    """The coder, or its wide form where some reading does not fit."""
    return coder if coder.startswith(WIDE) or not unfit(readings).any() else WIDE + coder


def _side(readings: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(words of what does not fit, the block with zeros in its place)."""
    x, null, aside = np.ma.getdata(readings), np.ma.getmaskarray(readings), unfit(readings)
    places = np.flatnonzero(aside)
    # 0 is a null; Python's integers, since a 64-bit value may take 65 bits
    codes = (0 if null[p] else 1 + (2 * v if v >= 0 else -2 * v - 1) for p in places for v in (int(x[p]),))
    side = to_words(put_sorted(places) + put_varints(codes))
    return np.concatenate([[len(side) >> 16, len(side) & LARGEST], side]), np.asarray(np.where(aside, 0, x), np.int64)


def _decode_wide(words: np.ndarray, coder: str, n_readings: int, n_bits: int, mu: int, sigma: int, first: int) -> np.ndarray:
    n = int(words[0]) << 16 | int(words[1])
    side = from_words(words[2 : 2 + n], 2 * n)
    places, at = get_sorted(side)
    codes, _ = get_varints(side, len(places), at)
    x = np.array(decode_block(words[2 + n :], coder, n_readings, n_bits - 16 * (2 + n), mu, sigma, first), np.int64)
    null = np.zeros(len(x), bool)
    for p, c in zip(places, codes, strict=True):
        null[p] = c == 0
        x[p] = 0 if c == 0 else -(c // 2) if (c - 1) & 1 else (c - 1) // 2
    return np.ma.MaskedArray(x, null) if null.any() else x


def decode_block(words: np.ndarray, coder: str, n_readings: int, n_bits: int, mu: int, sigma: int, first: int) -> np.ndarray:
    """The readings; masked where they are null."""
    if coder.startswith(WIDE):
        return _decode_wide(words, coder.removeprefix(WIDE), n_readings, n_bits, mu, sigma, first)
    if coder == "identity":
        return np.asarray(words, np.int64)
    if not n_readings:
        return np.empty(0, np.int64)
    delta = coder.startswith("delta")
    n = n_readings - delta
    side = (PARAM_BITS if coder.endswith("gaussian_ac") else 0) + (FIRST_BITS if delta else 0)
    data = from_words(words, (n_bits - side) // 8)
    if coder.endswith("gaussian_ac"):
        body = gaussian_decode(data, mu, sigma, n)
    elif coder == "delta_varint":
        body = unzigzag(np.array(get_varints(data, n)[0], np.int64))
    else:
        (size,), at = get_varints(data, 1)
        body, _ = huffman_decode(data[at + size :], data[at : at + size])
    return np.concatenate([[first], first + np.cumsum(body)]).astype(np.int64) if delta else body

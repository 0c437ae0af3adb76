"""Worked examples, inverses and bounds of the block kernels."""

from fractions import Fraction

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from meterpack.kernels.arith import ac_decode, ac_encode, adaptive_decode, adaptive_encode, exact_interval, exact_message, gaussian_decode, gaussian_encode
from meterpack.kernels.bwt import bwt, bwt_inverse
from meterpack.kernels.codec import Config, decode_group, encode, stages
from meterpack.kernels.firststage import CODERS, decode_block, encode_block
from meterpack.kernels.group import lloyd, pad, seeds, silhouette
from meterpack.kernels.huffman import code_lengths, huffman_decode, huffman_encode
from meterpack.kernels.lz import lz77_decode, lz77_encode, lz78_decode, lz78_encode, lzw_decode, lzw_encode
from meterpack.kernels.mtf import mtf, mtf_inverse
from meterpack.kernels.rle import ideal_bits, rle_classes, rle_classes_inverse, rle_dynamic, rle_dynamic_inverse, rle_marked, rle_marked_inverse, rle_static, rle_static_inverse, rle_tokens, rle_tokens_inverse

BLOCKS = st.one_of(
    st.lists(st.integers(-3, 3), max_size=200),
    st.lists(st.integers(-70000, 70000), max_size=80),
    st.builds(lambda x, n: [x] * n, st.integers(0, 65535), st.integers(0, 300)),
    st.builds(lambda x, n: x * n, st.lists(st.integers(0, 5), min_size=1, max_size=4), st.integers(1, 40)),
)
FAST = settings(max_examples=80, deadline=None)


def same(a, b):
    assert np.array_equal(np.asarray(a), np.asarray(b))


def test_worked_examples():
    last, primary = bwt([309, 501, 309, 309, 501, 309])
    same(last, [501, 501, 309, 309, 309, 309])
    assert primary + 1 == 3
    a, b = 0, 1
    same(mtf([b, b, a, a, a, a, a, a], [a, b])[0], [1, 0, 1, 0, 0, 0, 0, 0])
    assert rle_marked([1, 0, 1, 0, 0, 0, 0, 0]) == [(1, None), (0, None), (1, None), (0, 5)]
    cuts = [Fraction(x, 10) for x in (0, 2, 5, 6, 8, 9, 10)]
    ranges = {s: (lo, hi) for s, lo, hi in zip("abcdef", cuts, cuts[1:], strict=False)}
    assert exact_interval("ba", ranges) == (Fraction(2, 10), Fraction(26, 100))
    low, high = exact_interval("baccf", ranges)
    assert (low, high, (low + high) / 2) == (Fraction(23354, 100000), Fraction(2336, 10000), Fraction(23357, 100000))
    assert exact_message((low + high) / 2, ranges, 5) == list("baccf")
    assert ideal_bits(np.array([7, 7, 7, 7])) == 0
    assert ideal_bits(np.arange(8)) == 24


def test_bwt_is_the_sorted_rotations():
    rng = np.random.default_rng(0)
    for _ in range(200):
        x = rng.integers(0, rng.integers(1, 6) + 1, rng.integers(1, 64))
        rows = sorted((tuple(np.roll(x, -i)), i) for i in range(len(x)))
        same(bwt(x)[0], [r[-1] for r, _ in rows])


@FAST
@given(BLOCKS)
def test_inverses(block):
    x = np.array(block, np.int64)
    for sentinel in (None, "low", "high"):
        same(bwt_inverse(*bwt(x, sentinel), sentinel), x)
    ranks, alphabet = mtf(x)
    same(mtf_inverse(ranks, alphabet), x)
    same(rle_static_inverse(*rle_static(x)), x)
    same(rle_marked_inverse(rle_marked(x)), x)
    same(rle_tokens_inverse(*rle_tokens(x)), x)
    for cost in ("bits", "entropy"):
        same(rle_dynamic_inverse(*rle_dynamic(ranks, cost=cost)), ranks)
    same(rle_classes_inverse(*rle_classes(ranks)), ranks)
    same(ac_decode(*ac_encode(x))[0], x)
    same(adaptive_decode(*adaptive_encode(x))[0], x)
    same(gaussian_decode(*gaussian_encode(x), len(x)), x)
    same(huffman_decode(*huffman_encode(x)[:2])[0], x)
    same(lz77_decode(lz77_encode(abs(x))), abs(x))
    same(lz78_decode(lz78_encode(abs(x))), abs(x))
    data = (x % 256).astype(np.uint8).tobytes()
    assert lzw_decode(lzw_encode(data)) == data


@FAST
@given(BLOCKS)
def test_invariants(block):
    x = np.array(block, np.int64)
    if not len(x):
        return
    last, _ = bwt(x)
    assert ideal_bits(last) == pytest.approx(ideal_bits(x))
    ranks, alphabet = mtf(x)
    assert (ranks == 0).sum() == (x[1:] == x[:-1]).sum() + (x[0] == alphabet[0])
    assert rle_static(x)[1].sum() == len(x)
    payload = 8 * len(ac_encode(x)[0])
    assert payload <= ideal_bits(x) + 34 + len(x) / 2048
    assert payload >= ideal_bits(x) - 1
    if len(alphabet) > 1:
        bits = huffman_encode(x)[2]
        assert ideal_bits(x) - 1e-6 <= bits < ideal_bits(x) + len(x)
        counts = np.unique(x, return_counts=True)[1].tolist()
        assert sum(Fraction(1, 2**n) for n in code_lengths(counts)) == 1


def test_large_alphabets_agree_with_the_list():
    rng = np.random.default_rng(3)
    x = rng.integers(0, 2000, 5000)
    table, naive = np.unique(x).tolist(), []
    for s in x.tolist():
        naive.append(table.index(s))
        table.insert(0, table.pop(naive[-1]))
    same(mtf(x)[0], naive)
    same(mtf_inverse(*mtf(x)), x)


def test_dictionary_restart():
    data = np.random.default_rng(1).integers(0, 256, 300_000).astype(np.uint8).tobytes()
    assert lzw_decode(lzw_encode(data)) == data


CONFIGS = [Config(), Config(rle="static"), Config(rle="token", layout="concat", delta_order=2), Config(rle="rank_class", delta_scope="stream", bwt="low"), Config(coder="adaptive", rle="entropy"), Config(coder="huffman", bwt=None), Config(coder="gaussian", mtf=False, rle=None), Config(bwt="high", delta_order=0)]


@pytest.mark.parametrize("cfg", CONFIGS, ids=str)
def test_groups_round_trip(cfg):
    rng = np.random.default_rng(5)
    for streams in ([], [np.empty(0, np.int64)], [np.array([5])], [np.array([1, 2, 3]), np.array([10]), np.array([20, 21])], [rng.integers(0, 65536, n) for n in (40, 7, 0, 90)], [np.zeros(300, np.int64)] * 3):
        row = encode(streams, cfg)
        back = decode_group(row, [len(s) for s in streams], cfg)
        for a, b in zip(streams, back, strict=True):
            same(a, b)


def test_ragged_interleave_and_signed_difference():
    same(stages([np.array([1, 2, 3]), np.array([10]), np.array([20, 21])], Config())["interleaved"], [1, 10, 20, 2, 21, 3])
    s = stages([np.array([5, 5, 2, 65535, 0])], Config())
    assert s["firsts"] == [5]
    same(s["delta"], [0, -3, 65533, -65535])


@pytest.mark.parametrize("coder", CODERS)
def test_first_stage(coder):
    rng = np.random.default_rng(2)
    for x in ([], [7], [0] * 1440, rng.integers(0, 65536, 300), np.where(rng.random(1441) < 0.95, 0, 60000)):
        bits, mu, sigma, first, words = encode_block(np.array(x, np.int64), coder)
        assert ((words >= 0) & (words < 65536)).all()
        same(decode_block(words, coder, len(x), bits, mu, sigma, first), np.array(x, np.int64))


def test_kmeans():
    rng = np.random.default_rng(4)
    x = np.concatenate([rng.normal(c, 1, (20, 3)) for c in (0, 50, 100)]).round()
    ids = np.arange(60)
    for init, scope in (("kmeans++", "global"), ("kmeans++", "region"), ("uniform", "global")):
        chosen = seeds(x, ids, 3, 42, init=init, scope=scope)
        assert len(set(chosen)) == 3
        labels, centers, trace, done = lloyd(x, x[chosen])
        assert done and all(a >= b - 1e-6 for a, b in zip(trace, trace[1:], strict=False))
    best, *_ = lloyd(x, x[seeds(x, ids, 3, 42)])
    assert silhouette(x, best).mean() > silhouette(x, rng.integers(0, 3, 60)).mean()
    assert np.isnan(silhouette(x, np.zeros(60, int))).all()
    same(seeds(np.zeros((4, 2)), np.arange(4), 4, 1), seeds(np.zeros((4, 2)), np.arange(4), 4, 1))
    assert pad([np.arange(3), np.arange(5)], "pad").shape == (2, 5)
    assert pad([np.arange(3), np.arange(5)], "truncate").shape == (2, 3)
    assert pad([np.arange(9), np.arange(5)], "resample", 3).shape == (2, 3)
    assert pad([np.arange(9), np.arange(5)], "histogram", 4).sum() == 14


def test_ranks_of_large_alphabets(monkeypatch):
    """Ranks counted by bits are those of a list, in any order of the alphabet."""
    from meterpack.kernels import mtf as kernel

    monkeypatch.setattr(kernel, "LARGE", 0)
    rng = np.random.default_rng(8)
    assert kernel.larger_before(np.array([5, 1, 9, -3, 2])).tolist() == [0, 1, 0, 3, 2]
    for n, size in ((1, 1), (2, 9), (700, 3), (900, 800), (1024, 64)):
        x = rng.integers(0, size, n) * 5 - 9
        for alphabet in (np.unique(x), rng.permutation(np.arange(size) * 5 - 9)):
            ranks, _ = kernel.mtf(x, alphabet)
            line, want = alphabet.tolist(), []
            for s in x.tolist():
                want.append(line.index(s))
                line.insert(0, line.pop(want[-1]))
            assert ranks.tolist() == want and kernel.mtf_inverse(ranks, alphabet).tolist() == x.tolist()


def test_configurations_share_a_group():
    """Run lengths packed side by side give the rows of each alone."""
    from meterpack.kernels.codec import Config
    from meterpack.plans.recompress import pack_batch

    rng = np.random.default_rng(4)
    rows = [{"stream_id": i, "block_no": 0, "coder": "identity", "n_readings": 90, "n_bits": 1440, "mu": 0, "sigma": 0, "first": 0, "words": rng.integers(0, 900, 90)} for i in range(8)]
    cfgs = [Config(k=3, rle=r) for r in ("static", "dynamic", "token")]
    both = pack_batch(1, 0, rows, *cfgs)
    assert sorted(map(str, both)) == sorted(str(r) for c in cfgs for r in pack_batch(1, 0, rows, c))
    with pytest.raises(ValueError):
        pack_batch(1, 0, rows, Config(k=2), Config(k=3))


def test_coding_in_step_is_coding_one_by_one():
    """Many blocks at once give the bytes that each gives alone, also where they differ in length and have escaped symbols."""
    from meterpack.kernels import arith

    rng = np.random.default_rng(3)
    blocks = [rng.integers(0, top, n) for n in (0, 1, 2, 40, 511, 512, 513, 1500) for top in (1, 2, 300, 70000)]
    blocks += [np.where(rng.random(1440) < 0.05, rng.integers(0, 60000, 1440), 0) for _ in range(20)] + [np.array([0] * 900 + [9**9, -(9**9)])]
    assert arith.ac_encode_many(blocks) == [ac_encode(x) for x in blocks]
    assert arith.gaussian_encode_many(blocks) == [gaussian_encode(x) for x in blocks]
    for x, (payload, model) in zip(blocks, arith.ac_encode_many(blocks), strict=True):
        same(ac_decode(payload, model)[0], x)


def test_larger_before_and_rotations_of_long_blocks():
    from meterpack.kernels.bwt import rotation_order
    from meterpack.kernels.mtf import larger_before

    rng = np.random.default_rng(4)
    for n in (1, 2, 3, 255, 256, 257, 1000):
        x = rng.permutation(n)
        same(larger_before(x), [(x[:i] > v).sum() for i, v in enumerate(x)])
    x = rng.permutation((1 << 18) + 999)
    found = larger_before(x)
    for i in (1, 5000, 1 << 17, 1 << 18, len(x) - 1):
        assert found[i] == (x[:i] > x[i]).sum()
    for x in (np.tile([3, 1, 2], 7), np.zeros(9, np.int64), rng.integers(0, 2, 300)):
        same(rotation_order(x), sorted(range(len(x)), key=lambda i: (np.roll(x, -i).tolist(), i)))


def test_lloyd_with_kept_sums_is_lloyd():
    rng = np.random.default_rng(5)
    x = rng.integers(0, 65536, (300, 20)).astype(float)
    labels, centers, _, _ = lloyd(x, x[seeds(x, np.arange(300), 6, 42)])
    same(centers, np.stack([x[labels == c].mean(0) for c in range(6)]))


def test_grid_blocks_are_the_blocks_of_the_grid(spark, sf):
    from meterpack.sources import carriers as C

    for length in (256, 1440, 1000):
        row = lambda r: (r.stream_id, r.block_no, r.n_readings, tuple(r.readings))
        assert sorted(map(row, C.grid_blocks(spark, sf, length).collect())) == sorted(map(row, C.blocks(C.meter_grid(spark, sf), length).collect()))


def test_batches_packed_together_are_batches_packed_alone():
    from meterpack.plans.recompress import pack_batch, pack_batches

    rng = np.random.default_rng(6)
    row = lambda i: {"stream_id": i, "coder": "identity", "n_readings": 30, "n_bits": 480, "mu": 0, "sigma": 0, "first": 0, "words": rng.integers(0, 9, 30).astype(np.int32)}
    cfgs = tuple(Config(k=2, rle=rle) for rle in ("static", "dynamic"))
    batches = [(b, 0, [row(8 * b + i) for i in range(8)], cfgs) for b in range(20)]
    assert list(pack_batches(batches)) == [r for b, w, rows, c in batches for r in pack_batch(b, w, rows, *c)]

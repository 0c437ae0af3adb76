"""Re-compression is lossless on readings beyond 16 bits, nulls, and times outside the first thirty days."""

import collections
import datetime

import numpy as np
import pytest

from meterpack.kernels.codec import Config
from meterpack.kernels.firststage import CODERS, coder_for, decode_block, encode_block
from meterpack.plans.experiments import streams_of
from meterpack.plans.recompress import batch_by_rank, recompress, recover_readings
from meterpack.sources import carriers as C

START = datetime.datetime(2024, 1, 1)


@pytest.fixture(scope="module")
def skewed(spark, tmp_path_factory):
    """Meter 1 has sums above 65,535; meter 2 a null, a negative and a huge reading; meters 3 and 4 lie outside 30 days."""
    at = lambda slot: START + datetime.timedelta(minutes=30 * slot + 7)
    rows = [(1, at(i), 400.0) for i in range(200) for _ in range(3)] + [(2, at(i), x) for i, x in enumerate([5.0, None, 7.0, -3.0, 1e12, 9.0])]
    rows += [(3, at(1440 * 2 + 5), 11.0), (4, at(-3), 12.0), (1, at(1440), 13.0)]
    path = tmp_path_factory.mktemp("skewed")
    events = spark.createDataFrame([(i, *r) for i, r in enumerate(rows)], "event_id bigint, user_id bigint, ts timestamp_ntz, value double")
    events.write.parquet(f"{path}/events.parquet")
    return f"{path}", rows


def recovered(spark, path, name, coder, block):
    packed = recompress(batch_by_rank(streams_of(spark, path, name, coder)), Config(k=1))
    return {(r.stream_id, r.pos): r.sym for r in recover_readings(packed, block).collect()}


@pytest.mark.parametrize("coder", ["identity", "delta_gaussian_ac"])
def test_grid_keeps_all_readings(spark, skewed, coder):
    path, rows = skewed
    sums = collections.Counter()
    for user, ts, value in rows:
        sums[user, (ts - START) // datetime.timedelta(minutes=30)] += round(100 * (value or 0))
    back = recovered(spark, path, "meter_grid", coder, C.SLOTS)
    assert back == {(u, p): sums[u, p] for u in (1, 2, 3, 4) for p in range(-1440, 3 * 1440)}


def test_values_keep_nulls_and_places(spark, skewed):
    path, rows = skewed
    back = recovered(spark, path, "meter_value", "gaussian_ac", C.BLOCK)
    assert [back[2, i] for i in range(6)] == [500, None, 700, -300, 100_000_000_000_000, 900]
    assert len(back) == len(rows)


@pytest.mark.parametrize("coder", CODERS)
def test_wide_blocks(coder):
    ends = np.iinfo(np.int64)
    for x in (np.array([65536, 0, -1, ends.max, ends.min, 65535]), np.ma.MaskedArray([1, 2, 70000], [False, True, False]), np.ma.MaskedArray([0], [True])):
        own = coder_for(x, coder)
        bits, mu, sigma, first, words = encode_block(x, own)
        assert 0 <= words.min() and words.max() <= 65535
        back = decode_block(words, own, len(x), bits, mu, sigma, first)
        assert np.ma.asarray(back).tolist() == np.ma.asarray(x).tolist()

"""Seeding by draws over ranges of ids, against one pass over all of them."""

import hashlib

import pytest

from meterpack.operators import cluster


def number(text):
    return int(hashlib.md5(text.encode()).hexdigest()[:12], 16)


def plain_seeds(vectors, k, seed):
    chosen = [min(vectors, key=lambda i: hashlib.md5(f"{i}:{seed}:0".encode()).hexdigest())]
    for r in range(1, k):
        w = {i: min(sum((a - b) ** 2 for a, b in zip(v, vectors[c])) for c in chosen) for i, v in sorted(vectors.items())}
        if not sum(w.values()):
            break
        at = number(f"0:{seed}:{r}") % sum(w.values())
        for i, own in w.items():
            if at < own:
                break
            at -= own
        chosen.append(i)
    return chosen


@pytest.mark.parametrize("equal", [False, True])
def test_seeds_over_ranges(spark, equal):
    vectors = {i: [5, 5] if equal else [number(f"{i}:{j}") % 1000 for j in range(3)] for i in range(60)}
    df = spark.createDataFrame(sorted(vectors.items()), "stream_id bigint, vec array<bigint>")
    before = spark.conf.get("spark.sql.adaptive.enabled")
    spark.conf.set("spark.sql.adaptive.enabled", "false")  # keeps the ranges apart
    try:
        found = [r.stream_id for r in cluster.seed_rows(df, 4, 7).orderBy("cluster_id").collect()]
    finally:
        spark.conf.set("spark.sql.adaptive.enabled", before)
    assert found == plain_seeds(vectors, 4, 7)


def test_silhouette_in_blocks(spark, monkeypatch):
    """Blocks of vectors give what all pairs give, for two labellings at once; numbers whose squares leave a double are exact; a
    member alone has 0, one group null, one vector no row."""
    import numpy as np

    from meterpack.kernels import group
    from meterpack.operators import measures

    monkeypatch.setattr(measures, "BLOCK_ROWS", 7)
    rng = np.random.default_rng(3)
    x = rng.integers(-40, 40, (45, 9))
    labels = np.stack([rng.integers(0, 4, 45), np.arange(45) % 2 * 3, np.zeros(45, int)], 1)
    labels[0, 0] = 9
    rows = [(i, v.tolist(), *map(int, c)) for i, (v, c) in enumerate(zip(x, labels, strict=True))]
    vectors = spark.createDataFrame(rows, "stream_id bigint, vec array<bigint>, a int, b int, c int").repartition(5)
    found = {(r.labelling, r.stream_id): r for r in measures.silhouette(vectors, "a", "b", "c").collect()}
    assert len(found) == 3 * 45
    for j, name in enumerate("ab"):
        want = group.silhouette(x.astype(float), labels[:, j])
        for i in range(45):
            r = found[name, i]
            assert r.cluster_id == labels[i, j] and abs(r.s - want[i]) < 2e-6 and abs(r.s - r.s_piecewise) < 2e-6
    assert found["a", 0].s == 0 and all(found["c", i].s is None for i in range(45))
    assert measures.silhouette(vectors.where("stream_id = 1"), "a").count() == 0
    assert measures.silhouette(vectors.where("stream_id < 0"), "a").count() == 0
    far = np.array([[1 << 30, 0], [(1 << 30) + 3, 4]])
    assert measures.distances(far, far).tolist() == [[0, 5], [5, 0]]

"""k-means over the streams of one batch: seeding by squared distance, Lloyd's loop, random grouping."""

from __future__ import annotations

import hashlib

import numpy as np


def draw(batch: object, seed: int, r: int, below: int) -> int:
    return int(hashlib.md5(f"{batch}:{seed}:{r}".encode()).hexdigest()[:12], 16) % below


def random_cluster(stream_id: int, k: int, seed: int) -> int:
    return int(hashlib.md5(f"{stream_id}:{seed}".encode()).hexdigest()[:8], 16) % k


def pad(blocks: list[np.ndarray], mode: str = "pad", d: int | None = None) -> np.ndarray:
    """Vectors of one length: "pad" with zeros, "truncate", "resample" to d bin means, "histogram" of d value bins."""
    lengths = [len(b) for b in blocks]
    if mode == "histogram":
        d, top = d or 64, max((int(b.max()) for b in blocks if len(b)), default=0) + 1
        return np.stack([np.bincount(np.minimum(b * d // top, d - 1), minlength=d) for b in blocks]).astype(np.float64)
    if mode == "resample":
        d = d or min(lengths)
        cut = [np.linspace(0, n, d + 1).astype(int) for n in lengths]
        return np.stack([[b[a:z].mean() if z > a else 0.0 for a, z in zip(c, c[1:], strict=False)] for b, c in zip(blocks, cut, strict=True)])
    d = d or (min(lengths) if mode == "truncate" else max(lengths, default=0))
    out = np.zeros((len(blocks), d))
    for row, b in zip(out, blocks, strict=True):
        row[: min(d, len(b))] = b[:d]
    return out


def squares(x: np.ndarray) -> np.ndarray:
    """Sum of squares of each row, some rows at a time."""
    return np.concatenate([(x[a : a + 1024] ** 2).sum(1) for a in range(0, len(x), 1024)]) if len(x) else np.zeros(0)


def dist2(x: np.ndarray, centers: np.ndarray, of_x: np.ndarray | None = None) -> np.ndarray:
    """of_x: squares(x), where they are known."""
    return np.maximum((squares(x) if of_x is None else of_x)[:, None] - x @ (2 * centers).T + (centers**2).sum(1)[None], 0.0)


def seeds(x: np.ndarray, ids: np.ndarray, k: int, seed: int, batch: object = 0, scope: str = "global", init: str = "kmeans++") -> list[int]:
    """Rows of the first centres; ids ascend. The first has the least md5 of id and seed; each next one is drawn with
    weights by squared distance to the nearest so far, over all rows or over the region of the largest weight."""
    order = sorted(range(len(ids)), key=lambda i: hashlib.md5(f"{ids[i]}:{seed}:0".encode()).hexdigest())
    if init == "uniform":
        return order[:k]
    chosen, own = [order[0]], squares(x)
    while len(chosen) < k:
        all_d = np.rint(dist2(x, x[chosen], own)).astype(np.int64)
        near, w = all_d.argmin(1), all_d.min(1)
        w[chosen] = 0
        if scope == "region":
            w = np.where(near == np.bincount(near, w, len(chosen)).argmax(), w, 0)
        total = int(w.sum())
        if total:
            chosen.append(int(np.searchsorted(np.cumsum(w), draw(batch, seed, len(chosen), total), "right")))
        else:
            chosen.append(min(set(range(len(ids))) - set(chosen)))
    return chosen


def _exact(x: np.ndarray) -> bool:
    """Whether all sums of rows are integers that a double holds."""
    return bool(x.size) and all((np.rint(x[a : a + 1024]) == x[a : a + 1024]).all() for a in range(0, len(x), 1024)) and max(float(x.max()), -float(x.min())) * len(x) < 2.0**53


def lloyd(x: np.ndarray, start: np.ndarray, max_iter: int = 50) -> tuple[np.ndarray, np.ndarray, list[float], bool]:
    """(labels, centres, within-cluster squares of each round, converged). Ties go to the first centre; an empty cluster
    keeps its centre."""
    centers, labels, trace = start.astype(np.float64).copy(), None, []
    own, exact = squares(x), _exact(x)
    sums, sizes = np.zeros_like(centers), np.zeros(len(centers), np.int64)
    for _ in range(max_iter):
        d = dist2(x, centers, own)
        new = d.argmin(1)
        trace.append(float(d.min(1).sum()))
        if labels is not None and (new == labels).all():
            return labels, centers, trace, True
        if exact:  # sums of integers come out the same in any order, so only rows that moved are added and taken away
            moved = np.flatnonzero(labels != new) if labels is not None else np.arange(len(x))
            for rows in np.array_split(moved, -(-len(moved) // 1024)):
                kinds = np.arange(len(centers))[:, None]
                change = (new[rows] == kinds).astype(np.float64)
                if labels is not None:
                    change -= labels[rows] == kinds
                sums += change @ x[rows]
            labels, sizes = new, np.bincount(new, minlength=len(centers))
            some = sizes > 0
            centers[some] = sums[some] / sizes[some, None]
            continue
        labels = new
        for c in range(len(centers)):
            if (labels == c).any():
                centers[c] = x[labels == c].mean(0)
    return labels, centers, trace, False


def silhouette(x: np.ndarray, labels: np.ndarray) -> np.ndarray:
    """s of every row by plain Euclidean distance; 0 for rows alone in their group, NaN where there is one group."""
    kinds = np.unique(labels)
    if len(kinds) < 2:
        return np.full(len(x), np.nan)
    d = np.sqrt(dist2(x, x))
    np.fill_diagonal(d, 0.0)
    sums = np.stack([d[:, labels == c].sum(1) for c in kinds], 1)
    sizes = np.array([(labels == c).sum() for c in kinds])
    own = labels[:, None] == kinds[None]
    a = (sums * own).sum(1) / np.maximum(own @ sizes - 1, 1)
    b = np.where(own, np.inf, sums / sizes).min(1)
    top = np.maximum(a, b)
    return np.where((own @ sizes > 1) & (top > 0), (b - a) / np.where(top > 0, top, 1), 0.0)

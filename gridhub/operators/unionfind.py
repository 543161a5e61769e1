"""Components of a graph that fits one task, in numpy."""

from __future__ import annotations

import numpy as np

from gridhub.config import Neighborhood


def label_components(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Least member index of each node's component."""
    return join_labels(np.arange(n), a, b)


def join_labels(label: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Adds edges to flat labels, in place; labels stay flat and least."""
    while len(a):
        x, y = label[a], label[b]
        apart = x != y
        if not apart.any():
            break
        a, b, x, y = a[apart], b[apart], x[apart], y[apart]
        np.minimum.at(label, np.maximum(x, y), np.minimum(x, y))
        while True:
            up = label[label]
            if (up == label).all():
                break
            label[:] = up
    return label


def tile_components(tiles: np.ndarray, near: Neighborhood) -> np.ndarray:
    """Index of the lexicographically least tile of each tile's cluster.

    ``tiles`` is an integer array, one row per tile, in lexicographic order and unique.
    """
    n, dim = tiles.shape
    if not n:
        return np.zeros(0, np.int64)
    low = tiles.min(0)
    span = [int(x) + 2 * near.reach + 1 for x in tiles.max(0) - low]
    size = 1
    for s in span:
        size *= s
    dtype = np.int64 if size < 2**62 else object
    steps = [1] * dim
    for i in range(dim - 2, -1, -1):
        steps[i] = steps[i + 1] * span[i + 1]
    code = sum(((tiles[:, i] - low[i]).astype(dtype) + near.reach) * steps[i] for i in range(dim))
    found_a, found_b = [], []
    for offset in near.half_offsets(dim):
        wanted = code + sum(x * s for x, s in zip(offset, steps))
        at = np.minimum(np.searchsorted(code, wanted), n - 1)
        hit = np.flatnonzero(code[at] == wanted)
        found_a.append(hit)
        found_b.append(at[hit])
    return label_components(n, np.concatenate(found_a), np.concatenate(found_b))

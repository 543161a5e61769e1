"""Properties over random small grids, in numpy so that many cases are cheap."""

import numpy as np
from hypothesis import given, settings
from hypothesis import strategies as st

from gridhub.config import METRICS, Neighborhood
from gridhub.functions.shape import enclosing_ellipse
from gridhub.operators.unionfind import label_components, tile_components

cells = st.sets(st.tuples(st.integers(-6, 6), st.integers(-6, 6)), max_size=40)
nears = st.builds(Neighborhood, st.sampled_from(["chebyshev", "manhattan"]), st.integers(1, 3))


def clusters(found, near):
    arr = np.array(sorted(found), np.int64).reshape(-1, 2)
    root = tile_components(arr, near)
    out = {}
    for t, r in zip(arr.tolist(), root):
        out.setdefault(tuple(arr[r]), set()).add(tuple(t))
    return out


@settings(max_examples=60, deadline=None)
@given(cells, nears)
def test_clusters_are_far_apart_and_connected(found, near):
    got = clusters(found, near)
    assert sorted(t for g in got.values() for t in g) == sorted(found)
    dist = METRICS[near.metric]
    groups = list(got.values())
    for i, a in enumerate(groups):
        assert min(a) in got
        for b in groups[i + 1 :]:
            assert min(dist((x[0] - y[0], x[1] - y[1])) for x in a for y in b) > near.delta
        seen, todo = {min(a)}, [min(a)]
        while todo:
            t = todo.pop()
            for u in a - seen:
                if dist((t[0] - u[0], t[1] - u[1])) <= near.delta:
                    seen.add(u)
                    todo.append(u)
        assert seen == a


@settings(max_examples=40, deadline=None)
@given(cells, st.integers(-1000, 1000), st.integers(-1000, 1000), nears)
def test_shift_and_larger_delta(found, dx, dy, near):
    moved = {(x + dx, y + dy) for x, y in found}
    assert {frozenset((x + dx, y + dy) for x, y in g) for g in clusters(found, near).values()} == {frozenset(g) for g in clusters(moved, near).values()}
    wider = Neighborhood(near.metric, near.delta + 1)
    coarse = list(clusters(found, wider).values())
    assert all(any(g <= c for c in coarse) for g in clusters(found, near).values())


@settings(max_examples=40, deadline=None)
@given(st.integers(1, 30), st.lists(st.tuples(st.integers(0, 29), st.integers(0, 29)), max_size=60))
def test_union_find(n, pairs):
    pairs = [(a % n, b % n) for a, b in pairs]
    want = list(range(n))
    for _ in range(n):
        for a, b in pairs:
            want[a] = want[b] = min(want[a], want[b])
    a, b = (np.array(x, np.int64) for x in (zip(*pairs) if pairs else ((), ())))
    assert label_components(n, a, b).tolist() == want


def test_ellipse_encloses_and_is_tight():
    rng = np.random.default_rng(0)
    pts = rng.normal(size=(200, 2)) @ np.array([[3.0, 0.0], [1.0, 0.5]])
    centre, major, minor, angle = enclosing_ellipse(pts, 1e-5)
    turn = np.array([[np.cos(angle), np.sin(angle)], [-np.sin(angle), np.cos(angle)]])
    z = (pts - centre) @ turn.T
    r = (z[:, 0] / major) ** 2 + (z[:, 1] / minor) ** 2
    assert r.max() <= 1.001 and (r > 0.99).sum() >= 3

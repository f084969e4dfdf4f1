"""Blocks of cells and points are asked together, with the results of one after the other."""

import numpy as np
import pytest

from densegrid.functions.geometry import safe_reach
from densegrid.operators import indexes, tiles
from densegrid.operators.forest import merge_cells
from densegrid.params import ClusterParams
from densegrid.plans import engine
from tests.test_engine import brute, found, points_of

R = np.random.default_rng(21)


def spots(n, d, span):
    return np.unique(R.integers(0, span, (n, d)), axis=0)


@pytest.mark.parametrize("far", [0, 100_000])
def test_scanned_cells_by_blocks(far, monkeypatch):
    cells = spots(400, 8, 7)
    cells[len(cells) // 2 :, 1] += far
    cells = cells[np.lexsort(cells.T[::-1])]
    gaps = np.maximum(np.abs(cells[:, None] - cells[None]) - 1, 0)
    near = ((gaps**2).sum(axis=2) <= 8) & ~np.eye(len(cells), dtype=bool)
    calls, real = [], indexes.OffsetIndex._met
    monkeypatch.setattr(indexes.OffsetIndex, "_met", lambda self, several: calls.append(len(several)) or real(self, several))
    index = indexes.OffsetIndex(cells, max_offsets=10)
    for i in range(len(cells)):
        assert index.candidates(i).tolist() == np.flatnonzero(near[i]).tolist()
    assert len(calls) <= -(-len(cells) // index.BLOCK)
    some = np.array([3, 9, 200])
    assert index.union(some).tolist() == np.union1d(np.flatnonzero(near[some].any(axis=0)), some).tolist()


def test_kd_union_is_one_search(monkeypatch):
    cells = spots(500, 6, 12)
    index = indexes.KdIndex(cells)
    within = (np.abs(cells[:, None] - cells[None]) <= safe_reach(6)).all(axis=2)
    some = np.array([5, 6, 7, 300])
    assert set(np.flatnonzero(within[some].any(axis=0))) <= set(index.union(some).tolist())
    for i in some.tolist():
        assert index.candidates(i).tolist() == [j for j in np.flatnonzero(within[i]).tolist() if j != i]
    monkeypatch.setattr(index, "candidates", None)
    assert set(some) <= set(index.union(some).tolist())


def test_rectangles_are_asked_by_blocks():
    x = R.integers(0, 300, (700, 3))
    tree = indexes.RectangleTree(x)
    rows = set(tree.near(x[:40], 400).tolist())
    dd = ((x[:40, None] - x[None]) ** 2).sum(axis=2)
    assert set(np.flatnonzero((dd <= 400).any(axis=0)).tolist()) <= rows and len(rows) <= len(x)


@pytest.mark.parametrize("method", ["grid_full", "slab_full", "reference"])
@pytest.mark.parametrize("d", [2, 8])
def test_full_checks_by_blocks(spark, monkeypatch, method, d):
    x = np.concatenate([R.integers(0, 60, (150, d)), R.integers(0, 400, (60, d))])
    made = []
    real = tiles.merge_test

    def spy(tile, core):
        check = real(tile, core)
        one = lambda a, b: made.append((a, b)) or check(a, b)
        one.among = check.among
        return one

    monkeypatch.setattr(tiles, "merge_test", spy)
    eps = 12 if d == 2 else 45
    assert found(engine.cluster(points_of(spark, x), ClusterParams(eps, 4, method=method, tile_points=80))) == brute(x, eps, 4)
    assert not made


def test_checks_of_a_cell_at_once_count_alike():
    links = {(0, 1), (0, 3), (1, 2), (2, 3)}
    near = lambda g: np.array([h for h in range(5) if h != g])
    check = lambda g, h: (min(g, h), max(g, h)) in links
    one = merge_cells(range(5), near, check, 5, pruned=False)[1]
    all_ = merge_cells(range(5), near, None, 5, pruned=False, among=lambda g, near: np.array([check(g, h) for h in near.tolist()], bool))[1]
    assert one == all_ and one.checks == 10

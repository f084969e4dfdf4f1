"""Points are asked by blocks that are near in all dimensions; halos and long lists of cuts stay cheap."""

import numpy as np
import pyarrow as pa
import pytest

from densegrid.functions.geometry import cell_scale
from densegrid.operators import tiles
from densegrid.operators.tiles import TilePlan, deal, label_tile, merge_tile
from densegrid.params import ClusterParams
from tests.test_engine import points_of

R = np.random.default_rng(33)


@pytest.mark.parametrize("method", ["grid_full", "slab_full", "kdtree_pruned"])
def test_few_distances_where_points_are_sparse(monkeypatch, method):
    x, eps, min_pts = R.integers(0, 1000, (6000, 7)), 200, 4
    own = x[:, 6] < 700
    made, real = [], tiles.within
    monkeypatch.setattr(tiles, "within", lambda tile, a, b: made.append(len(a) * len(b)) or real(tile, a, b))
    rows = pa.table({"id": pa.array(range(len(x)), pa.int64()), "coord": pa.array(x.tolist(), pa.list_(pa.int64())), "own": pa.array(own)})
    prm = ClusterParams(eps, min_pts, method=method)
    flagged = pa.Table.from_batches(list(label_tile(rows, prm, 7, True)))
    got = np.zeros(len(x), bool)
    got[flagged.column("id").to_numpy()] = flagged.column("core").to_numpy(zero_copy_only=False)
    near = np.array([((x - p) ** 2).sum(axis=1) <= eps * eps for p in x])
    core = near.sum(axis=1) >= min_pts
    assert (got == core & own).all() and core.any() and not core.all()
    assert sum(made) < own.sum() * len(x) / 4
    found = pa.Table.from_batches(list(merge_tile(rows.append_column("core", pa.array(core)), prm, 7, True))).to_pylist()
    name = np.array([np.where(core)[0].min()] * len(x))
    scaled = np.floor(x * cell_scale(7, eps)).astype(int)
    for i in np.flatnonzero(core):
        name[i] = np.flatnonzero(core & (scaled == scaled[i]).all(axis=1)).min()
    want = {}
    for i in np.flatnonzero(own & ~core):
        for j in np.flatnonzero(near[i] & core):
            d2 = int(((x[i] - x[j]) ** 2).sum())
            want[i, name[j]] = min(d2, want.get((i, name[j]), d2))
    assert {(r["a"], r["b"]): int(r["v"]) for r in found if r["kind"] == "touch"} == want


def test_long_lists_of_cuts_and_halos_of_core_points(spark):
    x = R.integers(0, 5000, (300, 2))
    plan = TilePlan(((0, tuple(range(7, 500, 9))), (1, (100, 200))), 165, 300, 300)
    frame = points_of(spark, x).frame.selectExpr("id", "coord", "id % 3 = 0 AS core")
    dealt = deal(frame, plan, 2, 14.142135623730951, 2)
    text = dealt._jdf.queryExecution().optimizedPlan().toString()
    assert text.count("<=") < 40  # one comparison a cut made code that was never compiled
    cells, want = np.floor(x * cell_scale(2, 14.142135623730951)).astype(int), set()
    for i, c in enumerate(cells):
        slots = [[int(np.searchsorted(edges, c[k] + s, "right")) for s in (-2, 0, 2)] for k, edges in plan.cuts]
        for a in range(slots[0][0], slots[0][2] + 1):
            for b in range(slots[1][0], slots[1][2] + 1):
                own = (a, b) == (slots[0][1], slots[1][1])
                if own or i % 3 == 0:
                    want.add((i, a * 3 + b, own))
    assert {(r["id"], r["tile"], r["own"]) for r in dealt.collect()} == want


@pytest.mark.parametrize("rho", [0.02, 0.4])
def test_approximate_checks_by_blocks(monkeypatch, rho):
    """Cells of few points are not checked pair by pair; the links join what one pair after the other joins."""
    x = np.concatenate([R.integers(0, 400, (500, 8)), np.repeat(R.integers(0, 400, (20, 8)), 3, axis=0) + R.integers(0, 9, (60, 8))])
    prm, core = ClusterParams(140, 2, method="grid_approx", rho=rho), R.random(len(x)) < 0.9
    rows = pa.table({"id": pa.array(range(len(x)), pa.int64()), "coord": pa.array(x.tolist(), pa.list_(pa.int64())), "own": pa.array([True] * len(x)), "core": pa.array(core)})
    made, real = [], tiles.merge_test

    def spy(tile, core):
        check = real(tile, core)
        one = lambda a, b: made.append((a, b)) or check(a, b)
        one.among = check.among
        return one

    def trees():
        root = list(range(len(x)))
        for r in pa.Table.from_batches(list(merge_tile(rows, prm, 8, True))).to_pylist():
            if r["kind"] == "link":
                a, b = root[r["a"]], root[r["b"]]
                root = [min(a, b) if c in (a, b) else c for c in root]
        return root

    monkeypatch.setattr(tiles, "merge_test", spy)
    got = trees()
    assert not made and 1 < len({got[i] for i in np.flatnonzero(core)})
    monkeypatch.setattr(tiles.ProductMeeting, "FEW", 0)
    assert trees() == got and made

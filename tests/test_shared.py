"""Tiles shared by tasks, and cells checked by one product of their core points: the same results."""

import numpy as np
import pyarrow as pa
import pytest

from densegrid.operators import indexes, relational, tiles
from densegrid.operators.forest import Forest
from densegrid.params import ClusterParams
from densegrid.plans import engine
from tests.test_engine import brute, found, points_of

R = np.random.default_rng(33)


@pytest.mark.parametrize("method", ["slab_pruned", "slab_full", "grid_full", "kdtree_pruned", "reference"])
def test_wide_tile_is_shared(spark, monkeypatch, method):
    x = np.concatenate([R.integers(0, 60, (150, 8)), R.integers(0, 400, (60, 8)), R.integers(300, 360, (90, 8))])
    shared, real = [], tiles.share_wide
    monkeypatch.setattr(engine, "WIDE", 100)
    monkeypatch.setattr(engine, "share_wide", lambda dealt, wide, *a: shared.append(wide) or real(dealt, wide, *a))
    assert found(engine.cluster(points_of(spark, x), ClusterParams(45, 4, method=method))) == brute(x, 45, 4)
    assert len(shared) == 2 and max(shared[0].values()) > 1


@pytest.mark.parametrize("method", ["slab_pruned", "slab_full", "grid_full", "kdtree_pruned"])
@pytest.mark.parametrize("visit", ["once", "both"])
def test_few_points_a_cell_meet_by_products(monkeypatch, method, visit):
    x = np.concatenate([R.integers(0, 60, (150, 8)), R.integers(0, 400, (60, 8)), np.repeat(R.integers(0, 60, (9, 8)), 4, axis=0)])
    asked, real = [], tiles.ProductMeeting._ask
    monkeypatch.setattr(tiles.ProductMeeting, "_ask", lambda self, *a: asked.append(1) or real(self, *a))
    core = (((x[:, None] - x[None]) ** 2).sum(axis=2) <= 45 * 45).sum(axis=1) >= 4
    coord = pa.array(x.tolist(), pa.list_(pa.int64()))
    table = pa.table({"id": np.arange(len(x)), "coord": coord, "own": np.ones(len(x), bool), "core": core})
    rows = pa.Table.from_batches(list(tiles.merge_tile(table, ClusterParams(45, 4, method=method, visit=visit), 8, True))).to_pylist()
    forest, name = Forest(len(x)), {r["a"]: r["b"] for r in rows if r["kind"] == "name"}
    for r in rows:
        if r["kind"] == "link":
            assert forest.union(r["a"], r["b"])  # one tile's links make no circle
    least: dict[int, int] = {}
    for i in sorted(name):
        least.setdefault(forest.find(name[i]), i)
    assert {i: least[forest.find(name[i])] for i in name} == {i: c for i, c, role in brute(x, 45, 4) if role == "core"}
    n = {r["a"]: r["b"] for r in rows if r["kind"] == "counts"}
    assert asked and n[0] == n[1] + n[2] + n[3] and n[3] >= n[4] == sum(r["kind"] == "link" for r in rows)


def test_rectangles_of_a_block_are_those_of_its_points():
    x = R.integers(0, 300, (900, 5))
    tree, p = indexes.RectangleTree(x), x[:30]
    near = set(tree.near(p, 2500).tolist())
    assert near == set().union(*(tree.near(q[None], 2500).tolist() for q in p))


def test_features_are_worked_out_once(spark):
    x, read = R.integers(0, 400, (60, 2)), spark.sparkContext.accumulator(0)

    def seen(batches):
        for batch in batches:
            read.add(batch.num_rows)
            yield batch

    p = points_of(spark, x)
    frame = p.frame.mapInArrow(seen, p.frame.schema)
    assert found(engine.cluster(p.with_frame(frame), ClusterParams(45, 4))) == brute(x, 45, 4)
    assert read.value == len(x)


@pytest.mark.parametrize("weighty", [False, True])
def test_buckets_meet_block_against_block(spark, monkeypatch, weighty):
    x = np.concatenate([R.integers(0, 60, (150, 8)), R.integers(0, 400, (60, 8)), R.integers(300, 360, (90, 8))])
    if weighty:
        x = np.repeat(x[:150], 3, axis=0)
    rows, real = [], relational.bucket_blocks

    def spied(points, prm):
        deal, tasks = real(points, prm)

        def spy(frame):
            dealt = deal(frame)
            rows.append((tasks, dealt.groupBy("low", "high").count().agg({"count": "max"}).first()[0]))
            return dealt

        return spy, tasks

    monkeypatch.setattr(relational, "BUCKET_ROWS", 32)
    monkeypatch.setattr(relational, "LEAST_ROWS", 32)
    monkeypatch.setattr(relational, "bucket_blocks", spied)
    prm = ClusterParams(45, 4, method="bucket_pruned", fold=weighty)
    assert found(engine.cluster(points_of(spark, x), prm)) == brute(x, 45, 4)
    assert rows and all(tasks > 10 and most < 120 for tasks, most in rows)


def test_reference_takes_no_distances_within_a_tree(monkeypatch):
    x = np.concatenate([R.integers(0, 60, (1500, 3)), R.integers(300, 360, (1500, 3)), R.integers(0, 400, (60, 3))])
    coord = pa.array(x.tolist(), pa.list_(pa.int64()))
    table = pa.table({"id": np.arange(len(x)), "coord": coord, "own": np.ones(len(x), bool)})
    prm, taken, real = ClusterParams(45, 4, method="reference"), [], tiles.within
    monkeypatch.setattr(tiles, "within", lambda tile, a, b: taken.append(len(a) * len(b)) or real(tile, a, b))
    flagged = pa.Table.from_batches(list(tiles.label_tile(table, prm, 3, True)))
    core = flagged["core"].to_numpy(zero_copy_only=False)
    rows = pa.Table.from_batches(list(tiles.merge_tile(flagged.append_column("own", table["own"]), prm, 3, True))).to_pylist()
    assert sum(taken) < len(x) ** 2 // 2
    near = ((x[:, None] - x[None]) ** 2).sum(axis=2) <= 45 * 45
    ids = flagged["id"].to_numpy()
    assert sorted(ids[core].tolist()) == np.flatnonzero(near.sum(axis=1) >= 4).tolist()
    assert not any(r["kind"] == "link" for r in rows)  # all are own
    assert {(r["a"], r["b"]) for r in rows if r["kind"] == "name"} == {(i, c) for i, c, role in brute(x, 45, 4) if role == "core"}
    loose = np.setdiff1d(np.arange(len(x)), ids[core])
    assert {(r["a"], r["b"]) for r in rows if r["kind"] == "touch"} == {(i, j) for i in loose.tolist() for j in ids[core].tolist() if near[i, j]}

"""Repeated coordinates are worked on once: the work is that of the places, the results those of all points."""

import numpy as np
import pytest

from densegrid.operators import profile, relational
from densegrid.params import ClusterParams
from densegrid.plans import engine
from densegrid.streaming import incremental
from tests.test_engine import BLOBS, LATTICE, brute, found, points_of

TIMES = 30


def repeated(spark, x, times=TIMES):
    return points_of(spark, np.tile(x, (times, 1)))


def expected(x, eps, min_pts, times=TIMES, rule="min_cluster"):
    """Of the places, each as often: times as many points within eps are asked for."""
    rows = brute(x, eps, min_pts, rule)
    return sorted((i + len(x) * k, c, role) for k in range(times) for i, c, role in rows)


def counting(monkeypatch, where, name, seen):
    real = getattr(where, name)

    def spy(points, *a, **k):
        seen.append((getattr(points, "frame", points)).count())
        return real(points, *a, **k)

    monkeypatch.setattr(where, name, spy)


@pytest.mark.parametrize("method", ["slab_pruned", "kdtree_pruned", "reference"])
def test_tiles_hold_places(spark, monkeypatch, method):
    seen, x = [], np.unique(LATTICE, axis=0)
    counting(monkeypatch, engine, "plan_tiles", seen)
    prm = ClusterParams(2, 5 * TIMES, method=method, tile_points=1000)
    assert found(engine.cluster(repeated(spark, x), prm)) == expected(x, 2, 5) and seen == [len(x)]


def test_brute_pairs_places(spark, monkeypatch):
    seen, x = [], np.unique(BLOBS, axis=0)
    counting(monkeypatch, relational, "all_pairs", seen)
    assert found(engine.cluster(repeated(spark, x), ClusterParams(6, 4 * TIMES, method="brute"))) == expected(x, 6, 4) and seen == [len(x)]


def test_all_pairs_in_several_groups(spark):
    p = points_of(spark, BLOBS)
    frame = p.frame.withColumn("weight", p.frame["id"] + 1)
    got = sorted(map(tuple, relational.all_pairs(frame, ClusterParams(6, 4), 2, True, block=30).collect()))
    dd = ((BLOBS[:, None] - BLOBS[None]) ** 2).sum(axis=2)
    assert got == sorted((i, j, j + 1, int(dd[i, j])) for i, j in zip(*map(np.ndarray.tolist, np.nonzero(dd <= 36)), strict=True))


def test_assignment_asks_places(spark, monkeypatch):
    x = np.unique(BLOBS, axis=0)
    prm, points = ClusterParams(6, 4 * TIMES), repeated(spark, x)
    core = engine.cluster(points, prm).core
    seen = []
    counting(monkeypatch, profile, "eps_neighbours", seen)
    got = {r["id"]: r["cluster_id"] for r in profile.assign_new(core, points, prm).collect()}
    label = {i: c for i, c, role in expected(x, 6, 4) if role == "core"}
    assert len(got) == len(x) * TIMES and all(got[i] == c for i, c in label.items()) and seen == [len(x)]


def test_axioms_by_places(spark, monkeypatch):
    x = np.unique(BLOBS, axis=0)
    prm, points = ClusterParams(6, 4 * 3, border_rule="all"), repeated(spark, x, 3)
    labels, seen = engine.cluster(points, prm).labels, []
    counting(monkeypatch, relational, "eps_neighbours", seen)
    got = {r["cluster_id"]: (r["due"], r["held"], r["components"]) for r in relational.axiom_report(points, labels, prm).collect()}
    near, rows = ((x[:, None] - x[None]) ** 2).sum(axis=2) <= 36, brute(x, 6, 4, "all")
    due = {}
    for i, c, role in rows:
        if role == "core":
            due[c] = due.get(c, 0) + int(near[i].sum()) * 9
    assert got == {c: (n, n, 1) for c, n in due.items()} and seen == [len(x)]
    lost = labels.where("id % 2 = 0")  # points left out are due and not held
    less = {r["cluster_id"]: (r["due"], r["held"]) for r in relational.axiom_report(points, lost, prm).collect()}
    assert less and all(h < d for d, h in less.values())


def test_insertions_count_places(spark, monkeypatch):
    x = np.unique(BLOBS, axis=0)
    every, prm, seen = repeated(spark, x), ClusterParams(6, 4 * TIMES), []
    counting(monkeypatch, incremental, "eps_neighbours", seen)
    state = incremental.empty_state(every)
    for k in range(3):
        state = incremental.insert_points(state, every.with_frame(every.frame.where(f"pmod(xxhash64(id), 3) = {k}")), prm)
    got = sorted(map(tuple, incremental.state_labels(state, every, prm).collect()))
    assert got == expected(x, 6, 4) and max(seen) <= len(x)

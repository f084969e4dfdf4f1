import numpy as np
import pytest
from pyspark.sql import functions as F

from densegrid import workloads as w
from densegrid.operators import measures, profile, relational
from densegrid.operators.components import components, forest_roots
from densegrid.operators.generator import drift_clusters
from densegrid.params import ClusterParams
from densegrid.plans.engine import cluster
from densegrid.sources.points import Points, as_points, read_points, write_result

EXACT = ["slab_pruned", "slab_full", "grid_full", "kdtree_pruned", "reference", "bucket_pruned"]


def points_of(spark, x, ids=None):
    rows = [(int(i), [int(v) for v in c]) for i, c in zip(ids if ids is not None else range(len(x)), x, strict=True)]
    return Points(spark.createDataFrame(rows, "id bigint, coord array<bigint>"), len(x[0]) if len(x) else 2, True)


def found(result):
    return sorted(tuple(r) for r in result.labels.select("id", "cluster_id", "role").collect())


def brute(x, eps, min_pts, rule="min_cluster"):
    """By definition, in numpy."""
    x = np.asarray(x)
    near = ((x[:, None] - x[None]) ** 2).sum(axis=2) <= eps * eps
    core = near.sum(axis=1) >= min_pts
    label = np.where(core, np.arange(len(x)), -1)
    while True:
        new = np.array([label[near[i] & core].min() if core[i] else -1 for i in range(len(x))])
        if (new == label).all():
            break
        label = new
    out = []
    for i in range(len(x)):
        if core[i]:
            out.append((i, int(label[i]), "core"))
            continue
        own = sorted(set(label[near[i] & core].tolist()))
        out += [(i, c, "border") for c in (own if rule == "all" else own[:1])] or [(i, -1, "noise")]
    return sorted(out)


LATTICE = np.random.default_rng(3).integers(0, 9, (160, 4))
BLOBS = np.vstack([np.random.default_rng(k).normal(40 * k, 9, (50, 2)) for k in range(4)]).round().astype(int)


def test_toy(spark):
    got = found(cluster(w.toy(spark), ClusterParams(10, 4)))
    assert [r for r in got if r[0] in (5, 6, 11)] == [(5, 1, "border"), (6, 1, "border"), (11, -1, "noise")]
    every = found(cluster(w.toy(spark), ClusterParams(10, 4, border_rule="all")))
    assert (6, 1, "border") in every and (6, 7, "border") in every
    prm = ClusterParams(10, 4)
    pairs = spark.createDataFrame([(5, 6), (1, 11), (6, 10), (1, 7), (11, 11)], "a bigint, b bigint")
    met = {(r["a"], r["b"]) for r in relational.density_connected(w.toy(spark), prm, pairs).collect() if r["connected"]}
    assert met == {(5, 6), (6, 10)}  # the border point 6 is connected to both sides, noise not even to itself
    reach = {tuple(r) for r in relational.direct_reach(w.toy(spark), prm).collect()}
    assert (1, 5) in reach and (5, 1) not in reach  # a border is reached and reaches nothing
    assert {r[0] for r in relational.reachable_from(w.toy(spark), prm, 1).collect()} == {1, 2, 3, 4, 5, 6}


@pytest.mark.parametrize("method", EXACT)
def test_methods_equal_the_definition(spark, method):
    assert found(cluster(points_of(spark, LATTICE), ClusterParams(2, 6, method=method))) == brute(LATTICE, 2, 6)


@pytest.mark.parametrize("rule", ["min_cluster", "all"])
def test_border_rules(spark, rule):
    assert found(cluster(points_of(spark, BLOBS), ClusterParams(6, 6, border_rule=rule))) == brute(BLOBS, 6, 6, rule)


def test_tiles_change_nothing(spark):
    prm = ClusterParams(6, 6, tile_points=12)
    assert found(cluster(points_of(spark, BLOBS), prm)) == brute(BLOBS, 6, 6)
    assert found(cluster(points_of(spark, BLOBS), prm.with_(index_bytes=0))) == brute(BLOBS, 6, 6)  # posting lists
    assert found(cluster(points_of(spark, BLOBS), prm.with_(driver_roots=0))) == brute(BLOBS, 6, 6)  # distributed components


HOT = np.vstack([np.random.default_rng(1).integers(0, 4, (90, 2)), np.random.default_rng(2).integers(-40, 60, (90, 2))])


@pytest.mark.parametrize("method", ["slab_pruned", "slab_full", "grid_full", "kdtree_pruned", "reference"])
@pytest.mark.parametrize("rule", ["min_cluster", "all"])
def test_a_cell_of_half_the_points_is_dealt_to_several_tasks(spark, method, rule):
    prm = ClusterParams(7, 5, method=method, border_rule=rule, tile_points=30, tile_limit=40)
    assert found(cluster(points_of(spark, HOT), prm)) == brute(HOT, 7, 5, rule)


def test_hot_tiles_are_parted_and_others_are_not(spark):
    from densegrid.functions.geometry import safe_reach
    from densegrid.operators.tiles import deal, part_hot, plan_tiles

    p, prm = points_of(spark, HOT), ClusterParams(7, 5, tile_points=30)
    dealt = deal(p.frame, plan_tiles(p, prm), 2, 7, safe_reach(2))
    size = {r["tile"]: r["count"] for r in dealt.groupBy("tile").count().collect()}
    hot = max(size, key=size.get)
    calm, parted = part_hot(dealt, {hot: 5})
    assert {r["tile"]: r["count"] for r in calm.groupBy("tile").count().collect()} == {t: n for t, n in size.items() if t != hot}
    tasks = parted.groupBy("low", "high").count().collect()
    assert len(tasks) == 15 and max(r["count"] for r in tasks) < size[hot] * 0.6  # two of five groups
    plan = parted._jdf.queryExecution().executedPlan().toString() + calm._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and "BroadcastNestedLoopJoin" not in plan


def test_metamorphic(spark):
    base = {i: (c, r) for i, c, r in found(cluster(points_of(spark, BLOBS), ClusterParams(6, 6)))}
    for x, eps in ((BLOBS + np.array([-1000, 777]), 6), (BLOBS * 3, 18), (BLOBS[:, ::-1], 6)):
        assert {i: (c, r) for i, c, r in found(cluster(points_of(spark, x), ClusterParams(eps, 6)))} == base
    p = points_of(spark, BLOBS)
    assert {i: (c, r) for i, c, r in found(cluster(p.with_frame(p.frame.repartition(7, F.rand(3))), ClusterParams(6, 6)))} == base


def test_edge_cases(spark):
    assert found(cluster(points_of(spark, np.empty((0, 2))), ClusterParams(1, 1))) == []
    assert found(cluster(points_of(spark, [[3, 4]]), ClusterParams(1, 2))) == [(0, -1, "noise")]
    assert found(cluster(points_of(spark, [[3, 4]]), ClusterParams(1, 1))) == [(0, 0, "core")]
    same = [[5, 5]] * 8
    assert found(cluster(points_of(spark, same), ClusterParams(1, 8))) == [(i, 0, "core") for i in range(8)]
    assert {r[2] for r in found(cluster(points_of(spark, same), ClusterParams(1, 9)))} == {"noise"}
    line = [[i] for i in range(10)]
    assert {r[1] for r in found(cluster(points_of(spark, line), ClusterParams(100, 2)))} == {0}
    assert {r[1] for r in found(cluster(points_of(spark, [[3 * i] for i in range(10)]), ClusterParams(2, 2)))} == {-1}
    for bad in ({"eps": 0}, {"min_pts": 0}, {"method": "x"}, {"border_rule": "x"}):
        with pytest.raises(ValueError):
            ClusterParams(**{"eps": 1, "min_pts": 1, **bad})


def test_real_coordinates(spark):
    x = np.random.default_rng(5).normal(0, 1, (150, 3))
    rows = [(i, c.tolist()) for i, c in enumerate(x)]
    p = Points(spark.createDataFrame(rows, "id bigint, coord array<double>"), 3, False)
    assert found(cluster(p, ClusterParams(0.45, 4))) == brute(x, 0.45, 4)


def test_nulls(spark):
    df = spark.createDataFrame([(1, 1.0, 2.0), (2, None, 2.0), (3, float("nan"), 1.0), (None, 1.0, 1.0)], "id bigint, x double, y double")
    assert [r["id"] for r in as_points(df, "id", ["x", "y"], exact=False, null_policy="drop").frame.collect()] == [1]
    with pytest.raises(Exception, match="non-finite"):
        as_points(df, "id", ["x", "y"], exact=False).frame.collect()


def test_axioms(spark):
    p, prm = points_of(spark, BLOBS), ClusterParams(6, 6, border_rule="all")
    labels = cluster(p, prm).labels
    assert relational.check_axioms(p, labels, prm).isEmpty()
    broken = labels.withColumn("cluster_id", F.when(F.col("id") == 0, 999).otherwise(F.col("cluster_id")))
    assert not relational.check_axioms(p, broken, prm).isEmpty()


@pytest.mark.parametrize("rho", [0.001, 0.1, 0.5])
def test_approximate_is_between(spark, rho):
    p = points_of(spark, BLOBS)
    approx = {i: c for i, c, r in found(cluster(p, ClusterParams(6, 6, method="grid_approx", rho=rho))) if r == "core"}
    low = {i: c for i, c, r in brute(BLOBS, 6, 6) if r == "core"}
    assert approx.keys() == low.keys()
    near = ((BLOBS[:, None] - BLOBS[None]) ** 2).sum(axis=2)
    for i in low:
        for j in low:
            if near[i, j] <= 36:
                assert approx[i] == approx[j]  # what must merge has merged
    wide = {i: i for i in low}
    for _ in range(len(low)):
        new = {i: min(wide[j] for j in low if near[i, j] <= (6 * (1 + rho)) ** 2) for i in low}
        if new == wide:
            break
        wide = new
    assert all(wide[i] == wide[j] for i in low for j in low if approx[i] == approx[j])  # and nothing farther apart
    if rho == 0.001:
        assert approx == low


def test_approximate_cells_with_near_points_merge(spark):
    """Representatives on both sides would be up to eps * rho off each, and these would stay apart."""
    p = Points(spark.createDataFrame([(i, [x]) for i, x in enumerate((6.0, 8.9, 19.9, 18.1))], "id bigint, coord array<double>"), 1, False)
    for method in ("slab_pruned", "grid_approx"):
        assert found(cluster(p, ClusterParams(10, 2, method=method, rho=0.3))) == [(i, 0, "core") for i in range(4)]


def sandwiched(x, eps, min_pts, rho, labels):
    d2 = ((x[:, None] - x[None]) ** 2).sum(axis=2)
    core = (d2 <= eps * eps).sum(axis=1) >= min_pts
    got = {i: c for i, c, r in labels if r == "core"}
    assert got.keys() == {*np.flatnonzero(core).tolist()}
    wide = np.arange(len(x))
    for _ in range(len(x)):
        wide = np.array([wide[(d2[i] <= (eps * (1 + rho)) ** 2) & core].min() if core[i] else -1 for i in range(len(x))])
    for i in got:
        for j in got:
            assert d2[i, j] > eps * eps or got[i] == got[j]
            assert got[i] != got[j] or wide[i] == wide[j]


@pytest.mark.parametrize("seed", range(4))
def test_approximate_random_layouts(seed):
    """Both bounds for many small layouts, by the kernels in one process."""
    import pyarrow as pa

    from densegrid.operators.tiles import label_tile, merge_tile

    rng = np.random.default_rng(seed)
    for _ in range(60):
        d, n, rho = int(rng.integers(1, 4)), int(rng.integers(4, 30)), float(rng.uniform(0.05, 0.5))
        x = rng.uniform(0, 12 * d**0.5, (n, d)).round(1)
        prm = ClusterParams(5.0, int(rng.integers(1, 4)), method="grid_approx", rho=rho)
        rows = pa.table({"id": pa.array(range(n), pa.int64()), "coord": pa.array(x.tolist(), pa.list_(pa.float64())), "own": pa.array([True] * n)})
        flagged = pa.Table.from_batches(list(label_tile(rows, prm, d, False))).append_column("own", pa.array([True] * n))
        out = pa.Table.from_batches([b for b in merge_tile(flagged, prm, d, False)]).to_pylist()
        label = {r["a"]: r["b"] for r in out if r["kind"] == "name"}
        for _ in range(n):
            for r in out:
                if r["kind"] == "link":
                    low = min(label[i] for i in label if label[i] in (label[r["a"]], label[r["b"]]))
                    old = {label[r["a"]], label[r["b"]]}
                    label = {i: low if c in old else c for i, c in label.items()}
        sandwiched(x, 5.0, prm.min_pts, rho, [(i, c, "core") for i, c in label.items()])


def test_approximate_counts_lie_between():
    from densegrid.operators.tiles import SubCells

    rng = np.random.default_rng(6)
    for d in (1, 2, 3, 5):
        for rho in (0.01, 0.2, 0.5):
            p = rng.uniform(0, 10 / d**0.5, (60, d))
            q = rng.uniform(-15, 15, (200, d))
            got = SubCells(p, 10.0, rho).count(q, 100.0)
            d2 = ((q[:, None] - p[None]) ** 2).sum(axis=2)
            assert ((d2 <= 100).sum(axis=1) <= got).all() and (got <= (d2 <= (10 * (1 + rho)) ** 2 + 1e-9).sum(axis=1)).all()


def test_components(spark):
    edges = [(1, 2), (2, 3), (10, 11), (7, 7), (3, 30), (None, 4)] + [(100 + i, 101 + i) for i in range(40)]
    df = spark.createDataFrame(edges, "a bigint, b bigint")
    want = {1: 1, 2: 1, 3: 1, 30: 1, 10: 10, 11: 10, 7: 7} | {100 + i: 100 for i in range(41)}
    for rows in (components(df), forest_roots(df, 1000), forest_roots(df, 3)):
        assert {r["node"]: r["root"] for r in rows.collect()} == want
    assert components(df.limit(0)).count() == 0 == forest_roots(df.limit(0), 10).count()


def test_serial_counts_of_the_generated_layout(spark):
    """The counts of the anchors table, recomputed by the engine."""
    path = "/root/testdata/sf0.01"
    p = w.FIXTURES["spread3"].points(spark, path)
    prm = ClusterParams(30, 20, visit="both", box_prune=False)
    full, pruned = (measures.serial_merge_counts(p, prm.with_(method=m)) for m in ("slab_full", "slab_pruned"))
    assert (full["core_cells"], full["considered"], full["checks"], full["skipped"]) == (1037, 51120, 51120, 0)
    assert (pruned["checks"], pruned["unions"], pruned["considered"]) == (2381, 1027, 51120)
    got = {r["variant"]: r for r in measures.merge_counts(p, prm, ["slab_full", "slab_pruned"]).collect()}
    for r in got.values():  # the tiles meet the same pairs; what they unite more than once is told apart
        assert (r["core_cells"], r["considered"], r["needed"]) == (1037, 51120, 1027) and r["unions"] == r["needed"] + r["waste"]
        assert r["considered"] == r["skipped"] + r["boxed"] + r["checks"]
    ratio = {r["variant"]: r["ratio"] for r in measures.merge_ratio(spark.createDataFrame(list(got.values())), "slab_full").collect()}
    assert ratio["slab_pruned"] < 0.12


def test_timed_runs_are_cancelled(spark):
    import time

    began = time.perf_counter()
    slow = lambda: spark.range(200_000_000_000).select(F.sum(F.sqrt(F.col("id").cast("double")))).collect()
    assert measures.timed(slow, 3, 2.0, spark) == (2.0, "censored") and time.perf_counter() - began < 30
    assert measures.timed(lambda: spark.range(10).count(), 2, 60.0, spark)[1] == "ok"
    with pytest.raises(ZeroDivisionError):
        measures.timed(lambda: 1 / 0, 1, 5.0, spark)
    runs = spark.createDataFrame([("a", "w", 1, 1, 1.0, 1, "seconds", 8.0, "ok"), ("b", "w", 1, 1, 1.0, 1, "seconds", 2.0, "ok"), ("c", "w", 1, 1, 1.0, 1, "seconds", 9.0, "censored")], measures.METRIC)
    assert {r["variant"]: (r["speedup"], r["status"]) for r in measures.speedup(runs, "a").collect()} == {"a": (1.0, "ok"), "b": (4.0, "ok"), "c": (None, "censored")}
    assert {r["variant"]: r["status"] for r in measures.speedup(runs, "c").collect()} == {"a": "at_least", "b": "at_least", "c": "censored"}


def test_union_ablation(spark):
    rows = measures.union_ablation(points_of(spark, BLOBS), ClusterParams(6, 6)).collect()
    assert len(rows) == 6 and len({r["unions"] for r in rows}) == 1
    hops = {(r["policy"], r["compress"]): r["hops"] for r in rows}
    assert all(hops[p, True] <= hops[p, False] for p, _ in hops) and hops["by_size", False] <= hops["naive", False]


def test_index_report(spark):
    rows = measures.index_report(points_of(spark, BLOBS), ClusterParams(6, 6), ["slab_pruned", "kdtree_pruned", "grid_full"], [4, 6]).collect()
    assert len(rows) == 6 and all(r["seconds"] > 0 and r["bytes"] > 0 for r in rows)
    by = {(r["variant"], r["eps"]): r["pairs"] for r in rows}
    assert by["slab_pruned", 4.0] == by["kdtree_pruned", 4.0] and by["grid_full", 6.0] <= by["slab_pruned", 6.0]


def test_generator(spark):
    p, truth = drift_clusters(spark, 4000, 5, 3, noise=0.001)
    rows = p.frame.collect()
    assert len(rows) == 4000 and len({r["id"] for r in rows}) == 4000
    assert all(1000 <= v <= 10000 for r in rows for v in r["coord"])
    counts = {r["truth"]: r["count"] for r in truth.groupBy("truth").count().collect()}
    assert counts[-1] == 4 and set(counts) == {-1, 0, 1, 2, 3, 4}
    again = drift_clusters(spark, 4000, 5, 3, noise=0.001)[0].frame.repartition(3).collect()
    assert sorted(map(str, rows)) == sorted(map(str, again))
    labels = cluster(p, ClusterParams(60, 5)).labels
    row = measures.agreement(labels, truth.select("id", F.col("truth").alias("cluster_id"))).first()
    assert row["adjusted_rand"] > 0.9


def test_agreement(spark):
    a = spark.createDataFrame([(i, i % 3) for i in range(30)], "id bigint, cluster_id bigint")
    row = measures.agreement(a, a.withColumn("cluster_id", F.col("cluster_id") + 5)).first()
    assert row["adjusted_rand"] == row["precision"] == row["recall"] == 1.0


def test_reports(spark, tmp_path):
    p, prm = points_of(spark, BLOBS), ClusterParams(6, 6)
    r = cluster(p, prm)
    assert profile.cluster_profile(r.labels, p).agg(F.sum("size")).first()[0] == len(BLOBS)
    new = profile.assign_new(r.core, p, prm).join(r.labels.where("role = 'core'").withColumnRenamed("cluster_id", "c"), "id")
    assert new.where("cluster_id <> c").isEmpty()
    assert profile.suggest_eps(p, 4, 50).count() == 4
    for fmt in ("parquet", "orc", "json"):
        write_result(r.labels, f"{tmp_path}/{fmt}", fmt, ["role"])
        assert read_points(spark, f"{tmp_path}/{fmt}", fmt).count() == len(BLOBS)


def test_main_path_has_no_cross_join(spark):
    p = points_of(spark, BLOBS)
    plan = cluster(p, ClusterParams(6, 6)).labels._jdf.queryExecution().executedPlan().toString()
    plan += relational.eps_neighbours(p, ClusterParams(6, 6))._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and "BroadcastNestedLoopJoin" not in plan and "SinglePartition" not in plan


def test_runs_stopped_at_a_whole_number_of_seconds_are_reported(spark):
    p = Points(spark.createDataFrame([(i, [i]) for i in range(9)], "id bigint, coord array<bigint>"), 1, True)
    rows = measures.scalability_grid({"nine": (p, ClusterParams(2, 2))}, ["slab_pruned"], limit_s=0).collect()
    assert [(r["variant"], r["n"], r["value"], r["status"]) for r in rows] == [("slab_pruned", 9, 0.0, "censored")]

import math
import os
import re
import subprocess
import sys

import pytest

from densegrid import catalogue
from densegrid.streaming import windows

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
SOME = [
    "clusters_slab_pruned_part2d", "clusters_kdtree_pruned_events2d", "clusters_slab_pruned_emb54", "clusters_border_all_events2d", "clusters_toy",
    "eps_neighbour_counts_events2d", "cells_events2d", "cell_ids_events2d", "cell_curve_events2d", "neighbour_cells_offsets_part2d", "neighbour_cells_slab_sql_part2d",
    "neighbour_cells_slabs_part2d_box", "neighbour_cells_buckets_part2d", "slab_rows_events2d", "core_cells_events2d", "merge_edges_full_events2d", "profile_cube_events2d",
    "assign_new_part2d", "clusters_by_event_type_udtf", "stream_window_cell_counts", "stream_dense_cells", "json_feature_clusters",
]


def norm(v):
    return "-" if v is None or (isinstance(v, float) and math.isnan(v)) else repr(round(v, 9)) if isinstance(v, float) else str(v)


@pytest.mark.parametrize("name", SOME)
def test_query_equals_sql(spark, sf, duck, name):
    df = catalogue.queries()[name](spark, sf)
    cols = sorted(df.columns)
    mine = sorted(tuple(norm(r[c]) for c in cols) for r in df.collect())
    ran = duck.execute(catalogue.oracle_sql()[name])
    names = [c[0] for c in ran.description]
    assert sorted(names) == cols
    assert mine == sorted(tuple(norm(r[names.index(c)]) for c in cols) for r in ran.fetchall())


def test_every_sql_has_its_query():
    assert set(catalogue.oracle_sql()) <= set(catalogue.queries())


def test_session_windows(spark, sf):
    stream = windows.drain(windows.session_counts(windows.event_stream(spark, sf)), "sessions_test", "complete")
    batch = windows.session_counts(catalogue.load_table(spark, sf, "events").withColumn("ts", windows.F.col("ts").cast("timestamp")))
    assert sorted(map(str, stream.collect())) == sorted(map(str, batch.collect()))


def test_window_clusters_equal_the_batch(spark, sf, tmp_path):
    """Windows closed by the stream, all in few runs, against each window clustered alone."""
    from densegrid.operators.cells import F
    from densegrid.params import ClusterParams
    from densegrid.plans.engine import cluster
    from densegrid.sources.points import as_points

    prm = ClusterParams(600, 5)
    windows.cluster_windows(windows.event_stream(spark, sf), prm, f"{tmp_path}/out", f"{tmp_path}/state").awaitTermination()
    got = spark.read.parquet(f"{tmp_path}/out")
    events = catalogue.load_table(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    at = events.withColumn("start", F.window("ts", "7 days")["start"])
    starts = sorted(r["start"] for r in got.select("start").distinct().collect())
    assert len(starts) >= 3
    for start in starts:
        rows = at.where(F.col("start") == start)
        want = cluster(as_points(rows, "event_id", [F.floor(F.unix_timestamp("ts") / 60), F.round(F.col("value") * 100)]), prm).labels
        have = got.where(F.col("start") == start).select("id", "cluster_id", "role")
        assert sorted(map(tuple, have.collect())) == sorted(map(tuple, want.collect()))


def test_late_rows_are_counted(spark, tmp_path):
    import datetime

    day = lambda n, h=0: datetime.datetime(2024, 1, n, h)
    schema = "event_id bigint, ts timestamp, value double, user_id bigint"
    for k, rows in enumerate(([(1, day(1), 1.0, 1), (2, day(9), 1.0, 1)], [(3, day(20), 1.0, 1)], [(4, day(2), 1.0, 1), (5, day(3), 1.0, 1), (6, day(21), 1.0, 1)])):
        spark.createDataFrame(rows, schema).coalesce(1).write.parquet(f"{tmp_path}/in/part{k}")
        for f in os.listdir(f"{tmp_path}/in/part{k}"):
            if f.endswith(".parquet"):
                os.makedirs(f"{tmp_path}/all", exist_ok=True)
                os.rename(f"{tmp_path}/in/part{k}/{f}", f"{tmp_path}/all/{k}.parquet")
                os.utime(f"{tmp_path}/all/{k}.parquet", (1000 + k, 1000 + k))
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/all")
    query = windows.window_cell_counts(stream).writeStream.format("noop").outputMode("update").option("checkpointLocation", f"{tmp_path}/c1").trigger(availableNow=True).start()
    query.awaitTermination()
    assert windows.late_rows(query) == 2
    from densegrid.params import ClusterParams

    windows.cluster_windows(stream, ClusterParams(600, 1), f"{tmp_path}/out", f"{tmp_path}/c2").awaitTermination()
    late = spark.read.parquet(f"{tmp_path}/out_late").agg(windows.F.sum("late")).first()[0]
    assert late == 2 and {r["id"] for r in spark.read.parquet(f"{tmp_path}/out").collect()} == {1, 2}


def test_insertions_equal_the_batch(spark):
    import numpy as np

    from densegrid.params import ClusterParams
    from densegrid.sources.points import Points
    from densegrid.streaming import incremental
    from tests.test_engine import BLOBS, brute

    rng, prm = np.random.default_rng(5), ClusterParams(6, 6)
    turn = rng.integers(0, 4, len(BLOBS))
    of = lambda rows: Points(spark.createDataFrame([(int(i), [int(v) for v in BLOBS[i]]) for i in rows], "id bigint, coord array<bigint>"), 2, True)
    state = incremental.empty_state(of(range(3)))
    for k in range(4):
        state = incremental.insert_points(state, of(np.flatnonzero(turn == k).tolist()), prm)
    got = sorted(map(tuple, incremental.state_labels(state, of(range(3)), prm).collect()))
    assert got == brute(BLOBS, 6, 6)


def test_asof_and_filters(spark):
    from densegrid.operators import neighbours, profile
    from densegrid.sources.points import Points, read_points, scale_features, write_result

    events = spark.createDataFrame([(1, "a", 5), (2, "a", 1), (3, "b", 9), (4, None, 3)], "id bigint, k string, t int")
    marks = spark.createDataFrame([("a", 5, 10), ("a", 3, 7), ("a", 5, 11), ("b", 10, 1)], "k string, t int, v int")
    assert {r["id"]: r["v"] for r in profile.latest_before(events, marks, "k", "t", "v").collect()} == {1: 11, 2: None, 3: None, 4: None}
    p = Points(spark.createDataFrame([(i, [i, 0]) for i in range(10)], "id bigint, coord array<bigint>"), 2, True)
    assert {r["id"] for r in neighbours.in_ball(p, [4, 0], 2).collect()} == {2, 3, 4, 5, 6}
    assert {r["id"] for r in neighbours.in_box(p, [4, 0], [6, 0]).collect()} == {4, 5, 6}
    assert [r["coord"] for r in scale_features(p, [0.5, 2.0], [2.0, 1.0]).frame.orderBy("id").limit(1).collect()] == [[-1.0, -2.0]]
    assert {r["id"]: r["dist2"] for r in profile.k_distance(p, 3, 0.5).collect()}[0] == 4
    assert profile.k_distance(p, 11, 5).count() == 0


def test_csv_and_sql_helpers(spark, tmp_path):
    from densegrid.sources.points import as_points, read_points, write_result
    from densegrid.sql import register

    write_result(spark.createDataFrame([(1, 2.5, -1.0), (2, 0.0, 4.0)], "id bigint, x double, y double"), f"{tmp_path}/c", "csv")
    df = read_points(spark, f"{tmp_path}/c", "csv", "id bigint, x double, y double")
    assert sorted(map(tuple, as_points(df, "id", ["x", "y"], exact=False).frame.collect())) == [(1, [2.5, -1.0]), (2, [0.0, 4.0])]
    register(spark)
    row = spark.sql("SELECT sq_distance(array(0D, 3D), array(4D, 0D)) AS d, grid_cell(array(10D, -1D), 2D * sqrt(2D)) AS c").first()
    assert row["d"] == 25.0 and row["c"] == [5, -1]


def test_nothing_else_needs_the_training_data_operators():
    for folder, _, files in os.walk(os.path.join(ROOT, "densegrid")):
        if os.path.basename(folder) == "llm":
            continue
        for f in files:
            if f.endswith(".py"):
                assert not re.search(r"(import|from)\s+densegrid\.llm", open(os.path.join(folder, f)).read()), f
    code = "import sys, importlib.abc\nclass No(importlib.abc.MetaPathFinder):\n  def find_spec(self, name, path=None, target=None):\n    if name in ('densegrid.llm', 'corpus_pipeline'): raise ModuleNotFoundError(name=name)\nsys.meta_path.insert(0, No())\nimport __spark_entry__ as e\nassert 'clusters_toy' in e.queries() and 'pipeline' not in e.queries(), e.queries()\nassert e.oracle_sql()"
    subprocess.run([sys.executable, "-c", code], cwd=ROOT, check=True)


@pytest.mark.parametrize("name, table, key, out", [
    ("clusters_toy", "customer", "c_custkey", "id"),
    ("components_forest6", "customer", "c_custkey", "node"),
    ("generated_drift10", "orders", "o_orderkey", "id"),
    ("offset_counts", "customer", "c_custkey", "cells"),
])
def test_query_follows_its_table(spark, sf, tmp_path, name, table, key, out):
    """On a few rows of the table the result has these rows' keys, or says how many cells they fill."""
    catalogue.load_table(spark, sf, table).limit(70).write.parquet(f"{tmp_path}/{table}.parquet")
    keys = {r[0] for r in spark.read.parquet(f"{tmp_path}/{table}.parquet").select(key).collect()}
    got = [r[out] for r in catalogue.queries()[name](spark, str(tmp_path)).collect()]
    assert len(keys) == 70 and (set(got) == keys if out != "cells" else len(got) == 7 and 0 < max(got) <= 70)

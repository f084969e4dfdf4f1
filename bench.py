"""Times the headline queries; prints one JSON line.

BENCH_SF_DIR names the tables, BENCH_CPUS the local cores, BENCH_REPEATS the runs
whose mean is taken, BENCH_LIMIT the seconds after which a baseline is stopped (its
ratios are then lower bounds). Every data set is written out before its runs, which
read it like any other points; a first run warms up the session.
"""

from __future__ import annotations

import json
import os
import sys

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

from pyspark.sql import SparkSession  # noqa: E402

from densegrid import workloads as w  # noqa: E402
from densegrid.operators import measures  # noqa: E402
from densegrid.params import ClusterParams  # noqa: E402
from densegrid.plans.engine import cluster  # noqa: E402
from densegrid.plans.lineage import cut  # noqa: E402

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
REPEATS = int(os.environ.get("BENCH_REPEATS", "1"))
LIMIT = float(os.environ.get("BENCH_LIMIT", "25"))

#: fixture, settings at sf0.1 (eps shrinks where points are ten times as dense), methods; baselines are stopped at the limit.
RUNS = [
    ("part2d", (50, 4), ("slab_pruned", "slab_full", "grid_full", "grid_approx", "reference")),
    ("events2d", (100, 10), ("slab_pruned", "slab_full", "grid_full", "grid_approx", "kdtree_pruned", "reference")),
    ("spread3", (20, 20), ("slab_pruned", "slab_full", "reference")),
    ("customer30", (140, 70), ("slab_pruned", "slab_full", "grid_approx")),
    ("customer40", (160, 80), ("slab_pruned", "slab_full", "grid_full", "kdtree_pruned")),
    ("customer54", (187, 90), ("slab_pruned", "slab_full", "grid_full")),
    ("emb54", (10300, 4), ("slab_pruned", "slab_full", "grid_full")),
    ("spread10", (80, 20), ("slab_pruned",)), ("spread30", (140, 70), ("slab_pruned",)), ("spread40", (160, 80), ("slab_pruned",)),
]

#: The published ratios that are formed: name, fixture, the slower method, the faster.
RATIOS = [
    ("3d_per_point_over_bitmap", "spread3", "reference", "slab_full"),
    ("30d_approximate_over_full", "customer30", "grid_approx", "slab_pruned"),
    ("40d_grid_over_bitmap", "customer40", "grid_full", "slab_full"),
    ("40d_grid_over_full", "customer40", "grid_full", "slab_pruned"),
    ("54d_grid_over_bitmap", "customer54", "grid_full", "slab_full"),
    ("54d_bitmap_over_full", "customer54", "slab_full", "slab_pruned"),
    ("54d_grid_over_full", "customer54", "grid_full", "slab_pruned"),
    ("40d_kdtree_over_bitmap_runs", "customer40", "kdtree_pruned", "slab_pruned"),
]


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").appName("densegrid-bench").config("spark.sql.shuffle.partitions", CPUS).config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "12g"))
        .config("spark.sql.session.timeZone", "UTC").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    spark.sparkContext.setLogLevel("OFF")
    seconds, censored, checks = {}, [], {}
    for name, (eps, min_pts), methods in RUNS:
        points = w.FIXTURES[name].points(spark, SF_DIR)
        points = points.with_frame(cut(points.frame.repartition(int(CPUS))))
        for method in methods:
            prm, kept = ClusterParams(eps, min_pts, method=method), []

            def run(points=points, prm=prm, kept=kept) -> None:
                found = cluster(points, prm)
                found.labels.write.format("noop").mode("overwrite").save()
                kept[:] = [found]

            if not seconds:
                run()
            s, status = measures.timed(run, REPEATS, None if method == "slab_pruned" else LIMIT, spark)
            seconds[f"{method}_{name}"] = round(s, 3)
            if status != "ok":
                censored.append(f"{method}_{name}")
            elif method in ("slab_pruned", "slab_full"):
                checks[f"{method}_{name}"] = kept[0].counts.first()["checks"]
            print(f"{method}_{name}", round(s, 3), status, file=sys.stderr, flush=True)
    sweep = w.FIXTURES["customer40"].points(spark, SF_DIR)
    sweep = sweep.with_frame(cut(sweep.frame))
    index = {r["variant"]: r for r in measures.index_report(sweep, ClusterParams(120, 80), ["slab_pruned", "kdtree_pruned"]).collect()}
    ratios = {k: round(seconds[f"{slow}_{fx}"] / seconds[f"{fast}_{fx}"], 2) for k, fx, slow, fast in RATIOS if f"{fast}_{fx}" not in censored}
    ratios["40d_kdtree_over_bitmap_neighbour_step"] = round(index["kdtree_pruned"]["seconds"] / index["slab_pruned"]["seconds"], 2)
    share = {n: round(checks[f"slab_pruned_{n}"] / checks[f"slab_full_{n}"], 4) for n, *_ in RUNS if checks.get(f"slab_full_{n}") and f"slab_pruned_{n}" in checks}
    print(json.dumps({
        "metric": "total_seconds", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "censored": censored,
        "ratios": ratios, "at_least": [k for k, fx, slow, _ in RATIOS if k in ratios and f"{slow}_{fx}" in censored], "merge_check_ratio": share,
        "index_bytes": {k: r["bytes"] for k, r in index.items()}, "sf": SF_DIR.rsplit("sf", 1)[-1],
    }))
    spark.stop()


if __name__ == "__main__":
    main()

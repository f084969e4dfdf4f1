"""Cost and accuracy measures and the runs behind them."""

from __future__ import annotations

import threading
import time
import uuid
from itertools import product

import numpy as np
from pyspark.sql import DataFrame, SparkSession, functions as F

from densegrid.functions.geometry import box_offset_count, cell_of, reach, reachable_offset_count, safe_reach
from densegrid.operators.forest import Forest, merge_cells
from densegrid.operators.tiles import OUT, Tile, core_flags, deal, index_tile, make_index, merge_test, neighbour_tile, plan_tiles, run_tiles, visiting
from densegrid.params import ClusterParams
from densegrid.sources.points import Points

#: Rows that the serial schedule may gather: it is for counting on small data.
SERIAL_LIMIT = 200_000
METRIC = "variant string, workload string, n bigint, d int, eps double, min_pts int, metric string, value double, status string"


def offset_counts(spark: SparkSession, dims: list[int]) -> DataFrame:
    """d, reach, box (with the cell itself), reachable: large counts as text."""
    return spark.createDataFrame([(d, reach(d), str(box_offset_count(d)), str(reachable_offset_count(d))) for d in dims], "d int, reach int, box string, reachable string")


def offset_probes(workloads: list[Points], eps: float) -> DataFrame:
    """``offset_counts`` of the points' dimensions, with their occupied cells and how many offsets an enumeration probes from these."""
    counts, out = offset_counts(workloads[0].frame.sparkSession, [p.dim for p in workloads]), None
    for p in workloads:
        one = p.frame.select(cell_of(F.col("coord"), p.dim, eps).alias("cell")).distinct().agg(F.count("*").alias("cells")).select(F.lit(p.dim).alias("d"), "cells")
        out = one if out is None else out.union(one)
    return counts.join(out, "d").select("*", (F.col("cells") * F.col("reachable").cast("long")).cast("string").alias("probes"))


def serial_merge_counts(points: Points, prm: ClusterParams) -> dict[str, int]:
    """considered, skipped, checks, unions of one forest over all core cells in lexicographic order.

    The sequential schedule in one process, for at most ``SERIAL_LIMIT`` points.
    """
    table = points.frame.withColumn("own", F.lit(True)).limit(SERIAL_LIMIT + 1).toArrow()
    if table.num_rows > SERIAL_LIMIT:
        raise ValueError("too many points for the serial schedule")
    tile = Tile(table, prm, points.dim, points.exact)
    index = make_index(tile, prm)
    core = core_flags(tile, index)
    core_cell = np.logical_or.reduceat(core, tile.first[:-1])
    _, c = merge_cells(np.flatnonzero(core_cell).tolist(), visiting(tile, index, core_cell, strict=True), merge_test(tile, core), len(tile.cells), prm.method.endswith("pruned"), prm.visit, tile.pruned)
    return {"core_cells": int(core_cell.sum()), "considered": c.considered, "skipped": c.skipped, "boxed": c.boxed, "checks": c.checks, "unions": c.unions}


def merge_counts(points: Points, prm: ClusterParams, methods: list[str]) -> DataFrame:
    """A row for each method of what its tiles met, skipped, ruled out by boxes, checked and united.

    Pairs are met by the strict corner rule, each in the tile that owns its first
    cell, so ``considered`` is a number of the data alone. ``needed`` is how many
    unions one forest would make; tiles that link the same cells again make
    ``waste`` more. Nothing but one row a method reaches the driver.
    """
    from densegrid.plans.engine import cluster

    out = None
    for m in methods:
        r = cluster(points, prm.with_(method=m, strict=True))
        held = r.core.agg(F.count_distinct("cluster_id").alias("clusters"))
        row = r.counts.crossJoin(held).select(F.lit(m).alias("variant"), "core_cells", "considered", "skipped", "boxed", "checks", "unions", (F.col("core_cells") - F.col("clusters")).alias("needed"), (F.col("unions") - F.col("core_cells") + F.col("clusters")).alias("waste"))
        out = row if out is None else out.union(row)
    return out


def merge_ratio(counts: DataFrame, base: str) -> DataFrame:
    """variant, ratio: checks as a share of the base variant's."""
    b = counts.where(F.col("variant") == base).select(F.col("checks").alias("_base"))
    return counts.crossJoin(F.broadcast(b)).select("variant", (F.col("checks") / F.col("_base")).alias("ratio"))


def neighbour_pairs(points: Points, prm: ClusterParams) -> DataFrame:
    """a, b: the smallest point ids of neighbouring cells both ways, from the method's tile index (N4, N8)."""
    found = run_tiles(deal(points.frame, plan_tiles(points, prm), points.dim, prm.eps, safe_reach(points.dim)), neighbour_tile, OUT, prm, points.dim, points.exact)
    return found.where("kind = 'pair'").select("a", "b")


def index_report(points: Points, prm: ClusterParams, methods: list[str], eps_list: list[float] | None = None) -> DataFrame:
    """variant, eps, bytes, seconds, pairs of the methods' indexes over all tiles: the neighbour step alone.

    seconds: to build the indexes and ask them for every own cell, summed over tiles;
    bytes: of all that queries read; pairs: cells found.
    """
    out = None
    for e, m in product(eps_list or [prm.eps], methods):
        p = prm.with_(eps=float(e), method=m)
        found = run_tiles(deal(points.frame, plan_tiles(points, p), points.dim, p.eps, safe_reach(points.dim)), index_tile, OUT, p, points.dim, points.exact)
        row = found.agg(F.sum("a").alias("bytes"), F.sum("v").alias("seconds"), F.sum("b").alias("pairs")).select(F.lit(m).alias("variant"), F.lit(float(e)).alias("eps"), "bytes", "seconds", "pairs")
        out = row if out is None else out.union(row)
    return out


def slab_stats(slabs: DataFrame) -> DataFrame:
    """dim, positions, bytes: rows and stored bytes of each dimension's bit table."""
    return slabs.groupBy("dim").agg(F.count_distinct("pos").alias("positions"), F.sum(F.length("bits").cast("long")).alias("bytes"))


def timed(run, repeats: int = 3, limit_s: float | None = None, spark: SparkSession | None = None) -> tuple[float, str]:
    """Mean seconds of ``repeats`` runs and 'ok'; or, once one takes more than ``limit_s``, the limit and 'censored'.

    A run beyond the limit is stopped: its Spark jobs, which go under a group of
    their own, are cancelled until it gives up.
    """
    took = []
    for _ in range(repeats):
        began = time.perf_counter()
        if limit_s is None:
            run()
        elif not _ended(run, limit_s, spark or SparkSession.getActiveSession()):
            return float(limit_s), "censored"
        took.append(time.perf_counter() - began)
    return sum(took) / len(took), "ok"


def _ended(run, limit_s: float, spark: SparkSession) -> bool:
    sc, group, done, late = spark.sparkContext, f"timed-{uuid.uuid4().hex}", threading.Event(), threading.Event()

    def watch() -> None:
        if not done.wait(limit_s):
            late.set()
            while not done.wait(0.2):
                sc.cancelJobGroup(group)

    before = sc.getLocalProperty("spark.jobGroup.id")
    sc.setJobGroup(group, "a timed run")
    guard = threading.Thread(target=watch, daemon=True)
    guard.start()
    try:
        run()
    except Exception:
        if not late.is_set():
            raise
    finally:
        done.set()
        guard.join()
        sc.setLocalProperty("spark.jobGroup.id", before)
        sc.setLocalProperty("spark.job.description", None)
    return not late.is_set()


def bench(points: Points, workload: str, prm: ClusterParams, methods: list[str], repeats: int = 3, limit_s: float | None = None) -> DataFrame:
    """Seconds of whole runs, a row for each method; 'censored' rows have the limit."""
    from densegrid.plans.engine import cluster

    spark, rows, n = points.frame.sparkSession, [], points.frame.count()
    for m in methods:
        s, status = timed(lambda m=m: cluster(points, prm.with_(method=m)).labels.write.format("noop").mode("overwrite").save(), repeats, limit_s, spark)
        rows.append((m, workload, n, points.dim, float(prm.eps), prm.min_pts, "seconds", s, status))
    return spark.createDataFrame(rows, METRIC)


def speedup(runs: DataFrame, base: str) -> DataFrame:
    """workload, n, d, variant, speedup, status: the base variant's seconds over each variant's.

    With a censored base the ratio is a lower bound ('at_least'); a censored variant has none.
    """
    keys = ["workload", "n", "d", "eps"]
    b = runs.where(F.col("variant") == base).select(*keys, F.col("value").alias("_base"), F.col("status").alias("_how"))
    ratio = F.when(F.col("status") == "ok", F.col("_base") / F.col("value"))
    how = F.when(F.col("status") != "ok", F.col("status")).when(F.col("_how") != "ok", "at_least").otherwise("ok")
    return runs.join(b, keys).select("workload", "n", "d", "variant", ratio.alias("speedup"), how.alias("status"))


def union_ablation(points: Points, prm: ClusterParams) -> DataFrame:
    """policy, compress, unions, hops: each way of keeping a forest, over the core cells' links of a run that makes every check.

    hops: parent pointers followed. At most ``driver_roots`` links are fetched, else it is refused.
    """
    from densegrid.plans.engine import merge_rows

    links = merge_rows(points, prm.with_(method="slab_full")).where("kind = 'link'").select("a", "b")
    if links.count() > prm.driver_roots:
        raise ValueError("too many links for one forest")
    table = links.orderBy("a", "b").toArrow()
    _, at = np.unique(np.concatenate([table.column(c).to_numpy() for c in "ab"]), return_inverse=True)
    pairs, rows = at.reshape(2, -1).T.tolist(), []
    for policy, compress in product(("naive", "by_size", "by_min_id"), (True, False)):
        forest = Forest(int(at.max()) + 1 if len(at) else 0, policy, compress)
        unions = sum(forest.union(a, b) for a, b in pairs + pairs[::-1])  # the second visit finds all roots equal
        rows.append((policy, compress, unions, forest.hops))
    return points.frame.sparkSession.createDataFrame(rows, "policy string, compress boolean, unions bigint, hops bigint")


def same_partition(a: DataFrame, b: DataFrame) -> DataFrame:
    """id of every point whose cluster or role differs between two label frames; none if they are equal."""
    return _beside(a, b).where(~F.col("same")).select("id")


def partition_report(a: DataFrame, b: DataFrame) -> DataFrame:
    """cluster_id, role, points, same: how many points of each cluster of ``a`` have the same cluster and role in ``b``."""
    return _beside(a, b).groupBy("cluster_id", "role").agg(F.count("*").alias("points"), F.count_if("same").alias("same"))


def _beside(a: DataFrame, b: DataFrame) -> DataFrame:
    y = b.toDF("id", "cluster_b", "role_b")
    return a.join(y, "id", "full").withColumn("same", F.col("cluster_id").eqNullSafe(F.col("cluster_b")) & F.col("role").eqNullSafe(F.col("role_b")))


def agreement(a: DataFrame, b: DataFrame) -> DataFrame:
    """Adjusted Rand index and pair precision and recall of labelling ``a`` against ``b``; noise is one class."""
    table = a.select("id", F.col("cluster_id").alias("p")).join(b.select("id", F.col("cluster_id").alias("q")), "id").groupBy("p", "q").count()

    def pairs(df: DataFrame, name: str) -> DataFrame:
        c = F.col("count").cast("double")
        return df.agg(F.coalesce(F.sum(c * (c - 1) / 2), F.lit(0.0)).alias(name))

    total = table.agg(F.coalesce(F.sum("count"), F.lit(0)).cast("double").alias("n"))
    by = lambda k: table.groupBy(k).agg(F.sum("count").alias("count"))
    row = pairs(table, "both").crossJoin(pairs(by("p"), "one")).crossJoin(pairs(by("q"), "other")).crossJoin(total)
    every = F.col("n") * (F.col("n") - 1) / 2
    chance = F.col("one") * F.col("other") / every
    top = (F.col("one") + F.col("other")) / 2
    return row.select(F.when(top == chance, 1.0).otherwise((F.col("both") - chance) / (top - chance)).alias("adjusted_rand"), F.try_divide("both", "one").alias("precision"), F.try_divide("both", "other").alias("recall"))


def dataset_stats(points: Points, labels: DataFrame | None = None) -> DataFrame:
    """n, d and, given labels, the number of clusters."""
    row = points.frame.agg(F.count("*").alias("n")).withColumn("d", F.lit(points.dim))
    if labels is None:
        return row
    return row.crossJoin(labels.where("cluster_id >= 0").agg(F.count_distinct("cluster_id").alias("clusters")))


def scalability_grid(workloads: dict[str, tuple[Points, ClusterParams]], methods: list[str], repeats: int = 1, limit_s: float | None = None) -> DataFrame:
    """Seconds for every workload (a size in a dimension) and method."""
    out = None
    for name, (points, prm) in workloads.items():
        rows = bench(points, name, prm, methods, repeats, limit_s)
        out = rows if out is None else out.union(rows)
    return out

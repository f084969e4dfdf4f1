"""Clustering end to end: every method of the paper's comparison, one result."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, functions as F

from densegrid.functions.geometry import safe_reach
from densegrid.operators import relational
from densegrid.operators.components import forest_roots
from densegrid.operators.tiles import OUT, TilePlan, count_tile, deal, label_tile, merge_tile, named, part_hot, plan_tiles, run_tiles, share_wide
from densegrid.params import ClusterParams
from densegrid.plans.lineage import cut
from densegrid.sources.points import Points, fold_duplicates

NOISE = -1
#: Points a place, from which on places are clustered.
FOLD = 2
#: Rows of a tile, from which on several tasks may share it, each with cells of its own.
WIDE = 8_000


@dataclass(frozen=True)
class ClusterResult:
    """labels: id, cluster_id, role. core: id, coord, cluster_id of core points. counts: one row of merge counts."""

    labels: DataFrame
    core: DataFrame
    counts: DataFrame


def cluster(points: Points, prm: ClusterParams) -> ClusterResult:
    """Exact density clusters (with ``grid_approx``, approximate ones) of the points.

    A cluster's id is the smallest id of its core points; noise has -1. Repeated
    coordinates are legal; repeated ids are the caller's to avoid. An empty input
    gives an empty result.
    """
    if prm.fold:
        return _folded(points, prm.with_(fold=False))
    if prm.method == "brute":
        return relational.cluster_brute(points, prm)
    if "weight" not in points.frame.columns:  # read again and again below: features are worked out once
        points = points.with_frame(cut(_spread(points.frame)))
    if _repeats(points, prm):
        return _folded(points, prm)
    plan = plan_tiles(points, prm.with_(tile_points=1 << 60) if prm.method == "bucket_pruned" else prm)
    if plan.points == 0:
        return ClusterResult(_labels(points.frame.select("id", F.lit(-1).cast("long").alias("cluster_id"), F.lit("noise").alias("role"))), points.frame.withColumn("cluster_id", F.lit(-1).cast("long")), _counts(points.frame.select(F.lit("counts").alias("kind"), F.col("id").alias("a"), F.col("id").alias("b"))))
    flagged, found = relational.bucket_passes(points, prm) if prm.method == "bucket_pruned" else _passes(points, prm, plan)
    if prm.method == "reference":
        found = cut(named(found))
    roots = forest_roots(found.where("kind = 'link'").select("a", "b"), prm.driver_roots)
    names = found.where("kind = 'name'").select(F.col("a").alias("id"), F.col("b").alias("name"))
    core = names.join(roots, names["name"] == roots["node"], "left").select("id", F.coalesce("root", "name").alias("cluster_id"))
    touch = found.where("kind = 'touch'").join(roots, F.col("b") == F.col("node"), "left").select(F.col("a").alias("id"), F.coalesce("root", "b").alias("cluster_id"), F.col("v").alias("dist2"), F.col("b").alias("name"))
    labels = assign_roles(points.frame.select("id"), core, touch, prm.border_rule)
    return ClusterResult(labels, core.join(flagged.where("core").select("id", "coord"), "id"), _counts(found))


def _spread(frame: DataFrame) -> DataFrame:
    """The rows over at least as many partitions as there are cores: a table in one small file is read by one task."""
    cores = frame.sparkSession.sparkContext.defaultParallelism
    return frame.repartition(2 * cores, "id") if frame.rdd.getNumPartitions() < cores else frame


def _repeats(points: Points, prm: ClusterParams) -> bool:
    """Whether the points have so few places, by an estimate, that these are worth clustering in their stead."""
    if "weight" in points.frame.columns:
        return False
    n, places = points.frame.agg(F.count("*"), F.approx_count_distinct(F.xxhash64("coord"))).first()
    return n > prm.tile_points and places * FOLD <= n


def _folded(points: Points, prm: ClusterParams) -> ClusterResult:
    """Each distinct place once, with its weight and smallest id; every point then takes its place's label.

    For all methods but ``brute``: their counts add up weights.
    """
    if prm.method == "brute":
        raise ValueError(f"{prm.method} counts points one by one")
    places = cut(fold_duplicates(points))
    r = cluster(points.with_frame(places.select("id", "coord", "weight")), prm)
    at = points.frame.select(F.col("id").alias("own"), "coord").join(places.select("coord", "id"), "coord").select("own", "id", "coord")
    labels = at.join(r.labels, "id").select(F.col("own").alias("id"), "cluster_id", "role")
    core = at.join(r.core.select("id", "cluster_id"), "id").select(F.col("own").alias("id"), "cluster_id", "coord")
    return ClusterResult(labels, core, r.counts)


def merge_rows(points: Points, prm: ClusterParams) -> DataFrame:
    """What the tiles find: kind, a, b, v (``tiles.merge_tile``)."""
    return _passes(points, prm, plan_tiles(points, prm))[1]


def _passes(points: Points, prm: ClusterParams, plan: TilePlan) -> tuple[DataFrame, DataFrame]:
    """Points with their core flags, and the rows of the merging pass.

    A tile that holds more rows than a task should is dealt to several: its rows go
    into groups by their ids, and each two groups meet in a task of their own. Where a
    few tiles hold most of the rows, tasks share these, with all rows but cells of their
    own. Other tiles are left as they are.
    """
    d, exact, halo, limit = points.dim, points.exact, safe_reach(points.dim), prm.rows_limit(points.dim)
    kind = "bigint" if exact else "double"
    labelled = f"id long, coord array<{kind}>, core boolean"
    dealt, hot, wide = deal(points.frame, plan, d, prm.eps, halo), None, {}
    if plan.largest > limit // 2:  # the estimate is near the limit: count; there are at most rows / limit such tiles
        over = dealt.groupBy("tile").count().where(F.col("count") > limit).select("tile", F.ceil(2 * F.col("count") / limit).cast("long").alias("groups")).collect()
        hot = {r["tile"]: r["groups"] for r in over}
    elif plan.largest > WIDE:
        wide = _wide(dealt, prm)
    if wide:
        split = ["tile", "part"]
        flagged = cut(run_tiles(share_wide(dealt, wide, d, prm.eps), label_tile, labelled, prm, d, exact, split))
        return flagged, cut(run_tiles(share_wide(deal(flagged, plan, d, prm.eps, halo), wide, d, prm.eps), merge_tile, OUT, prm, d, exact, split))
    if not hot:
        flagged = cut(run_tiles(dealt, label_tile, labelled, prm, d, exact))
        return flagged, cut(run_tiles(deal(flagged, plan, d, prm.eps, halo), merge_tile, OUT, prm, d, exact))
    calm, parted = part_hot(dealt, hot)
    partial = run_tiles(parted, count_tile, f"id long, coord array<{kind}>, n long", prm, d, exact, ["tile", "low", "high"])
    summed = partial.groupBy("id").agg(F.max("coord").alias("coord"), (F.sum("n") >= prm.min_pts).alias("core"))
    flagged = cut(run_tiles(calm, label_tile, labelled, prm, d, exact).unionByName(summed))
    calm, parted = part_hot(deal(flagged, plan, d, prm.eps, halo), hot)
    return flagged, cut(run_tiles(calm, merge_tile, OUT, prm, d, exact).unionByName(run_tiles(parted, merge_tile, OUT, prm, d, exact, ["tile", "low", "high"])))


def _wide(dealt: DataFrame, prm: ClusterParams) -> dict[int, int]:
    """By how many tasks each wide tile is shared, so that all cores are busy where few tiles hold most of the work.

    Work goes by the square of a tile's rows. A tile is shared as its part of the work
    is more than half a core's; every task holds all its rows.
    """
    rows = {r["tile"]: r["count"] for r in dealt.groupBy("tile").count().where(F.col("count") > WIDE).collect()}
    work, cores = sum(n * n for n in rows.values()), 2 * dealt.sparkSession.sparkContext.defaultParallelism
    shared = {t: min(-(-n // (WIDE // 4)), -(-n * n * cores // work)) for t, n in rows.items()}
    return {t: k for t, k in shared.items() if k > 1}


def assign_roles(ids: DataFrame, core: DataFrame, touch: DataFrame, border_rule: str) -> DataFrame:
    """id, cluster_id, role from core (id, cluster_id) and touch (id, cluster_id, dist2): steps B1 to B4."""
    if border_rule == "all":
        border = touch.select("id", "cluster_id").distinct()
    elif border_rule == "nearest_core":
        border = touch.groupBy("id").agg(F.min(F.struct("dist2", "cluster_id")).alias("m")).select("id", F.col("m.cluster_id").alias("cluster_id"))
    else:
        border = touch.groupBy("id").agg(F.min("cluster_id").alias("cluster_id"))
    known = core.select("id", "cluster_id", F.lit("core").alias("role")).unionByName(border.select("id", "cluster_id", F.lit("border").alias("role")))
    return _labels(ids.join(known, "id", "left").select("id", F.coalesce("cluster_id", F.lit(NOISE)).alias("cluster_id"), F.coalesce("role", F.lit("noise")).alias("role")))


def _labels(df: DataFrame) -> DataFrame:
    return df.select(F.col("id").cast("long").alias("id"), F.col("cluster_id").cast("long").alias("cluster_id"), "role")


COUNTS = ("considered", "skipped", "boxed", "checks", "unions", "core_cells")


def _counts(found: DataFrame) -> DataFrame:
    n = [F.coalesce(F.sum(F.when(F.col("a") == k, F.col("b"))), F.lit(0)).alias(c) for k, c in enumerate(COUNTS)]
    return found.where("kind = 'counts'").agg(*n)

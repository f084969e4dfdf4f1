"""Reports on clusters, parameter help and assignment of new points."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window, functions as F

from densegrid.operators.relational import eps_neighbours
from densegrid.params import ClusterParams
from densegrid.plans.lineage import cut
from densegrid.sources.points import Points, fold_duplicates


def cluster_profile(labels: DataFrame, points: Points) -> DataFrame:
    """cluster_id, size, core, border, centre sums and bounding box of every cluster."""
    d = points.dim
    at = [f(F.col("coord")[i]).alias(f"{s}{i}") for s, f in (("sum", F.sum), ("lo", F.min), ("hi", F.max)) for i in range(d)]
    rows = labels.join(points.frame, "id").groupBy("cluster_id").agg(F.count("*").alias("size"), F.count_if(F.col("role") == "core").alias("core"), F.count_if(F.col("role") == "border").alias("border"), *at)
    arrays = [F.array(*[F.col(f"{s}{i}") for i in range(d)]).alias(s) for s in ("sum", "lo", "hi")]
    return rows.select("cluster_id", "size", "core", "border", *arrays)


def k_distance(points: Points, k: int, radius: float) -> DataFrame:
    """id, dist2 to the k-th nearest point, itself the first; none where there are fewer than k points.

    Points with fewer than k within ``radius`` are asked again with twice the radius,
    until each has its k: ``radius`` only decides how much work that is.
    """
    every, out = points.frame, None
    if every.limit(k).count() < k:
        return every.select("id", F.lit(None).cast("bigint" if points.exact else "double").alias("dist2")).limit(0)
    open_ = points
    while True:
        near = eps_neighbours(open_, ClusterParams(radius, 1), others=every)
        turn = F.row_number().over(Window.partitionBy("id").orderBy("dist2", "nbr_id"))
        found = cut(near.withColumn("turn", turn).where(F.col("turn") == k).select("id", "dist2"))
        out = found if out is None else out.unionByName(found)
        left = cut(open_.frame.join(found.select("id"), "id", "left_anti"))
        if left.isEmpty():
            return out
        open_, radius = points.with_frame(left.select("id", "coord")), radius * 2


def latest_before(events: DataFrame, marks: DataFrame, key: str, time: str, value: str) -> DataFrame:
    """``events`` with the latest ``value`` that ``marks`` (key, time, value) has for its key at its time or before: an as-of join.

    Both sides go through one sort by key and time, so no two rows are paired; null
    where nothing is early enough. Of marks at one time the largest value counts.
    """
    left = events.withColumn("_turn", F.lit(1)).withColumn("_value", F.lit(None).cast(dict(marks.dtypes)[value]))
    right = marks.groupBy(key, time).agg(F.max(value).alias("_value")).withColumn("_turn", F.lit(0))
    past = Window.partitionBy(key).orderBy(time, "_turn").rowsBetween(Window.unboundedPreceding, 0)
    seen = left.unionByName(right, allowMissingColumns=True).withColumn(value, F.last("_value", ignorenulls=True).over(past))
    return seen.where("_turn = 1").select(*events.columns, value)


def suggest_eps(points: Points, min_pts: int, radius: float, quantiles: tuple[float, ...] = (0.5, 0.75, 0.9, 0.95)) -> DataFrame:
    """quantile, eps: quantiles of the distance to the min_pts-th nearest point."""
    at = k_distance(points, min_pts, radius).agg(F.percentile_approx(F.sqrt(F.col("dist2").cast("double")), list(quantiles), 10_000).alias("e"))
    return at.select(F.explode(F.arrays_zip(F.array(*[F.lit(q) for q in quantiles]).alias("quantile"), F.col("e").alias("eps"))).alias("s")).select("s.quantile", "s.eps")


def assign_new(core: DataFrame, new: Points, prm: ClusterParams) -> DataFrame:
    """id, cluster_id for unseen points: that of the nearest core point within eps (ties: smallest cluster), else -1.

    ``core``: id, coord, cluster_id of a model's core points.
    """
    kinds = core.groupBy("coord").agg(F.min("id").alias("id"), F.min("cluster_id").alias("cluster_id"))
    places = cut(fold_duplicates(new))  # repeated places are asked once
    pairs = eps_neighbours(new.with_frame(places.select("id", "coord")), prm, others=(kinds := cut(kinds)).select("id", "coord"))
    best = pairs.join(kinds.select(F.col("id").alias("nbr_id"), "cluster_id").hint("merge"), "nbr_id").groupBy("id").agg(F.min(F.struct("dist2", "cluster_id")).alias("m"))
    found = places.select("id", "coord").join(best.hint("merge"), "id", "left").select("coord", F.coalesce("m.cluster_id", F.lit(-1)).cast("long").alias("cluster_id"))
    return new.frame.join(found.hint("merge"), "coord").select("id", "cluster_id")

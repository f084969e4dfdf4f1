"""Clusters kept up to date while points are added: insertions only ever merge."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from densegrid.operators.components import forest_roots
from densegrid.operators.relational import eps_neighbours
from densegrid.params import ClusterParams
from densegrid.plans.lineage import cut
from densegrid.sources.points import Points

STATE = "id bigint, coord array<{kind}>, n bigint, root bigint"


def empty_state(new: Points) -> DataFrame:
    """No points: id, coord, n (points within eps, itself included) and root (a core point's cluster, else null)."""
    return new.frame.sparkSession.createDataFrame([], STATE.format(kind="bigint" if new.exact else "double"))


def insert_points(state: DataFrame, new: Points, prm: ClusterParams) -> DataFrame:
    """The state with the points of ``new`` (of ids that it hasn't) added, written to shared files.

    Repeated coordinates are counted and linked once, by the number of their points.
    Only neighbours of new points gain counts, only points that become core bring
    links, and those join clusters by their names; a cluster is never taken apart.
    """
    fresh = new.frame.select("id", "coord", F.lit(None).cast("long").alias("n"), F.lit(None).cast("long").alias("root"))
    every = cut(state.unionByName(fresh))  # n is null for new points until the places are counted
    places = cut(every.groupBy("coord").agg(F.min("id").alias("id"), F.count_if(F.col("n").isNull()).alias("gain"), F.count("*").alias("size"), F.max("n").alias("n"), F.max("root").alias("root"), F.min(F.when(F.col("root").isNull(), F.col("id"))).alias("loose")))
    at = new.with_frame(places.where("gain > 0").select("id", "coord"))
    met = cut(eps_neighbours(at, prm, others=places.select("id", "coord")).select("id", "nbr_id"))
    side = places.select(F.col("id").alias("nbr_id"), "size")
    own = met.join(side, "nbr_id").groupBy("id").agg(F.sum("size").alias("whole"))
    old = met.join(places.select("id", "gain"), "id").groupBy(F.col("nbr_id").alias("id")).agg(F.sum("gain").alias("more"))
    counted = cut(places.join(own, "id", "left").join(old, "id", "left").withColumn("n", F.coalesce("whole", F.col("n") + F.coalesce("more", F.lit(0)))).select("id", "coord", "n", "root", "loose"))
    core = counted.where(F.col("n") >= prm.min_pts)
    turned = cut(core.where("loose IS NOT NULL").select(F.col("loose").alias("id"), "coord"))
    names = core.select(F.col("id").alias("nbr_id"), F.coalesce("root", "loose").alias("b"))
    links = cut(eps_neighbours(new.with_frame(turned), prm, others=core.select("id", "coord")).join(names, "nbr_id").select(F.col("id").alias("a"), "b"))
    roots = forest_roots(links, prm.driver_roots)
    named = counted.withColumn("name", F.when(F.col("n") >= prm.min_pts, F.coalesce("root", "loose"))).drop("root")
    named = named.join(roots, named["name"] == roots["node"], "left").select("coord", "n", F.coalesce("root", "name").alias("root"))
    return cut(every.select("id", "coord").join(named, "coord").select("id", "coord", "n", "root"))


def state_labels(state: DataFrame, new: Points, prm: ClusterParams) -> DataFrame:
    """id, cluster_id, role of a state, by the prm's border rule; ``new`` only says what kind of points they are."""
    from densegrid.plans.engine import assign_roles

    places = cut(state.groupBy("coord").agg(F.min("id").alias("id"), F.max("root").alias("cluster_id")))
    core = places.where("cluster_id IS NOT NULL")
    loose = new.with_frame(places.where("cluster_id IS NULL").select("id", "coord"))
    touch = eps_neighbours(loose, prm, others=core.select("id", "coord")).join(core.select(F.col("id").alias("nbr_id"), "cluster_id"), "nbr_id").select("id", "cluster_id", "dist2")
    found = assign_roles(places.select("id"), core.select("id", "cluster_id"), touch, prm.border_rule).join(places.select("id", "coord"), "id").select("coord", "cluster_id", "role")
    return state.select("id", "coord").join(found, "coord").select("id", "cluster_id", "role")

"""The definitions as joins, brute force, and the bucket-join method (E7, E8)."""

from __future__ import annotations

import math
from itertools import product

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F

from densegrid.functions.geometry import cell_scale, dist2, eps2, safe_reach
from densegrid.operators.components import components, forest_roots
from densegrid.operators.tiles import OUT, count_tile, merge_tile, run_tiles, sampled_cells
from densegrid.params import ClusterParams
from densegrid.plans.lineage import cut
from densegrid.sources.points import Points, fold_duplicates


def eps_neighbours(points: Points, prm: ClusterParams, m: int = 3, others: DataFrame | None = None) -> DataFrame:
    """id, nbr_id, dist2 of all pairs within the closed ball, each point with itself: an equi-join on buckets.

    Buckets of side eps over the first ``m`` dimensions; one side goes to the adjacent ones too.
    """
    dims = range(min(m, points.dim))
    key = [F.floor(F.col("coord")[i].cast("double") / prm.eps).alias(f"b{i}") for i in dims]
    left = points.frame.select("id", "coord", *key)
    for i in dims:
        left = left.withColumn(f"b{i}", F.explode(F.sequence(F.col(f"b{i}") - 1, F.col(f"b{i}") + 1)))
    right = (points.frame if others is None else others).select(F.col("id").alias("nbr_id"), F.col("coord").alias("nbr_coord"), *key)
    pairs = left.join(right, [f"b{i}" for i in dims]).withColumn("dist2", dist2(F.col("coord"), F.col("nbr_coord"), points.exact))
    return pairs.where(F.col("dist2") <= eps2(prm.eps, points.exact)).select("id", "nbr_id", "dist2")


def core_points(points: Points, prm: ClusterParams) -> DataFrame:
    """id of every point with at least min_pts neighbours."""
    return eps_neighbours(points, prm).groupBy("id").agg(F.count("*").alias("n")).where(F.col("n") >= prm.min_pts).select("id")


def direct_reach(points: Points, prm: ClusterParams) -> DataFrame:
    """core_id, id: the points directly density-reachable from each core point."""
    pairs = eps_neighbours(points, prm).select(F.col("id").alias("core_id"), F.col("nbr_id").alias("id"))
    return pairs.join(core_points(points, prm).withColumnRenamed("id", "core_id"), "core_id", "left_semi")


def reachable_from(points: Points, prm: ClusterParams, start: int, max_steps: int = 1000) -> DataFrame:
    """id of every point density-reachable from ``start`` (itself too, if core): a breadth-first iteration."""
    spark = points.frame.sparkSession
    step = cut(direct_reach(points, prm))
    seen = spark.createDataFrame([(start,)], "id bigint")
    size = 0
    reached = None
    for _ in range(max_steps):
        hop = step.join(seen.withColumnRenamed("id", "core_id"), "core_id", "left_semi").select("id").distinct()
        reached = cut(hop if reached is None else hop.union(reached).distinct())
        now = reached.count()
        if now == size:
            break
        size, seen = now, reached
    return reached


def density_connected(points: Points, prm: ClusterParams, pairs: DataFrame) -> DataFrame:
    """a, b, connected for each of the ``pairs`` (a, b) of ids: whether some point reaches both.

    Both then lie in one cluster, borders in any of theirs; the clusters come from
    the flagship, and noise is connected to nothing.
    """
    from densegrid.plans.engine import cluster

    labels = cut(cluster(points, prm.with_(border_rule="all")).labels.where("cluster_id >= 0").select("id", "cluster_id"))
    side = lambda s: labels.select(F.col("id").alias(s), "cluster_id")
    shared = pairs.join(side("a"), "a").join(side("b"), ["b", "cluster_id"]).select("a", "b", F.lit(True).alias("connected")).distinct()
    return pairs.join(shared, ["a", "b"], "left").select("a", "b", F.coalesce("connected", F.lit(False)).alias("connected"))


def axiom_report(points: Points, labels: DataFrame, prm: ClusterParams) -> DataFrame:
    """cluster_id, due, held, components: how many points its core points reach (as pairs), how many of those it
    holds, and how many components its core points fall into. A right clustering holds all that is due, in one."""
    places = cut(fold_duplicates(points))
    near = cut(eps_neighbours(points.with_frame(places.select("id", "coord")), prm).select(F.col("id").alias("p"), F.col("nbr_id").alias("q")))
    size = places.select(F.col("id").alias("q"), F.col("weight").alias("size"))
    dense = near.join(size, "q").groupBy("p").agg(F.sum("size").alias("n")).where(F.col("n") >= prm.min_pts).select("p")
    reach_ = cut(near.join(dense, "p", "left_semi"))
    at = points.frame.join(places.select("coord", F.col("id").alias("q")), "coord").select("id", "q")
    held = cut(labels.where("cluster_id <> -1").join(at, "id").groupBy("q", "cluster_id").agg(F.count("*").alias("inside"), F.count_if(F.col("role") == "core").alias("cores")))
    cores = held.where("cores > 0").select(F.col("q").alias("p"), "cluster_id", "cores")
    pairs = reach_.join(cores, "p").join(size, "q").join(held.select("q", "cluster_id", "inside"), ["q", "cluster_id"], "left")
    due = pairs.groupBy("cluster_id").agg(F.sum(F.col("cores") * F.col("size")).alias("due"), F.sum(F.col("cores") * F.coalesce("inside", F.lit(0))).alias("held"))
    links = reach_.join(cores.select(F.col("p").alias("q")).distinct(), "q", "left_semi").select(F.col("p").alias("a"), F.col("q").alias("b"))
    roots = components(links)
    one = cores.join(roots, cores["p"] == roots["node"]).groupBy("cluster_id").agg(F.count_distinct("root").alias("components"))
    return due.join(one, "cluster_id").select("cluster_id", "due", "held", "components")


def check_axioms(points: Points, labels: DataFrame, prm: ClusterParams) -> DataFrame:
    """Violations of maximality and of connectivity, as (axiom, id): none for a right clustering under ``all``."""
    reach_ = direct_reach(points, prm)
    held = labels.where("cluster_id <> -1")
    from_core = reach_.join(held.select(F.col("id").alias("core_id"), "cluster_id"), "core_id")
    missing = from_core.join(held.select("id", "cluster_id"), ["id", "cluster_id"], "left_anti").select(F.lit("maximality").alias("axiom"), "id")
    core = core_points(points, prm)
    links = reach_.join(core, "id", "left_semi").select(F.col("core_id").alias("a"), F.col("id").alias("b"))
    roots = components(links)
    split = held.join(roots, held["id"] == roots["node"]).groupBy("cluster_id").agg(F.count_distinct("root").alias("n"), F.min("id").alias("id")).where("n > 1")
    stray = held.where("role = 'border'").join(from_core.select("id", "cluster_id"), ["id", "cluster_id"], "left_anti")
    return missing.unionByName(split.select(F.lit("connectivity").alias("axiom"), "id")).unionByName(stray.select(F.lit("connectivity").alias("axiom"), "id"))


def noise_points(labels: DataFrame) -> DataFrame:
    return labels.where("cluster_id = -1").select("id")


def contrast_kmeans(points: Points, k: int, iterations: int = 20, seed: int = 1) -> DataFrame:
    """id, cluster_id of k-means: ball-shaped clusters, for contrast."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    rows = points.frame.select("id", array_to_vector(F.col("coord").cast("array<double>")).alias("features"))
    model = KMeans(k=k, maxIter=iterations, seed=seed).fit(rows)
    return model.transform(rows).select("id", F.col("prediction").cast("long").alias("cluster_id"))


def _result(points: Points, core: DataFrame, links: DataFrame, touch: DataFrame, prm: ClusterParams, counts: DataFrame):
    """Components of ``links`` (a, b) over core points, then roles; touch: id, core_id, dist2."""
    from densegrid.plans.engine import ClusterResult, assign_roles

    roots = forest_roots(links, prm.driver_roots)
    named = cut(core.join(roots, core["id"] == roots["node"], "left").select("id", F.coalesce("root", "id").alias("cluster_id")))
    near = touch.join(named.select(F.col("id").alias("core_id"), "cluster_id"), "core_id").select("id", "cluster_id", "dist2")
    labels = assign_roles(points.frame.select("id"), named, near, prm.border_rule)
    return ClusterResult(labels, named.join(points.frame, "id"), counts)


def _counts_row(spark: SparkSession, *n: int) -> DataFrame:
    from densegrid.plans.engine import COUNTS

    return spark.createDataFrame([tuple(int(x) for x in n)], ", ".join(f"{c} bigint" for c in COUNTS))


def all_pairs(places: DataFrame, prm: ClusterParams, d: int, exact: bool, block: int = 4096) -> DataFrame:
    """a, b, weight, dist2 of all pairs within the closed ball, each place with itself; weight: of b.

    Places (id, coord, weight) go into groups by their ids, and each two groups meet
    in a task, all against all.
    """
    n = max(1, -(-places.count() // block))
    group = F.pmod(F.xxhash64("id"), F.lit(n))
    rows = places.withColumn("grp", group).withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(n - 1).cast("long"))))
    rows = rows.select("id", "coord", "weight", "grp", F.least("grp", "other").alias("low"), F.greatest("grp", "other").alias("high"))
    limit = eps2(prm.eps, exact)

    def met(table: pa.Table) -> pa.Table:
        x = np.asarray(table.column("coord").combine_chunks().flatten().to_numpy(zero_copy_only=False)).reshape(-1, d)
        ids, weight, grp = (table.column(c).to_numpy() for c in ("id", "weight", "grp"))
        low, high = np.flatnonzero(grp == grp.min()), np.flatnonzero(grp == grp.max())
        crossed, out = table.column("low")[0].as_py() != table.column("high")[0].as_py(), []
        if crossed and grp.min() == grp.max():
            low = low[:0]
        for at in range(0, len(low), 256):
            part = low[at : at + 256]
            dd = np.zeros((len(part), len(high)), x.dtype)
            for k in range(d):
                diff = x[part, k][:, None] - x[high, k][None, :]
                dd += diff * diff
            i, j = np.nonzero(dd <= limit)
            one, two, v = part[i], high[j], dd[i, j]
            out.append((ids[one], ids[two], weight[two], v))
            if crossed:
                out.append((ids[two], ids[one], weight[one], v))
        a, b, w, v = (np.concatenate(z) for z in zip(*out, strict=True)) if out else (ids[:0], ids[:0], weight[:0], x[:0, 0])
        return pa.table({"a": a, "b": b, "weight": w, "dist2": v})

    return rows.groupBy("low", "high").applyInArrow(lambda table: met(table), f"a long, b long, weight long, dist2 {'long' if exact else 'double'}")


def cluster_brute(points: Points, prm: ClusterParams):
    """By definition, all places against all, each with the number of its points."""
    places = cut(fold_duplicates(points))
    pairs = cut(all_pairs(places.select("id", "coord", "weight"), prm, points.dim, points.exact))
    core = cut(pairs.groupBy(F.col("a").alias("id")).agg(F.sum("weight").alias("n")).where(F.col("n") >= prm.min_pts).select("id"))
    held = pairs.join(core.select(F.col("id").alias("b")), "b", "left_semi")
    links = held.join(core.select(F.col("id").alias("a")), "a", "left_semi").select("a", "b")
    touch = held.join(core.select(F.col("id").alias("a")), "a", "left_anti").select(F.col("a").alias("id"), F.col("b").alias("core_id"), "dist2")
    found = _result(points.with_frame(places.select("id", "coord")), core, links, touch, prm, _counts_row(points.frame.sparkSession, 0, 0, 0, 0, 0, 0))
    at = points.frame.select(F.col("id").alias("own"), "coord").join(places.select("coord", "id"), "coord")
    labels = at.select("own", "id").join(found.labels, "id").select(F.col("own").alias("id"), "cluster_id", "role")
    core = at.join(found.core.select("id", "cluster_id"), "id").select(F.col("own").alias("id"), "cluster_id", "coord")
    return type(found)(labels, core, found.counts)


#: Rows of a block, at most and at least; a bucket of more is dealt to several blocks by ids.
BUCKET_ROWS, LEAST_ROWS = 4_096, 512


def bucket_blocks(points: Points, prm: ClusterParams, m: int = 2):
    """A function that deals rows (with id, coord) to the tasks of a bucket join, and the number of tasks.

    Buckets are coarse keys of the cells over the ``m`` dimensions with most positions (in a sample),
    at least as wide as a cell's reach and wide enough to hold some thousand rows; those
    with more are parted into blocks by ids. Each two blocks of the same or of adjacent
    buckets meet in a task of their own (``low``, ``high``; ``grp``: the row's block), a
    block also itself. The driver holds the buckets' numbers of rows: a number for each
    few thousand rows.
    """
    d, spark = points.dim, points.frame.sparkSession
    scale = F.lit(cell_scale(d, prm.eps))
    at = [F.floor(F.col("coord")[i].cast("double") * scale) for i in range(d)]
    n = points.frame.count()
    spread = [len(np.unique(c)) for c in sampled_cells(points, prm, n).T]
    dims = sorted(range(d), key=lambda i: -spread[i])[: min(m, d)]
    rows = max(LEAST_ROWS, min(BUCKET_ROWS, n // (2 * spark.sparkContext.defaultParallelism)))
    wide = max(safe_reach(d) + 1, math.ceil((math.prod(spread[i] for i in dims) * rows / max(1, n)) ** (1 / len(dims))))
    key = [F.floor(at[i] / wide).alias(f"b{k}") for k, i in enumerate(dims)]
    names = [f"b{k}" for k in range(len(dims))]
    found = {tuple(r[k] for k in names): r["n"] for r in points.frame.select(*key).groupBy(*names).agg(F.count("*").alias("n")).collect()}
    groups = {k: -(-size // rows) for k, size in found.items()}
    start = dict(zip(groups, np.cumsum([0, *groups.values()]).tolist()))
    near = {k: [o for s in product((-1, 0, 1), repeat=len(k)) if (o := tuple(x + y for x, y in zip(k, s, strict=True))) in groups] for k in groups}
    tasks = sum(groups[k] * sum(groups[o] for o in near[k]) for k in groups) // 2 + sum(groups.values())
    schema = ", ".join([*(f"{k} bigint" for k in names), "start bigint", "groups bigint", "near array<struct<low:bigint,high:bigint>>"])
    table = spark.createDataFrame([(*k, start[k], groups[k], [(start[o], start[o] + groups[o] - 1) for o in near[k]]) for k in groups], schema)

    def deal(frame: DataFrame) -> DataFrame:
        own = frame.select(*frame.columns, *key).join(F.broadcast(table), names)
        own = own.withColumn("grp", F.col("start") + F.pmod(F.xxhash64(F.lit("block"), "id"), F.col("groups")))
        other = F.explode(F.flatten(F.transform("near", lambda s: F.sequence(s["low"], s["high"]))))
        dealt = own.select(*frame.columns, "grp", other.alias("other"))
        return dealt.select(*frame.columns, F.lit(True).alias("own"), "grp", F.least("grp", "other").alias("low"), F.greatest("grp", "other").alias("high"))

    return deal, tasks


def bucket_passes(points: Points, prm: ClusterParams) -> tuple[DataFrame, DataFrame]:
    """Points with their core flags, and what merging finds (``tiles.merge_tile``), by a join of cells on bucket keys.

    No task holds more than two blocks of rows. Merging goes in two pruned rounds: the
    first within each block, the second across two blocks, where cells that the first
    has brought into one tree are not checked. A cell that several blocks share counts
    in each.
    """
    d, exact, by = points.dim, points.exact, ["low", "high"]
    kind = "bigint" if exact else "double"
    deal, tasks = bucket_blocks(points, prm)
    # A number of its own, so that tasks are not put together by their bytes: their work is larger than these tell.
    parts = max(1, min(tasks, 2048, max(8 * points.frame.sparkSession.sparkContext.defaultParallelism, tasks // 16)))

    def run(dealt: DataFrame, kernel, schema: str) -> DataFrame:
        return run_tiles(dealt.repartition(parts, *by), kernel, schema, prm, d, exact, by)

    met = run(deal(points.frame), count_tile, f"id long, coord array<{kind}>, n long")
    flagged = cut(met.groupBy("id").agg(F.max("coord").alias("coord"), (F.sum("n") >= prm.min_pts).alias("core")))
    first = cut(run(deal(flagged).where("low = high"), merge_tile, OUT))
    roots = forest_roots(first.where("kind = 'link'").select("a", "b"), prm.driver_roots)
    names = first.where("kind = 'name'").select(F.col("a").alias("id"), F.col("b").alias("name"))
    seeds = names.join(roots, names["name"] == roots["node"], "left").select("id", F.coalesce("root", "name").alias("seed"))
    second = cut(run(deal(flagged.join(seeds, "id", "left")).where("low < high"), merge_tile, OUT))
    return flagged, first.unionByName(second)

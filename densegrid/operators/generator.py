"""The drift-cluster generator."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window, functions as F

from densegrid.sources.points import Points


def _uniform(*parts: Column | int) -> Column:
    """A value in [0, 1) drawn from the parts alone, the same whatever the partitioning."""
    cols = [F.lit(p) if isinstance(p, int) else p for p in parts]
    return F.pmod(F.xxhash64(*cols), F.lit(1 << 40)) / float(1 << 40)


def drift_clusters(spark: SparkSession, n: int | None, c: int, d: int, noise: float = 5e-6, lo: int = 1000, hi: int = 10000, scatter: int = 30, seed: int = 1, ids: DataFrame | None = None) -> tuple[Points, DataFrame]:
    """Points in whole numbers, and (id, truth): the cluster of each, -1 for noise.

    Each cluster begins at a uniform place; after every 0.00025 n objects of the
    data set its centre moves by -5, 0 or +5 in each dimension (33, 34 and 33 %).
    Objects lie uniformly within ``scatter`` of their centre. round(noise * n)
    objects, spread evenly over the ids, are uniform over the whole range. Ids
    run from 0 to n-1; given ``ids`` (id, from 0 on), only those, as they are among as
    many as the largest needs (n is not asked for).
    """
    if ids is not None:
        n = ids.agg(F.coalesce(F.max("id"), F.lit(-1))).first()[0] + 1
    every = max(1, round(0.00025 * n))
    walk = spark.range(c).withColumnRenamed("id", "k").crossJoin(spark.range(d).withColumnRenamed("id", "dim")).crossJoin(spark.range(-(-n // every) + 1).withColumnRenamed("id", "step"))
    draw = _uniform(F.lit("move"), F.col("k"), F.col("dim"), F.col("step"), seed)
    move = F.when(F.col("step") == 0, 0).when(draw < 0.33, -5).when(draw < 0.66, 5).otherwise(0)
    start = lo + F.floor(_uniform(F.lit("seed"), F.col("k"), F.col("dim"), seed) * (hi - lo))
    path = Window.partitionBy("k", "dim").orderBy("step").rowsBetween(Window.unboundedPreceding, 0)
    centres = walk.withColumn("at", start + F.sum(move).over(path)).groupBy("k", "step").agg(F.transform(F.array_sort(F.collect_list(F.struct("dim", "at"))), lambda s: s["at"]).alias("centre"))
    quiet = round(noise * n)
    gap = n // quiet if quiet else n + 1
    rows = (spark.range(n) if ids is None else ids).withColumn("k", F.when((F.col("id") % gap == gap - 1) & (F.floor(F.col("id") / gap) < quiet), F.lit(-1)).otherwise(F.col("id") % c)).withColumn("step", F.floor(F.col("id") / every))
    dims = F.sequence(F.lit(0), F.lit(d - 1))
    near = F.transform(dims, lambda i: F.floor(_uniform(F.lit("near"), F.col("id"), i, seed) * (2 * scatter + 1)) - scatter)
    any_ = F.transform(dims, lambda i: lo + F.floor(_uniform(F.lit("any"), F.col("id"), i, seed) * (hi - lo + 1)))
    met = rows.join(centres, ["k", "step"], "left")
    coord = F.when(F.col("k") >= 0, F.zip_with("centre", near, lambda a, b: F.least(F.greatest(a + b, F.lit(lo)), F.lit(hi)))).otherwise(any_)
    out = met.select("id", coord.cast("array<bigint>").alias("coord"), F.col("k").cast("long").alias("truth"))
    return Points(out.select("id", "coord"), d, True), out.select("id", "truth")

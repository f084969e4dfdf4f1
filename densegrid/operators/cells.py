"""Step 1: cell addresses and the table of occupied cells."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window, functions as F

from densegrid.functions.geometry import cell_of, eps2
from densegrid.params import ClusterParams
from densegrid.plans.lineage import cut
from densegrid.sources.points import Points


def assign_cells(points: Points, prm: ClusterParams) -> DataFrame:
    """id, coord, cell, cell_key; a projection, no shuffle."""
    return points.frame.withColumn("cell", cell_of(F.col("coord"), points.dim, prm.eps)).withColumn("cell_key", F.xxhash64("cell"))


def dense_ids(df: DataFrame, *order: str, name: str = "gid") -> DataFrame:
    """Adds ids 1..n in the given order: a range sort, then each partition's offset."""
    spread = cut(df.repartitionByRange(*order).withColumn("_part", F.spark_partition_id()))
    sizes = spread.groupBy("_part").count()
    before = sizes.select("_part", (F.sum("count").over(Window.orderBy("_part")) - F.col("count")).alias("_before"))
    row = F.row_number().over(Window.partitionBy("_part").orderBy(*order))
    return spread.withColumn("_row", row).join(F.broadcast(before), "_part").withColumn(name, F.col("_before") + F.col("_row")).drop("_part", "_row", "_before")


def cell_summary(points: Points, prm: ClusterParams) -> DataFrame:
    """gid, cell, cell_key, n, lo, hi of every occupied cell; one partially aggregated shuffle."""
    d = points.dim
    ends = [f(F.col("coord")[i]).alias(f"{s}{i}") for s, f in (("lo", F.min), ("hi", F.max)) for i in range(d)]
    cells = assign_cells(points, prm).groupBy("cell_key", "cell").agg(F.count("*").alias("n"), *ends)
    cells = cells.select("cell_key", "cell", "n", *[F.array(*[F.col(f"{s}{i}") for i in range(d)]).alias(s) for s in ("lo", "hi")])
    return cut(dense_ids(cells, "cell")).select("gid", "cell", "cell_key", "n", "lo", "hi")


def verify_cell_diameter(cells: DataFrame, prm: ClusterParams, exact: bool = True) -> DataFrame:
    """Cells whose points may lie farther apart than eps; rounding aside there are none."""
    squares = F.aggregate(F.zip_with("lo", "hi", lambda a, b: (b - a) * (b - a)), F.lit(0).cast("long") if exact else F.lit(0.0), lambda s, x: s + x)
    return cells.withColumn("diagonal2", squares).where(F.col("diagonal2") > eps2(prm.eps, exact))


def cell_curve(points: Points, eps_list: list[float]) -> DataFrame:
    """eps, occupied cells: a smaller eps has more."""
    at = F.explode(F.array(*[F.struct(F.lit(float(e)).alias("eps"), F.xxhash64(cell_of(F.col("coord"), points.dim, e)).alias("key")) for e in eps_list]))
    return points.frame.select(at.alias("s")).select("s.*").groupBy("eps").agg(F.count_distinct("key").alias("cells"))

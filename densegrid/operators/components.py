"""Connected components of an edge frame."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from densegrid.operators.forest import Forest
from densegrid.plans.lineage import Cut


def forest_roots(edges: DataFrame, most: int, a: str = "a", b: str = "b") -> DataFrame:
    """``components`` through one union-find forest on the driver, if there are at most ``most`` edges.

    A local forest pass has left fewer links than core cells; only their two ids
    travel. Beyond the bound the distributed rounds take over.
    """
    e = edges.select(F.col(a).cast("long").alias("a"), F.col(b).cast("long").alias("b")).where("a IS NOT NULL AND b IS NOT NULL")
    if e.count() > most:
        return components(e)
    table = e.toArrow()
    names, at = np.unique(np.concatenate([table.column(c).to_numpy() for c in "ab"]), return_inverse=True)
    half = len(at) // 2
    forest = Forest(len(names), "by_min_id")
    for x, y in zip(at[:half].tolist(), at[half:].tolist(), strict=True):
        forest.union(x, y)
    roots = names[np.array(forest.roots(), np.int64)] if len(names) else names
    out = pa.table({"node": pa.array(names, pa.int64()), "root": pa.array(roots, pa.int64())})
    return edges.sparkSession.createDataFrame(out)


def components(edges: DataFrame, a: str = "a", b: str = "b", max_rounds: int = 60) -> DataFrame:
    """(node, root) for every node of ``edges``: root is its component's smallest node.

    Each round relinks neighbours to the local minimum, first all larger ones,
    then all smaller ones; both steps are a partial-aggregated minimum and an
    equi-join, so a hub never has its neighbour list gathered in one task. The
    rounds are logarithmic in the component size. Self loops keep their node.
    Nulls in either column drop the edge. Nothing reaches the driver but a
    count and a checksum per round.
    """
    e = edges.select(F.col(a).cast("long").alias("u"), F.col(b).cast("long").alias("v")).where("u IS NOT NULL AND v IS NOT NULL")
    first = Cut(e.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct())
    nodes = first.frame.select(F.explode(F.array("u", "v")).alias("node")).distinct()
    current, seen = Cut(first.frame.where("u <> v")), None
    for _ in range(max_rounds):
        both = current.frame.union(current.frame.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        moved = large.join(low, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        after = Cut(moved.union(low.select("u", F.col("m").alias("v"))).distinct())
        row = after.frame.agg(F.count("*").alias("n"), F.sum(F.pmod(F.xxhash64("u", "v"), F.lit(1 << 40))).alias("h")).first()
        current.drop()
        current = after
        if seen == (row["n"], row["h"]):
            break
        seen = (row["n"], row["h"])
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return nodes.join(current.frame.select(F.col("u").alias("node"), F.col("v").alias("root")), "node", "left").select("node", F.coalesce("root", "node").alias("root"))

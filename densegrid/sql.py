"""The SQL surface: a table function that clusters each partition, and scalar helpers."""

from __future__ import annotations


import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession, functions as F
from pyspark.sql.udtf import AnalyzeArgument, AnalyzeResult
from pyspark.sql import types as T

from densegrid.operators.forest import merge_cells
from densegrid.operators.indexes import SlabIndex
from densegrid.operators.tiles import Tile, core_flags, distances2, merge_test, visiting
from densegrid.params import ClusterParams


def cluster_rows(ids: list[int], coords: list[list[float]], eps: float, min_pts: int) -> list[tuple[int, int, str]]:
    """(id, cluster_id, role) of points in one process, by the bitmap and forest method."""
    if not ids:
        return []
    prm, d = ClusterParams(float(eps), int(min_pts)), len(coords[0])
    exact = all(float(x).is_integer() for c in coords for x in c)
    kind = pa.int64() if exact else pa.float64()
    table = pa.table({"id": pa.array(ids, pa.int64()), "coord": pa.array([[int(x) if exact else float(x) for x in c] for c in coords], pa.list_(kind)), "own": pa.array([True] * len(ids))})
    tile = Tile(table, prm, d, exact)
    index = SlabIndex(tile.cells)
    core = core_flags(tile, index)
    core_cell = np.logical_or.reduceat(core, tile.first[:-1])
    partners = visiting(tile, index, core_cell)
    forest, _ = merge_cells(np.flatnonzero(core_cell).tolist(), partners, merge_test(tile, core), len(tile.cells), narrow=tile.pruned)
    least: dict[int, int] = {}
    for i in np.flatnonzero(core).tolist():
        r = int(forest.root[tile.of[i]])
        least[r] = min(least.get(r, int(tile.ids[i])), int(tile.ids[i]))
    out = []
    for i in range(len(tile.ids)):
        c = int(tile.of[i])
        if core[i]:
            out.append((int(tile.ids[i]), least[int(forest.root[c])], "core"))
            continue
        near = tile.pruned(c, partners(c))
        near = np.append(near, c) if core_cell[c] else near
        hit = [least[int(forest.root[k])] for k in near.tolist() if distances2(tile.x[i : i + 1], tile.x[tile.range(k)][core[tile.range(k)]]).min() <= tile.limit]
        out.append((int(tile.ids[i]), min(hit), "border") if hit else (int(tile.ids[i]), -1, "noise"))
    return out


class DenseClusters:
    """``dense_clusters(TABLE(t) PARTITION BY (k), eps, min_pts)``: t has id and coord; each partition apart."""

    @staticmethod
    def analyze(rows: AnalyzeArgument, eps: AnalyzeArgument, min_pts: AnalyzeArgument) -> AnalyzeResult:
        if not rows.isTable:
            raise ValueError("the first argument is a table")
        return AnalyzeResult(T.StructType().add("id", T.LongType()).add("cluster_id", T.LongType()).add("role", T.StringType()))

    def __init__(self):
        self.ids, self.coords, self.args = [], [], (1.0, 1)

    def eval(self, rows, eps, min_pts):
        self.ids.append(rows["id"])
        self.coords.append(list(rows["coord"]))
        self.args = (eps, min_pts)

    def terminate(self):
        yield from cluster_rows(self.ids, self.coords, *self.args)


def register(spark: SparkSession) -> None:
    """Registers dense_clusters, and grid_cell(coord, eps) and sq_distance(a, b) as SQL functions."""
    spark.udtf.register("dense_clusters", F.udtf(DenseClusters))
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION sq_distance(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION grid_cell(coord ARRAY<DOUBLE>, eps DOUBLE) RETURNS ARRAY<BIGINT> RETURN transform(coord, x -> floor(x * (sqrt(size(coord)) / eps)))")

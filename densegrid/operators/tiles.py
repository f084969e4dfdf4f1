"""Dealing points to tiles with a halo, and the two passes that run inside a tile.

A tile is a box of cells; it holds its own points and, as a halo, every point in
reach of them. The first pass finds the core points among a tile's own points.
The second merges core cells under a local forest and finds which core cells a
border point touches. A cell is named by its smallest core point, the same in
every tile that sees it, so the tiles' trees join up as components of their links.
"""

from __future__ import annotations

import math
import time
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.ml.feature import Bucketizer
from pyspark.sql import DataFrame, functions as F

from densegrid.functions.geometry import cell_of, cell_scale, eps2, reach, safe_reach
from densegrid.operators.forest import FlatForest, merge_cells, packed
from densegrid.operators.indexes import INDEXES, RectangleTree, SlabIndex, decoded, gaps2, near_blocks
from densegrid.params import ClusterParams
from densegrid.sources.points import Points

#: Points of one side, and of the other, whose distances are taken at once.
BLOCK, CHUNK = 256, 1024
#: Distances that are held at once.
HELD = 1 << 17
#: Points of a block that lie near one another in all dimensions, in up to so many of these; in more, a block has BLOCK.
NEAR_BLOCK, NEAR_DIM = 96, 12
#: Blocks for which an index is asked at once; a power of four.
TOGETHER = 16

#: Points, in expectation, from which tile bounds are taken; they decide balance, never results.
SAMPLE = 40_000
#: Copies that halos may add in one dimension, as a share of the points.
COPIES = 0.75
#: With so many tiles a core, of so many own points at most, halos are kept small: a dimension is cut with fewer copies, or not at all.
ENOUGH, ROOM, SPARE = 2, 60_000, (0.25, 0.5)


@dataclass(frozen=True)
class TilePlan:
    """Cut positions by dimension; a tile is named by its place between the cuts. ``largest``: its rows, estimated."""

    cuts: tuple[tuple[int, tuple[int, ...]], ...]
    tiles: int
    points: int
    largest: int


def plan_tiles(points: Points, prm: ClusterParams) -> TilePlan:
    """Cuts by the cells of a sample: about equal depths, each moved to where the fewest points lie within reach.

    One count and one filtered scan; the driver gets about ``SAMPLE`` coordinates.
    """
    d, halo = points.dim, safe_reach(points.dim)
    n = points.frame.count()
    need = max(1, -(-n // prm.tile_points))
    if need == 1:
        return TilePlan((), 1, n, n)
    cells = sampled_cells(points, prm, n)
    found = sorted(((best_cuts(cells[:, i], need, halo), i) for i in range(d)), key=lambda f: (-len(f[0][0]), f[0][1]))
    cuts, copies = [], np.ones(len(cells), np.int64)
    tiles = 1
    for (edges, _), i in found[:3]:
        if need > 1 and edges:
            enough = max(ENOUGH * points.frame.sparkSession.sparkContext.defaultParallelism, n // ROOM)
            few = [e for e, _ in (best_cuts(cells[:, i], need, halo, c) for c in SPARE) if tiles * (len(e) + 1) >= enough]
            if not few and tiles >= enough:
                continue
            edges = few[0] if few else best_cuts(cells[:, i], need, halo)[0]
            need = -(-need // (len(edges) + 1))
            tiles *= len(edges) + 1
            cuts.append((i, edges))
    tiles, rows, at = 1, np.arange(len(cells)), np.zeros(len(cells), np.int64)
    for i, edges in cuts:
        tiles *= len(edges) + 1
        low, high = (np.searchsorted(edges, cells[rows, i] + s, "right") for s in (-halo, halo))
        copies = high - low + 1
        step = np.arange(copies.sum()) - np.repeat(np.cumsum(copies) - copies, copies)
        at = np.repeat(at * (len(edges) + 1) + low, copies) + step
        rows = np.repeat(rows, copies)
    most = int(np.unique(at, return_counts=True)[1].max()) if len(at) else 0
    return TilePlan(tuple(cuts), tiles, n, int(most * n / max(1, len(cells))) + 1)


def sampled_cells(points: Points, prm: ClusterParams, n: int) -> np.ndarray:
    """The cells of about ``SAMPLE`` of ``n`` points."""
    some = points.frame.where(F.pmod(F.xxhash64("id"), F.lit(1 << 20)) < math.ceil(min(1.0, SAMPLE / max(1, n)) * (1 << 20))).select("coord").limit(2 * SAMPLE).toArrow()
    x = some.column("coord").combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(-1, points.dim)
    return np.floor(x.astype(np.float64) * cell_scale(points.dim, prm.eps)).astype(np.int64)


def best_cuts(column: np.ndarray, need: int, halo: int, most: float = COPIES) -> tuple[tuple[int, ...], float]:
    """As many cuts of one dimension, up to ``need`` parts, as copy at most ``most`` of the points; and that share."""
    at = np.sort(column)
    spots = np.unique(at)[1:]  # a cut at e parts cells below e from the rest
    if not len(spots):
        return (), 0.0
    crossed = np.searchsorted(at, spots + halo) - np.searchsorted(at, spots - halo)
    place, parts = np.searchsorted(at, spots) / len(at), min(need, 4096)
    while parts > 1:
        low, high = (np.searchsorted(place, (np.arange(1, parts) + s) / parts) for s in (-0.5, 0.5))
        chosen = sorted({int(a + crossed[a:b].argmin()) for a, b in zip(low, high, strict=True) if a < b})
        share = float(crossed[chosen].sum() / len(at))
        if share <= most and chosen:
            return tuple(int(e) for e in spots[chosen]), share
        parts = min(parts - 1, int(parts * 0.85))
    return (), 0.0


def deal(rows: DataFrame, plan: TilePlan, d: int, eps: float, halo: int) -> DataFrame:
    """``rows`` (with coord) once for each tile that sees them, with ``tile`` and ``own``."""
    scale, kept, own, tile = F.lit(cell_scale(d, eps)), rows.columns, F.lit(0).cast("long"), F.lit(0).cast("long")

    for k, (i, edges) in enumerate(plan.cuts):
        at = [F.floor(F.col("coord")[i].cast("double") * scale) + shift for shift in (-halo, halo, 0)]
        if len(edges) > 8:  # found by halving: long sums make code that is never compiled
            names = [f"_{n}{k}" for n in ("low", "high", "here")]
            rows = rows.withColumns({f"{n}_at": c.cast("double") for n, c in zip(names, at, strict=True)})
            split = [-math.inf, *map(float, edges), math.inf]
            rows = Bucketizer(splitsArray=[split] * 3, inputCols=[f"{n}_at" for n in names], outputCols=names).transform(rows)
            low, high, here = (F.col(n).cast("long") for n in names)
        else:
            low, high, here = (sum(((F.lit(e).cast("long") <= c).cast("long") for e in edges), F.lit(0).cast("long")) for c in at)
        rows = rows.withColumn(f"_at{k}", F.explode(F.sequence(low, high)))
        tile, own = tile * (len(edges) + 1) + F.col(f"_at{k}"), own * (len(edges) + 1) + here
    return _needed(rows.select(*kept, tile.alias("tile"), (tile == own).alias("own")))


def part_hot(dealt: DataFrame, hot: dict[int, int]) -> tuple[DataFrame, DataFrame]:
    """The rows of calm tiles; and those of hot ones once for each task (``low``, ``high``) that their group takes part in."""
    spark = dealt.sparkSession
    many = F.broadcast(spark.createDataFrame(list(hot.items()), "tile bigint, groups bigint"))
    group = F.pmod(F.xxhash64(F.lit("group"), "id"), F.col("groups"))
    rows = dealt.join(many, "tile").withColumn("grp", group).withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("groups") - 1)))
    return dealt.join(many, "tile", "left_anti"), rows.select(*dealt.columns, "grp", F.least("grp", "other").alias("low"), F.greatest("grp", "other").alias("high"))


def _needed(rows: DataFrame) -> DataFrame:
    """Without the rows of a halo that are known not to be core: merging has no use for them."""
    return rows.where("core OR own") if "core" in rows.columns else rows


def share_wide(dealt: DataFrame, wide: dict[int, int], d: int, eps: float) -> DataFrame:
    """The rows, those of wide tiles once for each task (``part``) that shares the tile: a cell's points are one's own."""
    spark = dealt.sparkSession
    many = F.broadcast(spark.createDataFrame(list(wide.items()), "tile bigint, parts bigint"))
    parts = F.coalesce("parts", F.lit(1).cast("long"))
    of = F.when(parts > 1, F.pmod(F.xxhash64(F.lit("part"), cell_of(F.col("coord"), d, eps)), parts)).otherwise(F.lit(0).cast("long"))
    rows = dealt.join(many, "tile", "left").withColumn("of", of)
    rows = rows.withColumn("part", F.explode(F.sequence(F.lit(0).cast("long"), parts - 1)))
    rows = _needed(rows.withColumn("own", F.col("own") & (F.col("of") == F.col("part"))).select(*dealt.columns, "part"))
    # A number of its own, so that tasks are not put together by their bytes: their work is larger than these tell.
    tasks = max(4 * sum(wide.values()), int(spark.conf.get("spark.sql.shuffle.partitions")))
    return rows.repartition(min(2048, tasks), "tile", "part")


class Tile:
    """The rows of one tile as matrices: cells sorted, points sorted by cell and id."""

    def __init__(self, table: pa.Table, prm: ClusterParams, d: int, exact: bool):
        x = np.asarray(table.column("coord").combine_chunks().flatten().to_numpy(zero_copy_only=False)).reshape(-1, d)
        ids = table.column("id").to_numpy()
        cell = np.floor(x.astype(np.float64) * cell_scale(d, prm.eps)).astype(np.int64)
        order = np.lexsort((ids, *cell.T[::-1]))
        self.order = order
        self.x, self.ids, cell = x[order], ids[order], cell[order]
        self.own = table.column("own").to_numpy(zero_copy_only=False).astype(bool)[order]
        self.weight = table.column("weight").to_numpy()[order] if "weight" in table.column_names else np.ones(len(ids), np.int64)
        #: In a task of a hot tile, the group of each row and whether there are two groups.
        self.group = table.column("grp").to_numpy()[order] if "grp" in table.column_names else None
        self.crossed = self.group is not None and len(ids) > 0 and table.column("low")[0].as_py() != table.column("high")[0].as_py()
        new = np.concatenate([[True], (cell[1:] != cell[:-1]).any(axis=1)]) if len(cell) else np.zeros(0, bool)
        self.first = np.append(np.flatnonzero(new), len(cell))
        self.cells, self.of = cell[self.first[:-1]], np.cumsum(new) - 1
        self.limit, self.prm, self.d = eps2(prm.eps, exact), prm, d
        starts = self.first[:-1]
        self.lo = np.minimum.reduceat(self.x, starts, axis=0)
        self.hi = np.maximum.reduceat(self.x, starts, axis=0)
        # Distances by products of coordinates around a middle: for whole numbers without any rounding, or not at all.
        low, high = (self.lo.min(axis=0), self.hi.max(axis=0)) if self.x.size else (np.zeros(d), np.zeros(d))
        span = high.astype(np.float64) - low
        most = float(((span + 1) ** 2).sum())  # no sum on the way to a distance is larger
        self.products = 4 * most < 2**52
        if self.products:
            y = self.x.astype(np.float64) - np.floor(low + span / 2)
            # Rows (y, 1, |y|^2), whose products with (-2y, |y|^2 - limit, 1) are distances less the limit.
            self.y = np.column_stack([y, np.ones(len(y)), (y * y).sum(axis=1)])
            if exact and most + self.limit < 2**24:
                self.y = self.y.astype(np.float32)
        self.doubt = 0.0 if exact else 1e-9 * (d * (float(span.max()) + 1) ** 2)
        # The cells' boxes by dimension, the widest first.
        self.wide = np.argsort(-span, kind="stable")
        kind = np.float32 if exact and most < 2**24 else self.x.dtype
        self.lo_by, self.hi_by = (np.ascontiguousarray((z - low)[:, self.wide].T, kind) for z in (self.lo, self.hi))
        self.low = low
        self.plain = "weight" not in table.column_names
        self.block = NEAR_BLOCK if d <= NEAR_DIM else BLOCK

    def range(self, c: int) -> slice:
        return slice(int(self.first[c]), int(self.first[c + 1]))

    def box_gap2(self, c: int, others: np.ndarray) -> np.ndarray:
        g = np.maximum(np.maximum(self.lo[others] - self.hi[c], self.lo[c] - self.hi[others]), 0)
        return (g * g).sum(axis=1)

    def pruned(self, c: int, near: np.ndarray) -> np.ndarray:
        return near[self.box_gap2(c, near) <= self.limit] if self.prm.box_prune else near

    def near(self, index, c: int) -> np.ndarray:
        """Cells near c by the index; where boxes decide anyway, without the test of the cells' own gaps."""
        return index.candidates(c) if self.prm.box_prune else index.neighbours(c)

    def rows_of(self, cells: np.ndarray) -> np.ndarray:
        n = self.first[cells + 1] - self.first[cells]
        return np.repeat(self.first[cells] - np.cumsum(n) + n, n) + np.arange(n.sum())


def distances2(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    diff = a[:, None, :] - b[None, :, :]
    return (diff * diff).sum(axis=2)


def within(tile: Tile, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """For rows ``a`` against rows ``b`` whether they lie within eps; what rounding could decide is taken again by differences."""
    if not tile.products:
        step = max(1, CHUNK * 64 // max(1, len(b) * tile.d))
        return np.concatenate([distances2(tile.x[a[k : k + step]], tile.x[b]) <= tile.limit for k in range(0, len(a), step)] or [np.zeros((0, len(b)), bool)])
    d, left = tile.d, tile.y[a]
    left = np.column_stack([left[:, :d] * left.dtype.type(-2), left[:, d + 1] - left.dtype.type(tile.limit), left[:, d]])
    hit, step = np.empty((len(a), len(b)), bool), max(64, HELD // max(1, len(a)))
    for k in range(0, len(b), step):  # so many that a product stays in the cache
        part = b[k : k + step]
        over = left @ tile.y[part].T
        np.less_equal(over, 0, out=hit[:, k : k + step])
        if tile.doubt:
            i, j = np.nonzero(np.abs(over) <= tile.doubt)
            diff = tile.x[a[i]] - tile.x[part[j]]
            hit[i, k + j] = (diff * diff).sum(axis=1) <= tile.limit
    return hit


def counted(tile: Tile, rows: np.ndarray, others: np.ndarray, count: np.ndarray) -> None:
    """Adds to ``count`` the weight of ``others`` within eps of each of ``rows``; a row that has min_pts is left as it is."""
    at = 0
    while at < len(others):
        open_ = np.flatnonzero(count < tile.prm.min_pts)
        if not len(open_):
            return
        part = others[at : at + max(CHUNK, HELD // len(rows) if at else 0)]
        hit = within(tile, rows[open_], part)
        count[open_] += np.count_nonzero(hit, axis=1) if tile.plain else hit @ tile.weight[part]
        at += len(part)


def reached(lo: np.ndarray, hi: np.ndarray, x: np.ndarray, limit) -> tuple[np.ndarray, np.ndarray]:
    """Of boxes (a row a dimension) those whose squared gap to the box around points is ``limit`` at most, and these gaps."""
    d, at, total = len(lo), None, np.zeros(lo.shape[1], lo.dtype)
    for k, (low, high) in enumerate(zip(x.min(axis=0), x.max(axis=0), strict=True)):
        a, b = (lo[k], hi[k]) if at is None else (lo[k].take(at), hi[k].take(at))
        gap = np.maximum(np.subtract(a, high, out=a if at is not None else None), np.subtract(low, b, out=b if at is not None else None))
        np.maximum(gap, 0, out=gap)
        gap *= gap
        total += gap
        if k + 1 == d or k % 8 in (1, 3, 5):
            keep = np.flatnonzero(total <= limit)
            if len(keep) < (len(total) if k + 1 == d else 0.9 * len(total)):
                at, total = keep if at is None else at.take(keep), total.take(keep)
    return np.arange(len(total)) if at is None else at, total


def nearby(tile: Tile, index, rows: np.ndarray, wanted: np.ndarray | None = None) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """``rows``, block by block, and rows that can lie within eps of any of a block's, the nearest first.

    The index is asked for many rows at once; of the cells (``wanted`` ones) that it finds
    those stay whose boxes the rows' box reaches, those of their quarters', and so on down to a block.
    """
    limit, size = tile.limit + tile.doubt, tile.block

    def parted(part, x, near, lo, hi):
        some, gap = reached(lo, hi, x, limit)
        if len(part) <= size:
            yield part, tile.rows_of(near[some[np.argsort(gap, kind="stable")]])
            return
        step = size * -(-len(part) // (4 * size))
        near, lo, hi = near.take(some), lo.take(some, axis=1), hi.take(some, axis=1)
        for k in range(0, len(part), step):
            yield from parted(part[k : k + step], x[k : k + step], near, lo, hi)

    for at in range(0, len(rows), TOGETHER * size):
        group = rows[at : at + TOGETHER * size]
        near = around(index, tile.of[group])
        if wanted is not None:
            near = near[wanted[near]]
        x = (tile.x[group] - tile.low)[:, tile.wide].astype(tile.lo_by.dtype)
        yield from parted(group, x, near, tile.lo_by.take(near, axis=1), tile.hi_by.take(near, axis=1))


def around(index, cells: np.ndarray) -> np.ndarray:
    """At least the cells within reach of any of several, by the cheapest way that the index has."""
    return getattr(index, "around", index.union)(cells)


def core_flags(tile: Tile, index) -> np.ndarray:
    """For the tile's own points whether they are core; counting stops at min_pts.

    Dense cells need no distances. The other points go in blocks that are near one
    another, first against the blocks beside theirs, as long as these settle enough, then
    against the cells that the index finds near any of the block's, the nearest first.
    """
    prm, core = tile.prm, np.zeros(len(tile.ids), bool)
    size = np.add.reduceat(tile.weight, tile.first[:-1])
    tight = ((tile.hi - tile.lo) ** 2).sum(axis=1) <= tile.limit  # all of the cell's points lie within eps of one another
    dense = tight & (size >= prm.min_pts)
    core[dense[tile.of]] = True
    blocks = near_blocks(tile.x, np.flatnonzero(tile.own & ~core), tile.block)
    beside, tried, settled = max(1, CHUNK // tile.block // 2), 0, 0
    for k, rows in enumerate(blocks):
        if tried >= 8 * tile.block and settled * 8 < tried:
            break
        count = np.zeros(len(rows), np.int64)
        counted(tile, rows, np.concatenate(blocks[max(0, k - beside) : k + beside + 1]), count)
        core[rows] = count >= prm.min_pts
        tried, settled = tried + len(rows), settled + np.count_nonzero(core[rows])
    left = np.concatenate([b[~core[b]] for b in blocks]) if blocks else np.zeros(0, np.int64)
    for rows, others in nearby(tile, index, left):
        count = np.zeros(len(rows), np.int64)
        counted(tile, rows, others, count)
        core[rows] = count >= prm.min_pts
    return core


class SubCells:
    """The core points of one cell, parted by halving the cell's side level by level: boxes and counts.

    ``level`` halvings leave parts of diagonal eps * rho at most. A part outside the
    ball of radius eps counts nothing, one inside that of eps * (1 + rho) counts
    whole, others are looked into; so a count lies between those of the two balls.
    """

    def __init__(self, p: np.ndarray, eps: float, rho: float):
        d = p.shape[1]
        self.wide, self.levels = (eps * (1 + rho)) ** 2, []
        part, fine = np.zeros(len(p), np.int64), p.astype(np.float64) * (math.sqrt(d) / eps)
        for level in range(max(0, math.ceil(math.log2(1 / rho))) + 1):
            if level:
                address = np.floor(fine * 2.0**level).astype(np.int64)
                _, first, part = np.unique(np.column_stack([above, address]), axis=0, return_index=True, return_inverse=True)
                part = part.ravel()
                parent = above[first]
            else:
                parent = np.zeros(1, np.int64)
            order = np.argsort(part, kind="stable")
            n = np.bincount(part)
            starts = np.cumsum(n) - n
            self.levels.append((np.minimum.reduceat(p[order], starts), np.maximum.reduceat(p[order], starts), n, parent))
            above = part
            if len(n) == len(p):
                break

    def count(self, q: np.ndarray, limit) -> np.ndarray:
        """For each point of ``q`` an approximate count of points around it."""
        out = np.zeros(len(q), np.int64)
        who, part = np.arange(len(q)), np.zeros(len(q), np.int64)
        for depth, (lo, hi, n, parent) in enumerate(self.levels):
            if depth:  # on to the parts of what is open
                first = np.searchsorted(parent, np.arange(len(self.levels[depth - 1][2])))
                last = np.searchsorted(parent, np.arange(len(self.levels[depth - 1][2])), "right")
                many = last[part] - first[part]
                who, part = np.repeat(who, many), np.repeat(first[part] - np.cumsum(many) + many, many) + np.arange(many.sum())
            gap = np.maximum(np.maximum(lo[part] - q[who], q[who] - hi[part]), 0)
            far = np.maximum(np.abs(q[who] - lo[part]), np.abs(hi[part] - q[who]))
            near = (gap * gap).sum(axis=1) <= limit
            whole = near & ((far * far).sum(axis=1) <= self.wide) if depth + 1 < len(self.levels) else near
            np.add.at(out, who[whole], n[part[whole]])
            who, part = who[near & ~whole], part[near & ~whole]
        return out


def merge_test(tile: Tile, core: np.ndarray):
    """The check whether two cells hold core points within eps; for the approximate method, by approximate counts."""
    prm, x, limit = tile.prm, tile.x, tile.limit
    rows = np.flatnonzero(core)
    ends = np.concatenate([[0], np.cumsum(np.add.reduceat(core, tile.first[:-1], dtype=np.int64))]).tolist()
    halved: dict[int, SubCells] = {}

    def near(p: np.ndarray, c: int) -> np.ndarray:
        g = np.maximum(np.maximum(tile.lo[c] - x[p], x[p] - tile.hi[c]), 0)
        return p[(g * g).sum(axis=1) <= limit]

    def check(a: int, b: int) -> bool:
        p, q = rows[ends[a] : ends[a + 1]], rows[ends[b] : ends[b + 1]]
        if len(p) == 1 == len(q):
            diff = x[p[0]] - x[q[0]]
            return bool((diff * diff).sum() <= limit)
        p = near(p, b)  # only points near the other's box can do
        if prm.method == "grid_approx":
            if b not in halved:
                halved[b] = SubCells(x[q], prm.eps, prm.rho)
            return bool(halved[b].count(x[p], limit).any())
        q = near(q, a)
        if not len(p) or not len(q):
            return False
        step = max(1, CHUNK * 64 // len(q))
        return any(within(tile, p[at : at + step], q[k : k + CHUNK * 64]).any() for at in range(0, len(p), step) for k in range(0, len(q), CHUNK * 64))

    def among(a: int, others: np.ndarray) -> np.ndarray:
        """The same for one cell and each of several, by one product of their points."""
        p, first, n = rows[ends[a] : ends[a + 1]], starts[others], starts[others + 1] - starts[others]
        ok = np.zeros(len(others), bool)
        part = np.cumsum(n) // (CHUNK * 16)  # cells by parts, so that what is held at once stays small
        for k in np.unique(part):
            at = np.flatnonzero(part == k)
            m = n[at]
            ends_of = np.cumsum(m) - m
            q = rows[np.repeat(first[at] - ends_of, m) + np.arange(m.sum())]
            step = max(1, CHUNK * 64 // len(q))
            for i in range(0, len(p), step):
                ok[at] |= np.logical_or.reduceat(within(tile, p[i : i + step], q).any(axis=0), ends_of)
        return ok

    starts = np.array(ends)
    check.among = None if prm.method == "grid_approx" else among
    return check


def make_index(tile: Tile, prm: ClusterParams):
    return INDEXES[prm.method](tile.cells, max_offsets=prm.max_offsets, budget=prm.index_bytes)


class BitMeeting:
    """Core cells that a cell has still to be checked with, found on bit words for a block of cells at once.

    Own words of the cell's tree are taken out before a bit is decoded, so that in a
    large tree the cells that need no check cost a few words each.
    """

    def __init__(self, tile: Tile, index: SlabIndex, core_cell: np.ndarray, vertices: list[int], later: bool):
        self.index, self.later, self.vertices = index, later, np.array(vertices, np.int64)
        self.core = packed(np.flatnonzero(core_cell), index.n)
        self.place, self.at = {int(g): k for k, g in enumerate(vertices)}, -BLOCK

    def __call__(self, g: int, forest: FlatForest) -> tuple[int, np.ndarray]:
        k = self.place[g]
        if not 0 <= k - self.at < BLOCK:
            self.at = k
            self.block = self.index.bits(self.vertices[k : k + BLOCK]) & self.core
        row, word, bit = self.block[k - self.at], g >> 6, g & 63
        gone = (1 << (bit + 1)) - 1 if self.later else 1 << bit
        row[word] &= np.uint64((1 << 64) - 1 - gone)
        if self.later:
            row[:word] = 0
        considered = int(np.bitwise_count(row).sum())
        own = forest.words(g)
        if own is not None:
            row &= ~own
        near = decoded(row)
        return considered, near[forest.root[near] != forest.root[g]]


class ProductMeeting:
    """For a block of cells the core cells that they meet, and by one product of their core points those within eps.

    For cells of few points each: a test by boxes costs more than the distances
    themselves. Called like ``BitMeeting``, but what it gives has passed the check, as
    some of ``checked`` pairs. With ``pruned``, cells that are in one tree as the block
    begins are left out of the product. For the approximate method the core points of a
    block are counted in a cell of several by its halved parts, as ``merge_test`` does; those
    of a cell of one are that point.
    """

    #: Core points a core cell, up to which this is worth while.
    FEW = 2

    def __init__(self, tile: Tile, index, core: np.ndarray, core_cell: np.ndarray, vertices: list[int], later: bool, pruned: bool):
        self.tile, self.index, self.later, self.pruned = tile, index, later, pruned
        self.vertices, self.core_cell, self.rows = np.array(vertices, np.int64), core_cell, np.flatnonzero(core)
        self.n = np.add.reduceat(core, tile.first[:-1], dtype=np.int64)
        self.starts = np.cumsum(self.n) - self.n
        self.place, self.at, self.size = {g: k for k, g in enumerate(vertices)}, 0, 0
        self.halved: dict[int, SubCells] = {}

    def _counted(self, c: int, mine: np.ndarray) -> np.ndarray:
        """Whether an approximate count of the core points of cell ``c`` around each of ``mine`` is above 0."""
        tile = self.tile
        if c not in self.halved:
            self.halved[c] = SubCells(tile.x[self._points(np.array([c]))[0]], tile.prm.eps, tile.prm.rho)
        return self.halved[c].count(tile.x[mine], tile.limit) > 0

    def _points(self, cells: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The core points of the cells, and where each cell's begin."""
        n = self.n[cells]
        first = np.cumsum(n) - n
        return self.rows[np.repeat(self.starts[cells] - first, n) + np.arange(n.sum())], first

    def _ask(self, cells: np.ndarray, forest: FlatForest) -> None:
        other, near = self.index.meeting(cells, int(cells[0]) + 1 if self.later else 0)
        keep = self.core_cell[other]
        if not keep.all():
            other, near = other[keep], near[:, keep]
        near &= other[None, :] > cells[:, None] if self.later else other[None, :] != cells[:, None]
        self.considered = np.count_nonzero(near, axis=1)
        if self.pruned:
            near &= forest.root[other][None, :] != forest.root[cells][:, None]
        self.checks = np.count_nonzero(near, axis=1)
        open_, met = np.flatnonzero(self.checks), near.any(axis=0)
        if not met.all():
            other, near = other[met], near[:, met]
        if len(open_):
            mine, one = self._points(cells[open_])
            rows, two = self._points(other)
            hit = within(self.tile, mine, rows)
            if len(mine) > len(open_):
                hit = np.logical_or.reduceat(hit, one, axis=0)
            if len(rows) > len(other):
                several = np.flatnonzero(self.n[other] > 1)  # most cells have one core point, which stands for them
                held = hit[:, np.repeat(self.n[other] > 1, self.n[other])]
                ends = np.cumsum(self.n[other[several]])
                hit = hit[:, two]
                hit[:, several] = np.logical_or.reduceat(held, ends - self.n[other[several]], axis=1)
                if self.tile.prm.method == "grid_approx":
                    for j in several.tolist():
                        hit[:, j] = np.logical_or.reduceat(self._counted(int(other[j]), mine), one)
            near[open_] &= hit
        self.other, self.hit = other, near
        self.open = (near & (forest.root[other][None, :] != forest.root[cells][:, None])).any(axis=1)

    def __call__(self, g: int, forest: FlatForest) -> tuple[int, np.ndarray]:
        k = self.place[g]
        if not self.at <= k < self.at + self.size:
            cells = self.vertices[k : k + self.index.together(BLOCK)]
            self.at, self.size = k, len(cells)
            self._ask(cells, forest)
        k -= self.at
        met, self.checked = int(self.considered[k]), int(self.checks[k])
        if not self.open[k]:
            return met, self.other[:0]
        near = self.other[self.hit[k]]
        return met, near[forest.root[near] != forest.root[g]]


def visiting(tile: Tile, index, core_cell: np.ndarray, strict: bool = False):
    """Core cells near a cell, in the order asked for; ``strict`` leaves out those that only rounding could bring near."""
    size = np.diff(tile.first)

    def partners(c: int) -> np.ndarray:
        near = tile.near(index, c)
        if strict:
            near = near[gaps2(tile.cells, c, near) < tile.d]
        near = near[core_cell[near]]
        if tile.prm.order == "nearest_first":
            near = near[np.argsort(tile.box_gap2(c, near), kind="stable")]
        elif tile.prm.order == "densest_first":
            near = near[np.argsort(-size[near], kind="stable")]
        return near

    return partners


OUT = "kind string, a long, b long, v double"


def _rows(kind: str, a, b, v) -> pa.RecordBatch:
    n = len(a)
    return pa.RecordBatch.from_arrays([pa.repeat(kind, n), pa.array(np.asarray(a, np.int64)), pa.array(np.asarray(b, np.int64)), pa.array(np.asarray(v, np.float64))], ["kind", "a", "b", "v"])


def label_tile(table: pa.Table, prm: ClusterParams, d: int, exact: bool) -> Iterator[pa.RecordBatch]:
    tile = Tile(table, prm, d, exact)
    if prm.method == "reference":
        tree = RectangleTree(tile.x)
        core = np.zeros(len(tile.ids), bool)
        own = np.flatnonzero(tile.own)
        for at in range(0, len(own), BLOCK):
            mine = own[at : at + BLOCK]
            count = np.zeros(len(mine), np.int64)
            counted(tile, mine, np.arange(max(0, mine[0] - CHUNK // 2), min(len(tile.ids), mine[0] + CHUNK // 2)), count)
            core[mine] = count >= prm.min_pts  # who has enough around itself needs no range query
            mine = mine[~core[mine]]
            if len(mine):
                rows = np.sort(tree.near(tile.x[mine], tile.limit))
                count = np.zeros(len(mine), np.int64)
                counted(tile, mine, rows, count)
                core[mine] = count >= prm.min_pts
    else:
        core = core_flags(tile, make_index(tile, prm))
    own = np.flatnonzero(tile.own)
    back = table.take(pa.array(tile.order[own]))
    yield pa.RecordBatch.from_arrays([back.column("id").combine_chunks(), back.column("coord").combine_chunks(), pa.array(core[own])], ["id", "coord", "core"])


def count_tile(table: pa.Table, prm: ClusterParams, d: int, exact: bool) -> Iterator[pa.RecordBatch]:
    """For a task of a hot tile how many points own ones reach, up to min_pts: in their own group, or across two.

    The coordinates come with the counts of the own group.
    """
    tile = Tile(table, prm, d, exact)
    index = make_index(tile, prm)
    tight = ((tile.hi - tile.lo) ** 2).sum(axis=1) <= tile.limit
    out = np.zeros(len(tile.ids), np.int64)
    for mine in np.unique(tile.group):
        met = tile.group != mine if tile.crossed else tile.group == mine
        size = np.add.reduceat(tile.weight * met, tile.first[:-1])
        dense = (tight & (size >= prm.min_pts))[tile.of]
        rows = np.flatnonzero(tile.own & (tile.group == mine))
        out[rows[dense[rows]]] = prm.min_pts
        rows = rows[~dense[rows]]
        for at in range(0, len(rows), BLOCK):
            part = rows[at : at + BLOCK]
            cells = np.unique(tile.of[part])
            others = tile.rows_of(np.union1d(around(index, cells), cells))
            count = np.zeros(len(part), np.int64)
            counted(tile, part, others[met[others]], count)
            out[part] = np.minimum(count, prm.min_pts)
    own = np.flatnonzero(tile.own)
    back = table.take(pa.array(tile.order[own]))
    coord = back.column("coord").combine_chunks()
    yield pa.RecordBatch.from_arrays([back.column("id").combine_chunks(), pa.nulls(len(own), coord.type) if tile.crossed else coord, pa.array(out[own])], ["id", "coord", "n"])


def merge_tile(table: pa.Table, prm: ClusterParams, d: int, exact: bool) -> Iterator[pa.RecordBatch]:
    """Rows: link (two named cells in one tree), name (a core point and its cell's name), touch (a
    border candidate, the name of a core cell it touches, squared distance), counts."""
    tile = Tile(table, prm, d, exact)
    core = table.column("core").to_numpy(zero_copy_only=False).astype(bool)[tile.order]
    if prm.method == "reference":
        yield from _merge_points(tile, core)
        return
    steps, began = [], time.perf_counter()
    index = make_index(tile, prm)
    starts = tile.first[:-1]
    core_cell = np.logical_or.reduceat(core, starts)
    name = np.minimum.reduceat(np.where(core, tile.ids, np.iinfo(np.int64).max), starts)
    own_cell = np.logical_or.reduceat(tile.own, starts)
    partners = visiting(tile, index, core_cell, strict=prm.strict)

    pruned = prm.method.endswith("pruned")
    vertices = np.flatnonzero(core_cell & own_cell).tolist()  # a pair belongs to the tile that owns its first cell
    began = _step(steps, began)
    quick = pruned and isinstance(index, SlabIndex) and not index.rest and prm.box_prune and prm.order == "as_given" and not prm.strict
    meet = BitMeeting(tile, index, core_cell, vertices, prm.visit == "once") if quick else None
    if tile.products and hasattr(index, "meeting") and index.together(1) and prm.box_prune and prm.order == "as_given" and not prm.strict and np.count_nonzero(core) <= ProductMeeting.FEW * np.count_nonzero(core_cell):
        meet = ProductMeeting(tile, index, core, core_cell, vertices, prm.visit == "once", pruned)
    check = merge_test(tile, core)
    forest = _sown(tile, core, table.column("seed").fill_null(0).to_numpy()[tile.order]) if "seed" in table.column_names else None
    forest, counts = merge_cells(vertices, partners, check, len(tile.cells), pruned, prm.visit, tile.pruned, meet, None if pruned else check.among, forest)
    if counts.links:
        a, b = np.array(counts.links).T
        yield _rows("link", name[a], name[b], np.zeros(len(a)))
    own_core = np.flatnonzero(core & tile.own)
    if tile.crossed:  # the two groups' parts of a cell have names of their own, and are one
        low = tile.group == tile.group.min()
        a, b = (np.minimum.reduceat(np.where(core & side, tile.ids, np.iinfo(np.int64).max), starts) for side in (low, ~low))
        both = np.flatnonzero((np.maximum(a, b) < np.iinfo(np.int64).max) & own_cell)
        yield _rows("link", a[both], b[both], np.zeros(len(both)))
    else:
        yield _rows("name", tile.ids[own_core], name[tile.of[own_core]], np.zeros(len(own_core)))
    yield _rows("counts", range(5), [counts.considered, counts.skipped, counts.boxed, counts.checks, counts.unions], np.zeros(5))
    yield _rows("counts", [5], [np.count_nonzero(core_cell & own_cell)], [0.0])
    began = _step(steps, began)
    for batch in touches(tile, index, core, core_cell):
        a, at, v = batch
        yield _rows("touch", tile.ids[a], name[at], v)
    _step(steps, began)
    yield _rows("seconds", range(3), np.zeros(3), steps)


def _sown(tile: Tile, core: np.ndarray, seed: np.ndarray) -> FlatForest:
    """Cells whose core points are known to be of one cluster (``seed``) as trees."""
    forest, rows = FlatForest(len(tile.cells)), np.flatnonzero(core)
    pairs = np.unique(np.column_stack([seed[rows], tile.of[rows]]), axis=0)
    same = np.flatnonzero(pairs[1:, 0] == pairs[:-1, 0])
    for a, b in zip(pairs[same, 1].tolist(), pairs[same + 1, 1].tolist(), strict=True):
        if forest.root[a] != forest.root[b]:
            forest.union(a, b)
    return forest


def _step(steps: list[float], began: float) -> float:
    now = time.perf_counter()
    steps.append(now - began)
    return now


def touches(tile: Tile, index, core: np.ndarray, core_cell: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Own points that are not core, core cells that they touch, and the least squared distance to each.

    Asked from the side that has fewer points.
    """
    loose, held = ~core & tile.own, core
    turned = np.count_nonzero(held) < np.count_nonzero(loose)
    if turned:
        loose, held = held, loose
    wanted = np.logical_or.reduceat(held, tile.first[:-1])
    whole = []
    blocks = near_blocks(tile.x, np.flatnonzero(loose), tile.block)
    for mine, rows in nearby(tile, index, np.concatenate(blocks) if blocks else np.zeros(0, np.int64), wanted):
        rows = rows[held[rows]]
        found = []
        for k in range(0, len(rows), CHUNK):
            i, j = np.nonzero(within(tile, mine, rows[k : k + CHUNK]))
            one, two = mine[i], rows[k + j]
            diff = tile.x[one] - tile.x[two]
            if turned:
                one, two = two, one
            found.append((one, tile.of[two], (diff * diff).sum(axis=1)))
        if found:
            part = _least(*(np.concatenate(z) for z in zip(*found, strict=True)))
            if not turned:
                yield part
            elif len(part[0]):
                whole.append(part)
    if whole:
        yield _least(*(np.concatenate(z) for z in zip(*whole, strict=True)))


def _least(i: np.ndarray, c: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The least ``v`` of each pair of ``i`` and ``c``."""
    order = np.lexsort((v, c, i))
    i, c, v = i[order], c[order], v[order]
    first = np.flatnonzero(np.concatenate([[True], (i[1:] != i[:-1]) | (c[1:] != c[:-1])])) if len(i) else i
    return i[first], c[first], v[first]


def _merge_points(tile: Tile, core: np.ndarray) -> Iterator[pa.RecordBatch]:
    """The per-point method: a range query for every own point; core points link to what they reach.

    Core points ask only for what is in other trees than theirs, as the block begins. Own
    core points are named by their tree; links (a core point, a tree's name) are given for
    those that others own, and touched core points by their ids (``named``).
    """
    at = np.flatnonzero(core)
    if not len(at):
        yield _rows("counts", range(6), np.zeros(6), np.zeros(6))
        return
    tree, forest = RectangleTree(tile.x[at]), FlatForest(len(at))
    place = np.full(len(tile.ids), -1)
    place[at] = np.arange(len(at))
    touch, met, unions = [], 0, 0
    own = np.flatnonzero(tile.own)
    for low in range(0, len(own), BLOCK):
        block = own[low : low + BLOCK]
        mine = block[core[block]]
        trees = np.unique(forest.root[place[mine]])
        rows = np.zeros(0, np.int64)
        if len(trees):
            rows = np.sort(tree.near(tile.x[mine], tile.limit, None if len(trees) > 1 else forest.root != trees[0]))
        for k in range(0, len(rows), 8 * CHUNK):
            part = rows[k : k + 8 * CHUNK]
            roots = forest.root[place[mine]]
            if (roots == roots[0]).all():  # what is in one tree stays in it
                part = part[forest.root[part] != roots[0]]
                if not len(part):
                    continue
            hit = within(tile, mine, at[part])
            met += int(hit.sum())
            apart = forest.root[part][None, :] != roots[:, None]
            for j in np.flatnonzero((hit & apart).any(axis=1)).tolist():
                me, near = int(place[mine[j]]), part[hit[j]]
                near = near[forest.root[near] != forest.root[me]]
                while len(near):
                    unions += 1
                    forest.union(me, int(near[0]))
                    near = near[forest.root[near] != forest.root[me]]
        loose = block[~core[block]]
        rows = np.sort(tree.near(tile.x[loose], tile.limit)) if len(loose) else rows[:0]
        for k in range(0, len(rows), 8 * CHUNK):
            part = rows[k : k + 8 * CHUNK]
            hit = within(tile, loose, at[part])
            met += int(hit.sum())
            i, j = np.nonzero(hit)
            one, two = loose[i], at[part[j]]
            diff = tile.x[one] - tile.x[two]
            touch.append((tile.ids[one], tile.ids[two], (diff * diff).sum(axis=1)))
    mine, top = tile.own[at], np.iinfo(np.int64).max
    least = np.full(len(at), top)  # a tree is named by its smallest own core point
    np.minimum.at(least, forest.root[mine], tile.ids[at[mine]])
    name = least[forest.root]
    far = np.flatnonzero((name < top) & (~mine | tile.crossed))  # what others own, and have names of their own for
    yield _rows("link", tile.ids[at[far]], name[far], np.zeros(len(far)))
    own_core = tile.ids[core & tile.own]
    if not tile.crossed:
        yield _rows("name", own_core, name[mine], np.zeros(len(own_core)))
    yield _rows("counts", range(6), [met, 0, 0, met, unions, len(own_core)], np.zeros(6))
    for batch in touch:
        yield _rows("touch", *batch)


def named(found: DataFrame) -> DataFrame:
    """The rows of the per-point method with names in place of the ids that links and touches hold."""
    names = found.where("kind = 'name'").select(F.col("a").alias("_id"), F.col("b").alias("_name"))

    def mapped(rows: DataFrame, c: str) -> DataFrame:
        return rows.join(names, F.col(c) == F.col("_id")).withColumn(c, F.col("_name")).drop("_id", "_name")

    links = mapped(mapped(found.where("kind = 'link'"), "a").distinct(), "b").where("a <> b").distinct()
    return found.where("kind NOT IN ('link', 'touch')").unionByName(links).unionByName(mapped(found.where("kind = 'touch'"), "b"))


def neighbour_tile(table: pa.Table, prm: ClusterParams, d: int, exact: bool) -> Iterator[pa.RecordBatch]:
    """Rows: pair (the smallest ids of two neighbouring cells, both ways)."""
    tile = Tile(table, prm, d, exact)
    index = make_index(tile, prm)
    name, own = tile.ids[tile.first[:-1]], np.logical_or.reduceat(tile.own, tile.first[:-1])
    box = prm.corner_rule == "box"
    a, b = [], []
    for c in np.flatnonzero(own).tolist():
        near = index.candidates(c) if box else index.neighbours(c)
        if box:
            near = near[(np.abs(tile.cells[near] - tile.cells[c]) <= reach(tile.d)).all(axis=1)]
        else:
            near = near[gaps2(tile.cells, c, near) < tile.d]
        a += [int(name[c])] * len(near)
        b += name[near].tolist()
    if a:
        yield _rows("pair", a, b, np.zeros(len(a)))


def index_tile(table: pa.Table, prm: ClusterParams, d: int, exact: bool) -> Iterator[pa.RecordBatch]:
    """One row: the index's bytes, the cells it finds for all own cells, and the seconds to build and ask it."""
    tile = Tile(table, prm, d, exact)
    own = np.flatnonzero(np.logical_or.reduceat(tile.own, tile.first[:-1]))
    began = time.perf_counter()
    index = make_index(tile, prm)
    found = sum(map(len, index.each(own)))
    yield _rows("index", [index.nbytes()], [found], [time.perf_counter() - began])


def run_tiles(dealt: DataFrame, kernel, schema: str, prm: ClusterParams, d: int, exact: bool, by: list[str] | None = None) -> DataFrame:
    """``kernel`` over every tile (or every task of a tile, by ``by``) that owns a point."""

    def run(table: pa.Table) -> pa.Table:
        batches = list(kernel(table, prm, d, exact)) if table.num_rows and pc.any(table.column("own")).as_py() else []
        return pa.Table.from_batches(batches, batches[0].schema) if batches else empty

    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import _parse_datatype_string

    empty = to_arrow_schema(_parse_datatype_string(schema)).empty_table()
    return dealt.groupBy(*(by or ["tile"])).applyInArrow(lambda table: run(table), schema)

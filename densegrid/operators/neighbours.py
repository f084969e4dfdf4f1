"""Neighbour-cell queries as DataFrame plans; the tile kernels are in tiles.

Each gives ordered pairs (gid_a, gid_b) of different occupied cells that can hold
points within eps of each other.
"""

from __future__ import annotations

from itertools import product

from pyspark.sql import Column, DataFrame, functions as F

from densegrid.functions.geometry import cell_gap2, dist2, eps2, reach, reachable_offset_count, safe_reach
from densegrid.params import ClusterParams
from densegrid.sources.points import Points

BUCKET_BITS = 32_768


def _rule(prm: ClusterParams, d: int, a: Column, b: Column) -> Column:
    """The corner rule: the whole box, or only what a point within eps can reach."""
    if prm.corner_rule == "box":
        return F.forall(F.zip_with(a, b, lambda x, y: F.abs(x - y)), lambda g: g <= reach(d))
    return cell_gap2(a, b) < d


def neighbours_by_offsets(cells: DataFrame, d: int, prm: ClusterParams) -> DataFrame:
    """Every reachable offset of every cell probed by an equi-join: Theta((2r+1)^d), refused beyond ``max_offsets``."""
    n = reachable_offset_count(d)
    if n > prm.max_offsets:
        raise ValueError(f"{n} neighbour cells in {d} dimensions exceed max_offsets={prm.max_offsets}; use a slab or bucket query")
    r = reach(d)
    near = (lambda o: True) if prm.corner_rule == "box" else (lambda o: sum(max(abs(x) - 1, 0) ** 2 for x in o) < d)
    offsets = [(list(o),) for o in product(range(-r, r + 1), repeat=d) if any(o) and near(o)]
    table = F.broadcast(cells.sparkSession.createDataFrame(offsets, "delta array<bigint>"))  # at most max_offsets rows
    probes = cells.select("gid", "cell").join(table).select(F.col("gid").alias("gid_a"), F.zip_with("cell", "delta", lambda x, y: x + y).alias("at")).withColumn("key", F.xxhash64("at"))
    there = cells.select(F.col("gid").alias("gid_b"), F.col("cell").alias("cell_b"), F.col("cell_key").alias("key"))
    return probes.join(there, "key").where("at = cell_b").select("gid_a", "gid_b")


def build_slabs(cells: DataFrame) -> DataFrame:
    """dim, pos, bucket, bits: for each occupied position of each dimension the cells there, as bitmaps."""
    rows = cells.select("gid", F.posexplode("cell").alias("dim", "pos"))
    return rows.groupBy("dim", "pos", F.bitmap_bucket_number("gid").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("gid")).alias("bits"))


def decode_bits(bits: Column, bucket: Column) -> Column:
    """The ids whose bits are set, in SQL functions alone: bytes with bits, then their bits."""
    filled = F.filter(F.transform(F.sequence(F.lit(0), F.lit(BUCKET_BITS // 8 - 1)), lambda i: F.struct(i.alias("i"), F.conv(F.hex(F.substring(bits, i + 1, F.lit(1))), 16, 10).cast("int").alias("v"))), lambda s: s["v"] > 0)
    each = F.flatten(F.transform(filled, lambda s: F.filter(F.transform(F.sequence(F.lit(0), F.lit(7)), lambda b: F.when(F.call_function("shiftright", s["v"], b).bitwiseAND(1) == 1, s["i"] * 8 + b)), lambda x: x.isNotNull())))
    return F.transform(each, lambda p: (bucket - 1) * BUCKET_BITS + p + 1)


def neighbours_by_slabs_sql(cells: DataFrame, d: int, prm: ClusterParams, budget_bytes: int = 4 << 30) -> DataFrame:
    """OR of each position's window, made once; AND over the dimensions of each cell; then the corner rule.

    Refused where the windows of all cells would move more than ``budget_bytes``:
    the tile kernels do the same without moving bitmaps.
    """
    r = safe_reach(d)
    n = cells.count()
    moved = n * d * (-(-n // BUCKET_BITS)) * (BUCKET_BITS // 8)
    if moved > budget_bytes:
        raise ValueError(f"the bitmaps of {n} cells in {d} dimensions would move {moved} bytes; use a tile method")
    slabs = build_slabs(cells)
    spots = slabs.select("dim", "pos").distinct()
    reachable = spots.select("dim", F.col("pos").alias("centre"), F.explode(F.sequence(F.col("pos") - r, F.col("pos") + r)).alias("pos"))
    windows = reachable.join(slabs, ["dim", "pos"]).groupBy("dim", "centre", "bucket").agg(F.bitmap_or_agg("bits").alias("bits"))
    asked = cells.select("gid", F.posexplode("cell").alias("dim", "centre"))
    both = asked.join(windows, ["dim", "centre"]).groupBy("gid", "bucket").agg(F.bitmap_and_agg("bits").alias("bits"), F.count("*").alias("dims")).where(F.col("dims") == d)
    found = both.select(F.col("gid").alias("gid_a"), F.explode(decode_bits(F.col("bits"), F.col("bucket"))).alias("gid_b")).where("gid_a <> gid_b")
    a, b = (cells.select(F.col("gid").alias(f"gid_{s}"), F.col("cell").alias(f"cell_{s}")) for s in "ab")
    return found.join(a, "gid_a").join(b, "gid_b").where(_rule(prm, d, F.col("cell_a"), F.col("cell_b"))).select("gid_a", "gid_b")


def neighbours_by_buckets(cells: DataFrame, d: int, prm: ClusterParams, m: int = 2, safe: bool = False) -> DataFrame:
    """A coarse key over the ``m`` dimensions with most positions, one side copied to the adjacent keys, an equi-join.

    ``safe`` also gives the pairs that only rounding could bring within eps.
    """
    r, m = safe_reach(d), min(m, d)
    spread = cells.agg(*[F.approx_count_distinct(F.col("cell")[i]).alias(f"k{i}") for i in range(d)]).first()
    dims = sorted(range(d), key=lambda i: -spread[i])[:m]
    key = [F.floor(F.col("cell")[i] / (r + 1)).alias(f"b{i}") for i in dims]
    left = cells.select(F.col("gid").alias("gid_a"), F.col("cell").alias("cell_a"), *key)
    for i in dims:
        left = left.withColumn(f"b{i}", F.explode(F.sequence(F.col(f"b{i}") - 1, F.col(f"b{i}") + 1)))
    right = cells.select(F.col("gid").alias("gid_b"), F.col("cell").alias("cell_b"), *key)
    near = cell_gap2(F.col("cell_a"), F.col("cell_b")) <= d if safe else _rule(prm, d, F.col("cell_a"), F.col("cell_b"))
    return left.join(right, [f"b{i}" for i in dims]).where((F.col("gid_a") != F.col("gid_b")) & near).select("gid_a", "gid_b")


def in_box(points: Points, low: list[float], high: list[float]) -> DataFrame:
    """The points within a closed box, by a range in every dimension."""
    inside = F.lit(True)
    for i, (a, b) in enumerate(zip(low, high, strict=True)):
        inside &= F.col("coord")[i].between(a, b)
    return points.frame.where(inside)


def in_ball(points: Points, centre: list[float], eps: float) -> DataFrame:
    """The points within eps of a place, with their squared distances; the ball's box is tested first."""
    at = F.array(*[F.lit(int(x) if points.exact else float(x)) for x in centre]).cast(f"array<{'bigint' if points.exact else 'double'}>")
    near = in_box(points, [x - eps for x in centre], [x + eps for x in centre])
    return near.withColumn("dist2", dist2(F.col("coord"), at, points.exact)).where(F.col("dist2") <= eps2(eps, points.exact))


def neighbours_of(cells: DataFrame, gid: int, d: int, prm: ClusterParams) -> DataFrame:
    """The neighbours of one cell: a range in every dimension."""
    at = cells.where(F.col("gid") == gid).select("cell").first()["cell"]
    inside = F.lit(True)
    for i, x in enumerate(at):
        inside &= F.col("cell")[i].between(x - reach(d), x + reach(d))
    here = F.array(*[F.lit(x).cast("long") for x in at])
    return cells.where(inside & (F.col("gid") != gid)).where(_rule(prm, d, F.col("cell"), here)).select("gid", "cell")

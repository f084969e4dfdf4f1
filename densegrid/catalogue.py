"""Every query of the clustering engine, with the SQL that checks it."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from densegrid import oracle, workloads as w
from densegrid.operators import measures, neighbours, profile, relational
from densegrid.operators.cells import assign_cells, cell_curve, cell_summary, verify_cell_diameter
from densegrid.operators.components import components
from densegrid.operators.generator import drift_clusters
from densegrid.operators.tiles import deal, label_tile, plan_tiles, run_tiles
from densegrid.functions.geometry import safe_reach
from densegrid.params import ClusterParams
from densegrid.plans.engine import cluster
from densegrid.sources.points import Points, fold_duplicates, load_table, scale_features
from densegrid.sql import register
from densegrid.streaming import incremental, windows

Query = Callable[[SparkSession, str], DataFrame]
_QUERIES: dict[str, Query] = {}
_SQL: dict[str, str] = {}


def _add(name: str, run: Query, sql: str | None = None) -> None:
    _QUERIES[name] = run
    if sql:
        _SQL[name] = sql


def _params(name: str, **changes) -> ClusterParams:
    eps, min_pts = w.SETTINGS[name]
    return ClusterParams(eps, min_pts, **changes)


def _points(spark: SparkSession, sf_dir: str, name: str) -> Points:
    return w.FIXTURES[name].points(spark, sf_dir)


def _labels(spark: SparkSession, sf_dir: str, name: str, **changes) -> DataFrame:
    return cluster(_points(spark, sf_dir, name), _params(name, **changes)).labels


def _sql(name: str, **k) -> str:
    return oracle.clusters(w.FIXTURES[name], *w.SETTINGS[name], **k)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _labels(spark, sf_dir, "part2d")


# Clusters: every method of the comparison, every workload.
for _fx, _methods in {
    "part2d": ("slab_pruned", "slab_full", "grid_full", "kdtree_pruned", "reference", "bucket_pruned"),
    "events2d": ("slab_pruned", "slab_full", "grid_full", "kdtree_pruned", "reference", "bucket_pruned"),
    "noisy3": ("slab_pruned", "slab_full", "grid_full", "kdtree_pruned", "reference"),
    "customer2d": ("slab_pruned",), "lattice4": ("slab_pruned", "kdtree_pruned"), "line7": ("slab_pruned", "slab_full", "grid_full"), "events2d_fine": ("slab_pruned",), "doc16": ("slab_pruned", "grid_full"),
    "emb10": ("slab_pruned", "slab_full"), "emb20": ("slab_pruned",), "emb30": ("slab_pruned", "grid_full"), "emb64": ("slab_pruned",), "emb40": ("slab_pruned", "kdtree_pruned"), "emb54": ("slab_pruned", "slab_full", "grid_full", "kdtree_pruned", "reference", "bucket_pruned"),
    "noisy10": ("slab_pruned",), "noisy15": ("slab_pruned",), "noisy20": ("slab_pruned",), "noisy30": ("slab_pruned",), "noisy40": ("slab_pruned", "kdtree_pruned"),
    "customer10": ("grid_full", "bucket_pruned"), "customer40": ("slab_full", "grid_full"), "customer54": ("slab_pruned", "slab_full", "grid_full", "reference"),
}.items():
    for _m in _methods:
        _add(f"clusters_{_m}_{_fx}", lambda s, d, fx=_fx, m=_m: _labels(s, d, fx, method=m), _sql(_fx))
for _fx in ("spread3", "spread10", "spread15", "spread20", "spread30", "spread40"):
    _add(f"clusters_slab_pruned_{_fx}", lambda s, d, fx=_fx: _labels(s, d, fx), _sql(_fx))
_add("clusters_border_nearest_events2d", lambda s, d: _labels(s, d, "events2d", border_rule="nearest_core"), _sql("events2d", border_rule="nearest_core"))
_add("clusters_border_all_events2d", lambda s, d: _labels(s, d, "events2d", border_rule="all"), _sql("events2d", border_rule="all"))
_add("clusters_visit_both_events2d", lambda s, d: _labels(s, d, "events2d", visit="both"), _sql("events2d"))
_add("clusters_nearest_first_events2d", lambda s, d: _labels(s, d, "events2d", order="nearest_first"), _sql("events2d"))
_add("clusters_densest_first_events2d", lambda s, d: _labels(s, d, "events2d", order="densest_first"), _sql("events2d"))
_add("clusters_many_tiles_events2d", lambda s, d: _labels(s, d, "events2d", tile_points=1500), _sql("events2d"))
_add("clusters_approx_events2d", lambda s, d: _labels(s, d, "events2d", method="grid_approx", rho=0.1))


def _sandwich(spark: SparkSession, sf_dir: str, fx: str, rho: float) -> DataFrame:
    """For each cluster at eps (low) and each at eps * (1 + rho) (high) of core points: its core points, and how many an approximate cluster leaves outside."""
    points, prm = _points(spark, sf_dir, fx), _params(fx)
    core = lambda **k: cluster(points, prm.with_(**k)).labels.where("role = 'core'").select("id", "cluster_id")
    low, mid = core(), core(method="grid_approx", rho=rho).withColumnRenamed("cluster_id", "mid")
    held = points.with_frame(points.frame.join(low.select("id"), "id", "left_semi"))
    high = cluster(held, prm.with_(eps=prm.eps * (1 + rho), min_pts=1)).labels.select("id", "cluster_id")
    split = low.join(mid, "id").groupBy("cluster_id").agg(F.count("*").alias("points"), (F.count_distinct("mid") - 1).alias("violations"))
    ends = Window.partitionBy("mid")
    wide = high.join(mid, "id").withColumn("stray", F.min("cluster_id").over(ends) < F.max("cluster_id").over(ends)).groupBy("cluster_id").agg(F.count("*").alias("points"), F.count_if("stray").alias("violations"))
    return split.select(F.lit("low").alias("side"), "*").union(wide.select(F.lit("high").alias("side"), "*"))


def _sandwich_sql(fx: str, rho: float) -> str:
    """The same from the definitions: core points by eps, their components at both radii, no violations."""
    f, (eps, min_pts) = w.FIXTURES[fx], w.SETTINGS[fx]
    wide = oracle.dist2_sql(len(f.features))
    far = oracle.base(f, eps, min_pts).replace("lab(id, root) USING KEY (id)", f"""e2 AS MATERIALIZED (SELECT a.id, b.id AS nid FROM pts a JOIN pts b ON {wide} <= {int(eps * eps * (1 + rho) ** 2 + 1e-9)} WHERE a.id IN (SELECT id FROM core) AND b.id IN (SELECT id FROM core)),
hi(id, root) USING KEY (id) AS (
    SELECT id, id FROM core
    UNION
    SELECT e.nid, min(l.root) FROM hi l JOIN e2 e ON l.id = e.id JOIN recurring.hi r ON r.id = e.nid
    WHERE l.root < r.root GROUP BY e.nid),
lab(id, root) USING KEY (id)""")
    return f"{far} SELECT 'low' AS side, root AS cluster_id, count(*) AS points, count(*) - count(id) AS violations FROM lab GROUP BY root UNION ALL SELECT 'high', root, count(*), count(*) - count(id) FROM hi GROUP BY root"


for _fx, _rho in (("events2d", 0.1), ("part2d", 0.3), ("noisy3", 0.2), ("emb54", 0.01)):
    _add(f"approx_between_{_fx}", lambda s, d, fx=_fx, rho=_rho: _sandwich(s, d, fx, rho), _sandwich_sql(_fx, _rho))
_add("clusters_brute_part2d", lambda s, d: _labels(s, d, "part2d", method="brute"), _sql("part2d"))
_add("noise_events2d", lambda s, d: relational.noise_points(_labels(s, d, "events2d")), f"{oracle.labels(w.FIXTURES['events2d'], *w.SETTINGS['events2d'])} SELECT id FROM lbl WHERE cluster_id = -1")
_add("clusters_toy", lambda s, d: _labels(s, d, "toy", border_rule="all"), _sql("toy", border_rule="all"))


# Definitions.
def _base(name: str) -> str:
    return oracle.base(w.FIXTURES[name], *w.SETTINGS[name])


def _connected(spark: SparkSession, sf_dir: str) -> DataFrame:
    points, prm = _points(spark, sf_dir, "part2d"), _params("part2d")
    ends, core = (df.agg(F.min("id"), F.max("id")).first() for df in (points.frame, relational.core_points(points, prm)))
    pairs = spark.createDataFrame(sorted({(a, b) for a in (*ends, core[0]) for b in core}), "a bigint, b bigint")
    return relational.density_connected(points, prm, pairs)


_add("eps_neighbour_counts_events2d", lambda s, d: relational.eps_neighbours(_points(s, d, "events2d"), _params("events2d")).groupBy("id").agg(F.count("*").alias("n")), f"{_base('events2d')} SELECT id, count(*) AS n FROM nb GROUP BY id")
_add("core_points_part2d", lambda s, d: relational.core_points(_points(s, d, "part2d"), _params("part2d")), f"{_base('part2d')} SELECT id FROM core")
_add("direct_reach_part2d", lambda s, d: relational.direct_reach(_points(s, d, "part2d"), _params("part2d")), f"{_base('part2d')} SELECT c.id AS core_id, n.nid AS id FROM core c JOIN nb n ON c.id = n.id")
_add("density_reachable_part2d", lambda s, d: relational.reachable_from(p := _points(s, d, "part2d"), _params("part2d"), relational.core_points(p, _params("part2d")).agg(F.min("id")).first()[0]), f"{oracle.labels(w.FIXTURES['part2d'], *w.SETTINGS['part2d'], border_rule='all')} SELECT id FROM lbl WHERE cluster_id = (SELECT min(id) FROM core)")
_add("axiom_report_part2d", lambda s, d: relational.axiom_report(_points(s, d, "part2d"), _labels(s, d, "part2d", border_rule="all"), _params("part2d")), f"""{oracle.labels(w.FIXTURES['part2d'], *w.SETTINGS['part2d'], border_rule='all')},
    due AS (SELECT l.root AS cluster_id, n.nid AS id, count(*) AS pairs FROM lab l JOIN nb n ON l.id = n.id GROUP BY 1, 2),
    met AS (SELECT due.cluster_id, sum(pairs) AS due, sum(CASE WHEN lbl.id IS NOT NULL THEN pairs ELSE 0 END) AS held FROM due LEFT JOIN lbl ON lbl.id = due.id AND lbl.cluster_id = due.cluster_id GROUP BY 1)
    SELECT cluster_id, CAST(due AS BIGINT) AS due, CAST(held AS BIGINT) AS held, (SELECT count(DISTINCT k.root) FROM lab k JOIN lbl ON lbl.id = k.id AND lbl.cluster_id = met.cluster_id AND lbl.role = 'core') AS components FROM met""")
_add("density_connected_part2d", _connected, f"{oracle.labels(w.FIXTURES['part2d'], *w.SETTINGS['part2d'], border_rule='all')} SELECT a.id AS a, b.id AS b, EXISTS (SELECT 1 FROM lbl x JOIN lbl y ON x.cluster_id = y.cluster_id WHERE x.id = a.id AND y.id = b.id AND x.cluster_id >= 0) AS connected FROM (SELECT min(id) AS id FROM pts UNION SELECT max(id) FROM pts UNION SELECT min(id) FROM core) a, (SELECT min(id) AS id FROM core UNION SELECT max(id) FROM core) b")
_add("contrast_kmeans_part2d", lambda s, d: relational.contrast_kmeans(_points(s, d, "part2d"), 10))

# Cells.
_ev = w.FIXTURES["events2d"]


def _flat_cells(cells: DataFrame, dim: int, *more: str) -> DataFrame:
    return cells.select(*[F.col("cell")[i].alias(f"c{i}") for i in range(dim)], *more)


_add("cells_events2d", lambda s, d: _flat_cells(cell_summary(_points(s, d, "events2d"), _params("events2d")), 2, "n"), f"{oracle.cells(_ev, 300)} SELECT c0, c1, n FROM cells")
_add("cell_boxes_events2d", lambda s, d: _flat_cells(cell_summary(_points(s, d, "events2d"), _params("events2d")), 2).join(_boxes(s, d), ["c0", "c1"]), f"{oracle.cells(_ev, 300)} SELECT c0, c1, min(x0) AS lo0, max(x0) AS hi0, min(x1) AS lo1, max(x1) AS hi1 FROM spot GROUP BY c0, c1")
_add("cell_ids_events2d", lambda s, d: _flat_cells(cell_summary(_points(s, d, "events2d"), _params("events2d")), 2, "gid"), f"{oracle.cells(_ev, 300)} SELECT c0, c1, row_number() OVER (ORDER BY c0, c1) AS gid FROM cells")
_add("cell_diameter_events2d", lambda s, d: _flat_cells(verify_cell_diameter(cell_summary(_points(s, d, "events2d"), _params("events2d")), _params("events2d")), 2, "diagonal2"), f"{oracle.cells(_ev, 300)} SELECT c0, c1, (max(x0) - min(x0)) ** 2 AS diagonal2 FROM spot GROUP BY c0, c1 HAVING (max(x0) - min(x0)) * (max(x0) - min(x0)) + (max(x1) - min(x1)) * (max(x1) - min(x1)) > 90000")
_add("fold_duplicates_lattice4", lambda s, d: fold_duplicates(_points(s, d, "lattice4")).select(*[F.col("coord")[i].alias(f"x{i}") for i in range(4)], "weight", "id"), f"WITH pts AS ({w.FIXTURES['lattice4'].select()}) SELECT x0, x1, x2, x3, count(*) AS weight, min(id) AS id FROM pts GROUP BY x0, x1, x2, x3")
_add("cell_stats_spread3", lambda s, d: cell_summary(_points(s, d, "spread3"), _params("spread3")).agg(F.count("*").alias("cells"), *[F.count_distinct(F.col("cell")[i]).alias(f"k{i}") for i in range(3)]), f"{oracle.cells(w.FIXTURES['spread3'], 30)} SELECT count(*) AS cells, count(DISTINCT c0) AS k0, count(DISTINCT c1) AS k1, count(DISTINCT c2) AS k2 FROM cells")
_add("cell_curve_events2d", lambda s, d: cell_curve(_points(s, d, "events2d"), [75, 150, 300, 600, 1200]), " UNION ALL ".join(f"(WITH q{e} AS ({oracle.cells(_ev, e)} SELECT count(*) AS cells FROM cells) SELECT CAST({e} AS DOUBLE) AS eps, cells FROM q{e})" for e in (75, 150, 300, 600, 1200)))
def _offset_sql() -> str:
    """Every offset of the box, its gaps' squares added up; and the cells that a method probing them would ask from."""
    one = []
    for d in range(1, 8):
        r = math.ceil(math.sqrt(d))
        box = ", ".join(f"generate_series(-{r}, {r}) o{i}(x{i})" for i in range(d))
        gap = " + ".join(f"greatest(abs(x{i}) - 1, 0) * greatest(abs(x{i}) - 1, 0)" for i in range(d))
        counts = f"SELECT count(*) AS box, count(*) FILTER ({gap} < {d}) - 1 AS reachable FROM {box}"
        cells = oracle.cells(_first_features(d), w.SETTINGS["customer10"][0])
        one.append(f"(SELECT CAST({d} AS INTEGER) AS d, CAST(ceil(sqrt({d})) AS INTEGER) AS reach, CAST(box AS VARCHAR) AS box, CAST(reachable AS VARCHAR) AS reachable, n AS cells, CAST(n * reachable AS VARCHAR) AS probes FROM ({counts}), ({cells} SELECT count(*) AS n FROM cells))")
    return " UNION ALL ".join(one)


def _first_features(d: int) -> w.Fixture:
    fx = w.FIXTURES["customer10"]
    return w.Fixture(fx.table, fx.id, fx.features[:d])


_add("offset_counts", lambda s, d: measures.offset_probes([_first_features(k).points(s, d) for k in range(1, 8)], w.SETTINGS["customer10"][0]), _offset_sql())


def _boxes(spark: SparkSession, sf_dir: str) -> DataFrame:
    cells = cell_summary(_points(spark, sf_dir, "events2d"), _params("events2d"))
    return cells.select(*[F.col(c)[i].alias(f"{n}{i}") for c, n in (("cell", "c"), ("lo", "lo"), ("hi", "hi")) for i in range(2)])


# Neighbour cells: every index, the same pairs.
def _cell_pairs(spark: SparkSession, sf_dir: str, name: str, find, rule: str = "exact") -> DataFrame:
    fx, prm = w.FIXTURES[name], _params(name, corner_rule=rule)
    d = len(fx.features)
    cells = cell_summary(_points(spark, sf_dir, name), prm)
    pairs = find(cells, d, prm)
    for s in "ab":
        pairs = pairs.join(cells.select(F.col("gid").alias(f"gid_{s}"), *[F.col("cell")[i].alias(f"{s}{i}") for i in range(d)]), f"gid_{s}")
    return pairs.drop("gid_a", "gid_b")


def _tile_pairs(spark: SparkSession, sf_dir: str, name: str, method: str, rule: str = "exact") -> DataFrame:
    points, prm = _points(spark, sf_dir, name), _params(name, method=method, corner_rule=rule)
    at, pairs = assign_cells(points, prm), measures.neighbour_pairs(points, prm)
    for s in "ab":
        pairs = pairs.join(at.select(F.col("id").alias(s), *[F.col("cell")[i].alias(f"{s}{i}") for i in range(points.dim)]), s)
    return pairs.drop("a", "b")


for _rule in ("exact", "box"):
    _tail, _q = "" if _rule == "exact" else "_box", oracle.neighbour_cells(w.FIXTURES["part2d"], 150, _rule)
    _add(f"neighbour_cells_offsets_part2d{_tail}", lambda s, d, r=_rule: _cell_pairs(s, d, "part2d", neighbours.neighbours_by_offsets, r), _q)
    _add(f"neighbour_cells_slab_sql_part2d{_tail}", lambda s, d, r=_rule: _cell_pairs(s, d, "part2d", neighbours.neighbours_by_slabs_sql, r), _q)
    _add(f"neighbour_cells_slabs_part2d{_tail}", lambda s, d, r=_rule: _tile_pairs(s, d, "part2d", "slab_pruned", r), _q)
    _add(f"neighbour_cells_buckets_part2d{_tail}", lambda s, d, r=_rule: _cell_pairs(s, d, "part2d", neighbours.neighbours_by_buckets, r), _q)
_add("neighbour_cells_kdtree_part2d", lambda s, d: _tile_pairs(s, d, "part2d", "kdtree_pruned"), oracle.neighbour_cells(w.FIXTURES["part2d"], 150))
_add("neighbour_cells_slabs_events2d", lambda s, d: _tile_pairs(s, d, "events2d", "slab_pruned"), oracle.neighbour_cells(_ev, 300))
_add("neighbour_cells_buckets_noisy3", lambda s, d: _cell_pairs(s, d, "noisy3", neighbours.neighbours_by_buckets), oracle.neighbour_cells(w.FIXTURES["noisy3"], 30))
_add("slab_rows_events2d", lambda s, d: neighbours.build_slabs(cell_summary(_points(s, d, "events2d"), _params("events2d"))).groupBy("dim", "pos").agg(F.sum(F.bitmap_count("bits")).alias("popcount")), f"{oracle.cells(_ev, 300)} SELECT CAST(0 AS INTEGER) AS dim, c0 AS pos, count(*) AS popcount FROM cells GROUP BY c0 UNION ALL SELECT 1, c1, count(*) FROM cells GROUP BY c1")
_add("slab_stats_emb40", lambda s, d: measures.slab_stats(neighbours.build_slabs(cell_summary(_points(s, d, "emb40"), _params("emb40")))).select("dim", "positions"), f"{oracle.cells(w.FIXTURES['emb40'], 8300)} " + " UNION ALL ".join(f"SELECT CAST({i} AS INTEGER) AS dim, count(DISTINCT c{i}) AS positions FROM cells" for i in range(40)))
for _fx, _eps in {"emb40": (7900, 8300, 8700, 9200, 9600), "emb54": (9500, 9900, 10300, 10700, 11100), "customer40": (140, 150, 160, 170, 180), "events2d": (75, 150, 300, 600, 1200)}.items():
    _add(f"index_sweep_{_fx}", lambda s, d, fx=_fx, e=_eps: measures.index_report(_points(s, d, fx), _params(fx), ["slab_pruned", "kdtree_pruned"], list(e)))


# Labelling and merging.
def _core_cells(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    points, prm = _points(spark, sf_dir, name), _params(name)
    flagged = run_tiles(deal(points.frame, plan_tiles(points, prm), points.dim, prm.eps, safe_reach(points.dim)), label_tile, "id long, coord array<bigint>, core boolean", prm, points.dim, True)
    return assign_cells(points.with_frame(flagged), prm).groupBy("cell").agg(F.bool_or("core").alias("is_core"))


_add("core_cells_events2d", lambda s, d: _flat_cells(_core_cells(s, d, "events2d"), 2, "is_core"), f"{_base('events2d')}, spot AS ({oracle.cells(_ev, 300)} SELECT * FROM spot) SELECT c0, c1, bool_or(id IN (SELECT id FROM core)) AS is_core FROM spot GROUP BY c0, c1")
_add("core_components_events2d", lambda s, d: _labels(s, d, "events2d").where("role = 'core'").select("id", F.col("cluster_id").alias("root")), f"{_base('events2d')} SELECT id, root FROM lab")


def _merge_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    points, prm = _points(spark, sf_dir, "events2d"), _params("events2d")
    core = relational.core_points(points, prm)
    at = assign_cells(points, prm).join(core, "id", "left_semi").select("id", "cell")
    near = relational.eps_neighbours(points, prm).join(at.toDF("id", "a"), "id").join(at.toDF("nbr_id", "b"), "nbr_id")
    return near.where("a < b").select(*[F.col(s)[i].alias(f"{s}{i}") for s in "ab" for i in range(2)]).distinct()


_add("merge_edges_full_events2d", _merge_edges, f"{_base('events2d')}, spot AS ({oracle.cells(_ev, 300)} SELECT * FROM spot) SELECT DISTINCT a.c0 AS a0, a.c1 AS a1, b.c0 AS b0, b.c1 AS b1 FROM ee JOIN spot a ON ee.id = a.id JOIN spot b ON ee.nid = b.id WHERE (a.c0, a.c1) < (b.c0, b.c1)")
for _fx in ("spread3", "events2d", "emb54", "customer54"):
    _add(f"merge_counts_{_fx}", lambda s, d, fx=_fx: measures.merge_counts(_points(s, d, fx), _params(fx, visit="both", box_prune=False), ["grid_full", "slab_full", "slab_pruned"]))
    _add(f"merge_ratio_{_fx}", lambda s, d, fx=_fx: measures.merge_ratio(measures.merge_counts(_points(s, d, fx), _params(fx, visit="both", box_prune=False), ["grid_full", "slab_full", "slab_pruned"]), "grid_full"))
for _fx in ("noisy3", "events2d", "emb54"):
    _add(f"merge_bounds_{_fx}", lambda s, d, fx=_fx: measures.merge_counts(_points(s, d, fx), _params(fx, box_prune=False), ["grid_full", "slab_full", "slab_pruned"]).select("variant", "core_cells", "considered", F.when(F.col("variant").endswith("full"), F.col("checks")).alias("full_checks"), "needed"), oracle.merge_bounds(w.FIXTURES[_fx], *w.SETTINGS[_fx], ("grid_full", "slab_full"), ("slab_pruned",)))
_add("union_ablation_events2d", lambda s, d: measures.union_ablation(_points(s, d, "events2d"), _params("events2d")))


def _forest(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Components of the links from each customer to the next richer one of its nation and segment, the richest to itself."""
    rows = load_table(spark, sf_dir, "customer")
    richer = F.lead("c_custkey").over(Window.partitionBy("c_nationkey", "c_mktsegment").orderBy("c_acctbal", "c_custkey"))
    return components(rows.select(F.col("c_custkey").alias("a"), F.coalesce(richer, "c_custkey").alias("b")))


_add("components_forest6", _forest, "SELECT c_custkey AS node, min(c_custkey) OVER (PARTITION BY c_nationkey, c_mktsegment) AS root FROM customer")

# Measures.
_add("partition_equality_events2d", lambda s, d: measures.partition_report(_labels(s, d, "events2d"), _labels(s, d, "events2d", method="grid_full")), f"{oracle.labels(_ev, *w.SETTINGS['events2d'])} SELECT cluster_id, role, count(*) AS points, count(*) AS same FROM lbl GROUP BY cluster_id, role")
_add("approx_agreement_events2d", lambda s, d: measures.agreement(_labels(s, d, "events2d", method="grid_approx", rho=0.001), _labels(s, d, "events2d")))
_add("dataset_stats_part2d", lambda s, d: measures.dataset_stats(_points(s, d, "part2d"), _labels(s, d, "part2d")), f"{oracle.labels(w.FIXTURES['part2d'], *w.SETTINGS['part2d'])} SELECT (SELECT count(*) FROM pts) AS n, CAST(2 AS INTEGER) AS d, count(DISTINCT cluster_id) FILTER (cluster_id >= 0) AS clusters FROM lbl")
_METHODS = ["reference", "grid_full", "grid_approx", "slab_full", "slab_pruned"]
for _fx in ("part2d", "customer3", "customer10", "customer30", "customer40", "emb54"):
    _add(f"method_seconds_{_fx}", lambda s, d, fx=_fx: measures.bench(_points(s, d, fx), fx, _params(fx), _METHODS, repeats=3, limit_s=60))
_add("speedups_customer54", lambda s, d: measures.speedup(measures.bench(_points(s, d, "customer54"), "customer54", _params("customer54"), _METHODS, repeats=1, limit_s=60), "grid_full"))


def _scalability(spark: SparkSession, sf_dir: str, d: int) -> DataFrame:
    """The generator's twin over all rows of three tables; a run of more than ten seconds is stopped and says so."""
    sets = {f"{t}{d}": (_points(spark, sf_dir, f"{t}{d}"), _params(f"{t}{d}")) for t in w.SIZES}
    return measures.scalability_grid(sets, ["slab_full", "slab_pruned"], limit_s=10)


for _d in (10, 15, 20):
    _add(f"scalability_{_d}d", lambda s, d, n=_d: _scalability(s, d, n))
_add("generated_drift10", lambda s, d: drift_clusters(s, None, 10, 10, ids=load_table(s, d, "orders").select(F.col("o_orderkey").alias("id")))[0].frame)

# Reports and the relational surface.
_lbl = f"{oracle.labels(_ev, *w.SETTINGS['events2d'])}"


def _labelled_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = load_table(spark, sf_dir, "events").withColumnRenamed("event_id", "id")
    return events.join(_labels(spark, sf_dir, "events2d"), "id")


_add("cluster_profile_part2d", lambda s, d: profile.cluster_profile(_labels(s, d, "part2d"), _points(s, d, "part2d")).select("cluster_id", "size", "core", "border", *[F.col(c)[i].alias(f"{c}{i}") for c in ("sum", "lo", "hi") for i in range(2)]), f"{oracle.labels(w.FIXTURES['part2d'], *w.SETTINGS['part2d'])} SELECT cluster_id, count(*) AS size, count(*) FILTER (role = 'core') AS core, count(*) FILTER (role = 'border') AS border, CAST(sum(x0) AS BIGINT) AS sum0, CAST(sum(x1) AS BIGINT) AS sum1, min(x0) AS lo0, min(x1) AS lo1, max(x0) AS hi0, max(x1) AS hi1 FROM lbl JOIN pts USING (id) GROUP BY cluster_id")
_add("profile_rollup_events2d", lambda s, d: _labelled_events(s, d).rollup("role", "event_type").agg(F.count("*").alias("n")), f"{_lbl} SELECT role, event_type, count(*) AS n FROM lbl JOIN events ON lbl.id = event_id GROUP BY ROLLUP (role, event_type)")
_add("profile_cube_events2d", lambda s, d: _labelled_events(s, d).cube("role", "event_type").agg(F.count("*").alias("n"), F.count_distinct("user_id").alias("users")), f"{_lbl} SELECT role, event_type, count(*) AS n, count(DISTINCT user_id) AS users FROM lbl JOIN events ON lbl.id = event_id GROUP BY CUBE (role, event_type)")
_add("largest_clusters_events2d", lambda s, d: _labels(s, d, "events2d").where("cluster_id >= 0").groupBy("cluster_id").agg(F.count("*").alias("size")).orderBy(F.desc("size"), "cluster_id").limit(10), f"{_lbl} SELECT cluster_id, count(*) AS size FROM lbl WHERE cluster_id >= 0 GROUP BY cluster_id ORDER BY size DESC, cluster_id LIMIT 10")
_add("cluster_ranks_part2d", lambda s, d: _labels(s, d, "part2d").where("cluster_id >= 0").join(load_table(s, d, "part").select(F.col("p_partkey").alias("id"), "p_size"), "id").select("cluster_id", "id", F.rank().over(Window.partitionBy("cluster_id").orderBy("p_size")).cast("long").alias("rnk"), F.lag("id").over(Window.partitionBy("cluster_id").orderBy("id")).alias("before"), F.count("*").over(Window.partitionBy("cluster_id").orderBy("id").rowsBetween(Window.unboundedPreceding, 0)).alias("so_far")), f"{oracle.labels(w.FIXTURES['part2d'], *w.SETTINGS['part2d'])} SELECT cluster_id, id, rank() OVER (PARTITION BY cluster_id ORDER BY p_size) AS rnk, lag(id) OVER (PARTITION BY cluster_id ORDER BY id) AS before, count(*) OVER (PARTITION BY cluster_id ORDER BY id ROWS UNBOUNDED PRECEDING) AS so_far FROM lbl JOIN part ON id = p_partkey WHERE cluster_id >= 0")
_add("core_minus_noise_parts", lambda s, d: load_table(s, d, "part").select(F.col("p_partkey").alias("id")).exceptAll(relational.noise_points(_labels(s, d, "part2d"))), f"{oracle.labels(w.FIXTURES['part2d'], *w.SETTINGS['part2d'])} SELECT p_partkey AS id FROM part EXCEPT ALL SELECT id FROM lbl WHERE cluster_id = -1")
_add("clustered_users_semi", lambda s, d: load_table(s, d, "events").join(_labels(s, d, "events2d").where("role = 'core'").withColumnRenamed("id", "event_id"), "event_id", "left_semi").select("user_id").distinct(), f"{_lbl} SELECT DISTINCT user_id FROM events WHERE event_id IN (SELECT id FROM lbl WHERE role = 'core')")
_add("noise_share_by_day", lambda s, d: _labelled_events(s, d).groupBy(F.to_date("ts").alias("day")).agg(F.count_if(F.col("role") == "noise").alias("noise"), F.count("*").alias("n")), f"{_lbl} SELECT CAST(ts AS DATE) AS day, count(*) FILTER (role = 'noise') AS noise, count(*) AS n FROM lbl JOIN events ON lbl.id = event_id GROUP BY 1")
_add("json_feature_clusters", lambda s, d: _labelled_events(s, d).where("role = 'core'").groupBy(F.get_json_object("props", "$.k").cast("long").alias("k")).agg(F.count("*").alias("n")), f"{_lbl} SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM lbl JOIN events ON lbl.id = event_id WHERE role = 'core' GROUP BY 1")
_add("k_distance_part2d", lambda s, d: profile.k_distance(_points(s, d, "part2d"), 4, 400), f"WITH pts AS ({w.FIXTURES['part2d'].select()}), nb AS (SELECT a.id, {oracle.dist2_sql(2)} AS dist2, row_number() OVER (PARTITION BY a.id ORDER BY {oracle.dist2_sql(2)}, b.id) AS turn FROM pts a, pts b) SELECT id, dist2 FROM nb WHERE turn = 4")
_add("suggest_eps_part2d", lambda s, d: profile.suggest_eps(_points(s, d, "part2d"), 4, 400))


def _latest_core(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each event with its user's latest core event at that time or before."""
    rows = _labelled_events(spark, sf_dir)
    marks = rows.where("role = 'core'").select("user_id", "ts", F.col("id").alias("core_id"))
    return profile.latest_before(rows.select("id", "user_id", "ts"), marks, "user_id", "ts", "core_id").select("id", "core_id")


_add("asof_latest_core_event", _latest_core, f"{_lbl}, mark AS (SELECT user_id, ts, max(id) AS core_id FROM lbl JOIN events ON id = event_id WHERE role = 'core' GROUP BY ALL) SELECT e.event_id AS id, m.core_id FROM events e ASOF LEFT JOIN mark m ON e.user_id = m.user_id AND e.ts >= m.ts")


def _grouping_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    _labelled_events(spark, sf_dir).createOrReplaceTempView("densegrid_labelled")
    return spark.sql("SELECT role, event_type, count(*) AS n, CAST(grouping_id(role, event_type) AS BIGINT) AS level FROM densegrid_labelled GROUP BY GROUPING SETS ((role, event_type), (role), ())")


_add("profile_grouping_sets_events2d", _grouping_sets, f"{_lbl} SELECT role, event_type, count(*) AS n, CAST(grouping_id(role, event_type) AS BIGINT) AS level FROM lbl JOIN events ON lbl.id = event_id GROUP BY GROUPING SETS ((role, event_type), (role), ())")


def _frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = _labels(spark, sf_dir, "part2d").where("cluster_id >= 0").join(load_table(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"), F.col("p_size").cast("long").alias("size")), "id")
    by = Window.partitionBy("cluster_id").orderBy("size", "id")
    near = Window.partitionBy("cluster_id").orderBy("size").rangeBetween(-5, 5)
    return rows.select("id", F.row_number().over(by).cast("long").alias("place"), F.dense_rank().over(Window.partitionBy("cluster_id").orderBy("size")).cast("long").alias("dense"), F.ntile(4).over(by).cast("long").alias("quarter"), F.first_value("id").over(by).alias("first_id"), F.lead("id").over(by).alias("next_id"), F.count("*").over(near).alias("alike"), F.sum("size").over(by.rowsBetween(-2, 2)).alias("around"))


_add("cluster_frames_part2d", _frames, f"{oracle.labels(w.FIXTURES['part2d'], *w.SETTINGS['part2d'])} SELECT id, row_number() OVER b AS place, dense_rank() OVER (PARTITION BY cluster_id ORDER BY p_size) AS dense, ntile(4) OVER b AS quarter, first_value(id) OVER b AS first_id, lead(id) OVER b AS next_id, count(*) OVER (PARTITION BY cluster_id ORDER BY p_size RANGE BETWEEN 5 PRECEDING AND 5 FOLLOWING) AS alike, CAST(sum(p_size) OVER (PARTITION BY cluster_id ORDER BY p_size, id ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS BIGINT) AS around FROM lbl JOIN part ON id = p_partkey WHERE cluster_id >= 0 WINDOW b AS (PARTITION BY cluster_id ORDER BY p_size, id)")
_add("same_role_intersect_events2d", lambda s, d: _labels(s, d, "events2d").where("role = 'core'").select("id").intersect(_labels(s, d, "events2d_fine").where("role = 'core'").select("id")).union(_labels(s, d, "events2d").where("role = 'noise'").select("id").intersect(_labels(s, d, "events2d_fine").where("role = 'noise'").select("id"))), f"WITH a AS ({_sql('events2d')}), b AS ({_sql('events2d_fine')}) SELECT id FROM a WHERE role = 'core' INTERSECT SELECT id FROM b WHERE role = 'core' UNION ALL (SELECT id FROM a WHERE role = 'noise' INTERSECT SELECT id FROM b WHERE role = 'noise')")
_add("points_in_box_events2d", lambda s, d: neighbours.in_box(_points(s, d, "events2d"), [5000, 1000], [20000, 4000]).select("id"), f"WITH pts AS ({_ev.select()}) SELECT id FROM pts WHERE x0 BETWEEN 5000 AND 20000 AND x1 BETWEEN 1000 AND 4000")
_add("points_in_ball_events2d", lambda s, d: neighbours.in_ball(_points(s, d, "events2d"), [20000, 3000], 2500).select("id", "dist2"), f"WITH pts AS ({_ev.select()}) SELECT id, (x0 - 20000) * (x0 - 20000) + (x1 - 3000) * (x1 - 3000) AS dist2 FROM pts WHERE (x0 - 20000) * (x0 - 20000) + (x1 - 3000) * (x1 - 3000) <= 6250000")


def _one_cell(spark: SparkSession, sf_dir: str) -> DataFrame:
    cells = cell_summary(_points(spark, sf_dir, "events2d"), _params("events2d"))
    fullest = cells.orderBy(F.desc("n"), "gid").first()["gid"]
    return _flat_cells(neighbours.neighbours_of(cells, fullest, 2, _params("events2d")), 2)


_add("neighbours_of_fullest_events2d", _one_cell, f"{oracle.cells(_ev, 300)} SELECT b.c0, b.c1 FROM (SELECT * FROM cells ORDER BY n DESC, c0, c1 LIMIT 1) a JOIN cells b ON greatest(abs(a.c0 - b.c0) - 1, 0) ** 2 + greatest(abs(a.c1 - b.c1) - 1, 0) ** 2 < 2 AND (a.c0 <> b.c0 OR a.c1 <> b.c1)")
_add("scaled_features_part2d", lambda s, d: cluster(scale_features(_points(s, d, "part2d"), [0.5, 0.5], [100, 90000]), ClusterParams(75, 4)).labels, _sql("part2d"))
_add("clusters_folded_lattice4", lambda s, d: _labels(s, d, "lattice4", fold=True), _sql("lattice4"))
_add("clusters_folded_part2d", lambda s, d: _labels(s, d, "part2d", fold=True), _sql("part2d"))


def _inserted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All parts, put in by thirds."""
    points, prm = _points(spark, sf_dir, "part2d"), _params("part2d")
    state = incremental.empty_state(points)
    for k in range(3):
        state = incremental.insert_points(state, points.with_frame(points.frame.where(F.pmod("id", F.lit(3)) == k)), prm)
    return incremental.state_labels(state, points, prm)


_add("clusters_incremental_part2d", _inserted, _sql("part2d"))


def _assign(spark: SparkSession, sf_dir: str) -> DataFrame:
    prm = _params("part2d")
    return profile.assign_new(cluster(_points(spark, sf_dir, "part2d"), prm).core, _FRESH.points(spark, sf_dir), prm)


#: Points that the model has not seen: every part, a little off its place.
_FRESH = w.Fixture("part", "p_partkey", ("p_size * 100 + 37", "round(p_retailprice * 100) + 53"))


def _assign_sql() -> str:
    near = f"{oracle.dist2_sql(2)} <= 22500"
    return f"{_base('part2d')}, fresh AS ({_FRESH.select()}) SELECT a.id, coalesce(arg_min(l.root, ({oracle.dist2_sql(2)}, l.root)), -1) AS cluster_id FROM fresh a LEFT JOIN (lab l JOIN pts b ON l.id = b.id) ON {near} GROUP BY a.id"


_add("assign_new_part2d", _assign, _assign_sql())


def _by_type(spark: SparkSession, sf_dir: str) -> DataFrame:
    register(spark)
    kinds = load_table(spark, sf_dir, "events").select(F.col("event_id").alias("id"), "event_type")
    _points(spark, sf_dir, "events2d").frame.join(kinds, "id").createOrReplaceTempView("densegrid_events")
    return spark.sql("SELECT id, cluster_id, role FROM dense_clusters(TABLE(densegrid_events) PARTITION BY (event_type), 600, 8)")


def _by_type_sql() -> str:
    near = f"{oracle.dist2_sql(2)} <= 360000 AND a.t = b.t"
    fx = _ev.select().replace(" FROM events", ", event_type AS t FROM events")
    chain = oracle.labels(_ev, 600, 8)
    return chain.replace(_ev.select(), fx).replace(f"ON {oracle.dist2_sql(2)} <= 360000", f"ON {near}") + " SELECT id, cluster_id, role FROM lbl"


_add("clusters_by_event_type_udtf", _by_type, _by_type_sql())

# Streams.
_add("stream_window_cell_counts", lambda s, d: windows.drain(windows.window_cell_counts(windows.event_stream(s, d)), "densegrid_windows").withColumn("start", F.date_format("start", "yyyy-MM-dd")), "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS start, CAST(floor(round(value * 100) / 5000) AS BIGINT) AS cell, count(*) AS n FROM events GROUP BY 1, 2")
_add("batch_window_cell_counts", lambda s, d: windows.window_cell_counts(load_table(s, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))).withColumn("start", F.date_format("start", "yyyy-MM-dd")), _SQL["stream_window_cell_counts"])
_add("stream_sliding_counts", lambda s, d: windows.drain(windows.window_cell_counts(windows.event_stream(s, d), "2 days", slide="1 day"), "densegrid_sliding").withColumn("start", F.date_format("start", "yyyy-MM-dd")), "SELECT strftime(day - to_days(k), '%Y-%m-%d') AS start, cell, count(*) AS n FROM (SELECT date_trunc('day', ts) AS day, CAST(floor(round(value * 100) / 5000) AS BIGINT) AS cell FROM events), (VALUES (0), (1)) t(k) GROUP BY 1, 2")
_add("stream_dense_cells", lambda s, d: windows.drain(windows.dense_cells(windows.event_stream(s, d), 50), "densegrid_dense", "append"), "SELECT cell, CAST(50 AS BIGINT) AS n FROM (SELECT CAST(floor(round(value * 100) / 5000) AS BIGINT) AS cell FROM events) GROUP BY cell HAVING count(*) >= 50")


def queries() -> dict[str, Query]:
    return dict(_QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(_SQL)

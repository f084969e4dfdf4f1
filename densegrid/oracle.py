"""DuckDB SQL for the same results, from the definitions: all pairs, keyed recursion for components."""

from __future__ import annotations

from densegrid.functions.geometry import cell_scale, eps2
from densegrid.workloads import Fixture


def dist2_sql(d: int, a: str = "a", b: str = "b") -> str:
    return " + ".join(f"({a}.x{i} - {b}.x{i}) * ({a}.x{i} - {b}.x{i})" for i in range(d))


def base(fx: Fixture, eps: float, min_pts: int) -> str:
    """pts, nb (id, nid, d2), core (id), lab (id, root): the chain that most queries start from."""
    d = len(fx.features)
    return f"""WITH RECURSIVE pts AS MATERIALIZED ({fx.select()}),
nb AS MATERIALIZED (SELECT a.id, b.id AS nid, {dist2_sql(d)} AS d2 FROM pts a JOIN pts b ON {dist2_sql(d)} <= {eps2(eps, True)} AND abs(a.x0 - b.x0) <= {int(eps)}),
core AS MATERIALIZED (SELECT id FROM nb GROUP BY id HAVING count(*) >= {min_pts}),
ee AS MATERIALIZED (SELECT n.id, n.nid FROM nb n JOIN core c ON n.id = c.id JOIN core e ON n.nid = e.id),
lab(id, root) USING KEY (id) AS (
    SELECT id, id FROM core
    UNION
    SELECT e.nid, min(l.root) FROM lab l JOIN ee e ON l.id = e.id JOIN recurring.lab r ON r.id = e.nid
    WHERE l.root < r.root GROUP BY e.nid)"""


_BORDER = {
    "min_cluster": "SELECT n.id, min(l.root) AS root FROM nb n JOIN lab l ON n.nid = l.id WHERE n.id NOT IN (SELECT id FROM core) GROUP BY n.id",
    "nearest_core": "SELECT n.id, arg_min(l.root, (n.d2, l.root)) AS root FROM nb n JOIN lab l ON n.nid = l.id WHERE n.id NOT IN (SELECT id FROM core) GROUP BY n.id",
    "all": "SELECT DISTINCT n.id, l.root FROM nb n JOIN lab l ON n.nid = l.id WHERE n.id NOT IN (SELECT id FROM core)",
}


def labels(fx: Fixture, eps: float, min_pts: int, border_rule: str = "min_cluster") -> str:
    """Adds lbl (id, cluster_id, role)."""
    return f"""{base(fx, eps, min_pts)},
border AS ({_BORDER[border_rule]}),
lbl AS (
    SELECT id, root AS cluster_id, 'core' AS role FROM lab
    UNION ALL SELECT id, root, 'border' FROM border
    UNION ALL SELECT id, -1, 'noise' FROM pts WHERE id NOT IN (SELECT id FROM lab) AND id NOT IN (SELECT id FROM border))"""


def clusters(fx: Fixture, eps: float, min_pts: int, border_rule: str = "min_cluster") -> str:
    return f"{labels(fx, eps, min_pts, border_rule)}\nSELECT id, cluster_id, role FROM lbl"


def cells(fx: Fixture, eps: float) -> str:
    """WITH pts, spot (id, x.., c..), cells (c.., n)."""
    d = len(fx.features)
    c = format(cell_scale(d, eps), ".17e")
    at = ", ".join(f"CAST(floor(CAST(x{i} AS DOUBLE) * {c}) AS BIGINT) AS c{i}" for i in range(d))
    keys = ", ".join(f"c{i}" for i in range(d))
    return f"WITH pts AS MATERIALIZED ({fx.select()}), spot AS MATERIALIZED (SELECT *, {at} FROM pts), cells AS MATERIALIZED (SELECT {keys}, count(*) AS n FROM spot GROUP BY {keys})"


def neighbour_cells(fx: Fixture, eps: float, rule: str = "exact") -> str:
    d = len(fx.features)
    gap = " + ".join(f"greatest(abs(a.c{i} - b.c{i}) - 1, 0) * greatest(abs(a.c{i} - b.c{i}) - 1, 0)" for i in range(d))
    r = int(-(-(d**0.5) // 1))
    near = f"{gap} < {d}" if rule == "exact" else " AND ".join(f"abs(a.c{i} - b.c{i}) <= {r}" for i in range(d))
    differ = " OR ".join(f"a.c{i} <> b.c{i}" for i in range(d))
    cols = ", ".join(f"{s}.c{i} AS {s}{i}" for s in "ab" for i in range(d))
    return f"{cells(fx, eps)} SELECT {cols} FROM cells a JOIN cells b ON {near} AND ({differ})"


def merge_bounds(fx: Fixture, eps: float, min_pts: int, full: tuple[str, ...], pruned: tuple[str, ...]) -> str:
    """A row for each method: core cells, pairs of them that the strict corner rule calls near (each once), checks of the methods that skip none, unions that one forest makes."""
    d = len(fx.features)
    c = format(cell_scale(d, eps), ".17e")
    at = ", ".join(f"CAST(floor(CAST(x{i} AS DOUBLE) * {c}) AS BIGINT) AS c{i}" for i in range(d))
    gap = " + ".join(f"greatest(abs(a.c{i} - b.c{i}) - 1, 0) * greatest(abs(a.c{i} - b.c{i}) - 1, 0)" for i in range(d))
    row = lambda c: f"({', '.join(f'{c}.c{i}' for i in range(d))})"
    rows = " UNION ALL ".join(f"SELECT '{m}' AS variant, core_cells, considered, {'considered' if m in full else 'CAST(NULL AS BIGINT)'} AS full_checks, core_cells - clusters AS needed FROM n" for m in full + pruned)
    return f"""{base(fx, eps, min_pts)},
held AS MATERIALIZED (SELECT DISTINCT {", ".join(f"c{i}" for i in range(d))} FROM (SELECT {at} FROM pts WHERE id IN (SELECT id FROM core))),
n AS MATERIALIZED (SELECT (SELECT count(*) FROM held) AS core_cells, (SELECT count(*) FROM held a JOIN held b ON {gap} < {d} AND {row("a")} < {row("b")}) AS considered, (SELECT count(DISTINCT root) FROM lab) AS clusters)
{rows}"""

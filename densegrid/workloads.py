"""The experiment workloads on the given tables (FIXTURES F0 to F3), in the terms of both engines."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from densegrid.sources.points import Points, as_points, load_table


@dataclass(frozen=True)
class Fixture:
    """A table, an id and whole-numbered features; {DIV} and {AT} differ between the engines."""

    table: str
    id: str
    features: tuple[str, ...]
    where: str = ""

    def text(self, expr: str, duckdb: bool) -> str:
        return expr.replace("{DIV}", "//" if duckdb else "div").replace("{MINUTE}", "date_diff('minute', timestamp '2024-01-01', ts)" if duckdb else "timestampdiff(MINUTE, timestamp_ntz'2024-01-01 00:00:00', ts)").replace("{DAY}", "date_diff('day', date '1995-01-01', l_shipdate::date)" if duckdb else "datediff(to_date(l_shipdate), date'1995-01-01')")

    def points(self, spark: SparkSession, sf_dir: str) -> Points:
        df = load_table(spark, sf_dir, self.table)
        if self.where:
            df = df.where(self.where)
        return as_points(df, self.text(self.id, False), [self.text(f, False) for f in self.features])

    def select(self) -> str:
        """DuckDB: id, x0, x1, ... as whole numbers."""
        cols = ", ".join(f"CAST({self.text(f, True)} AS BIGINT) AS x{i}" for i, f in enumerate(self.features))
        return f"SELECT CAST({self.text(self.id, True)} AS BIGINT) AS id, {cols} FROM {self.table}" + (f" WHERE {self.where}" if self.where else "")


def spread(d: int, table: str = "orders", key: str = "o_orderkey", where: str = "", noisy: bool = False, id: str = "") -> Fixture:
    """The generator's twin in whole-number arithmetic: ten drifting clusters by key."""
    k, out = f"cast({key} as bigint)", []
    for i in range(d):
        mul = (7368787 * i + 2654435) % 1000003
        centre = f"1000 + (({k} % 10) * {7919 + 104729 * i} + {31337 * i * i + 17}) % 9000"
        step = f"((({k} {{DIV}} 10) {{DIV}} 3) * {((2 * i + 1) * 48271) % 65521} + {977 * i}) % 65521 % 3 - 1"
        x = f"{centre} + 5 * ({step}) + ({k} * {mul} + {12345 * i}) % 1000003 % 61 - 30"
        if noisy:
            x = f"CASE WHEN {k} % 97 = 0 THEN 1000 + ({k} * {mul} + {54321 * i + 7}) % 1000003 % 9001 ELSE {x} END"
        out.append(x)
    return Fixture(table, id or key, tuple(out), where)


class Embedding(Fixture):
    """The first k elements of the vectors, in units of 1e-4."""

    def text(self, expr: str, duckdb: bool) -> str:
        if expr.isdigit():
            return f"round(cast(embedding[{int(expr) + duckdb}] as double) * 10000)"
        return expr


class Grams(Fixture):
    """Whole texts as hashed word features: in thousandths, the share of words whose length and ends fall into each bin."""

    def text(self, expr: str, duckdb: bool) -> str:
        if not expr.isdigit():
            return expr
        words, code, size, fn = ("string_split(lower(coalesce(text, '')), ' ')", "unicode", "len", "list_filter") if duckdb else ("split(lower(coalesce(text, '')), ' ')", "ascii", "size", "filter")
        arrow = "lambda w: " if duckdb else "w -> "
        hits = f"{size}({fn}({words}, {arrow}(length(w) * 31 + {code}(concat(w, 'a')) * 7) % {len(self.features)} = {expr}))"
        return f"cast({hits} as bigint) * 1000 {'//' if duckdb else 'div'} {size}({words})"


LINE_ID = "((l_orderkey * 8 + l_linenumber) * 20000 + l_partkey) * 1000 + l_suppkey"

#: Scalability: the generator's twin over three tables, each ten times (four times) the one before.
SIZES = {"customer": ("c_custkey", ""), "orders": ("o_orderkey", ""), "lineitem": ("l_orderkey * 8 + l_linenumber", LINE_ID)}

FIXTURES: dict[str, Fixture] = {
    "part2d": Fixture("part", "p_partkey", ("p_size * 100", "round(p_retailprice * 100)")),
    "events2d": Fixture("events", "event_id", ("{MINUTE}", "round(value * 100)")),
    "events2d_fine": Fixture("events", "event_id", ("{MINUTE}", "round(value * 100)")),
    "customer2d": Fixture("customer", "c_custkey", ("round(c_acctbal * 100)", "c_nationkey * 10000")),
    "toy": Fixture("customer", "c_custkey", ("round(c_acctbal * 10)", "c_nationkey * 100000")),
    "line7": Fixture("lineitem", LINE_ID, ("l_quantity * 20", "round(l_extendedprice / 100)", "round(l_discount * 100) * 100", "round(l_tax * 100) * 100", "l_linenumber * 150", "({DAY} * 2) {DIV} 5", "l_suppkey * 10")),
    "lattice4": Fixture("lineitem", LINE_ID, ("l_quantity", "round(l_discount * 100)", "round(l_tax * 100)", "l_linenumber")),
    **{f"emb{k}": Embedding("embeddings", "vec_id", tuple(map(str, range(k)))) for k in (10, 20, 30, 40, 54, 64)},
    **{f"spread{d}": spread(d) for d in (3, 10, 15, 20, 30, 40)},
    **{f"noisy{d}": spread(d, noisy=True) for d in (3, 10, 15, 20, 30, 40)},
    **{f"{t}{d}": spread(d, t, k, id=i) for t, (k, i) in SIZES.items() for d in (3, 10, 15, 20, 30, 40, 54)},
    "doc16": Grams("documents", "doc_id", tuple(map(str, range(16)))),
}

#: eps and min_pts by fixture.
SETTINGS = {
    "part2d": (150, 4), "events2d": (300, 10), "customer2d": (5000, 4), "line7": (200, 10), "lattice4": (2, 180),
    "emb10": (2500, 4), "emb20": (4900, 4), "emb30": (6700, 4), "emb40": (8300, 4), "emb54": (10300, 4), "emb64": (11500, 4),
    **{f"{t}{d}": s for t in SIZES for d, s in {3: (30, 20), 10: (80, 20), 15: (95, 30), 20: (110, 40), 30: (140, 70), 40: (160, 80), 54: (187, 90)}.items()},
    "doc16": (12, 4), "toy": (500, 4), "events2d_fine": (200, 4),
    "spread3": (30, 20), "spread10": (80, 20), "spread15": (95, 30), "spread20": (110, 40), "spread30": (140, 70), "spread40": (160, 80),
    "noisy3": (30, 20), "noisy10": (80, 20), "noisy15": (95, 30), "noisy20": (110, 40), "noisy30": (140, 70), "noisy40": (160, 80),
}

# Small layouts of this project's own, in full.
TOY = [(1, 0, 0), (2, 4, 0), (3, 0, 4), (4, 4, 4), (5, -9, 0), (6, 14, 4), (7, 24, 4), (8, 28, 4), (9, 24, 8), (10, 28, 8), (11, 50, 50)]
CELLS9 = [("a", 0, 0), ("b", 1, 2), ("c", 2, 0), ("d", 2, 1), ("e", 3, 2), ("f", 4, 1), ("g", 4, 2), ("h", 6, 0), ("i", 3, 0)]
FOREST6 = ([(1, 2), (1, 3), (2, 3), (3, 4), (4, 5), (4, 6), (5, 6)], {(1, 2), (1, 3), (2, 3), (4, 5), (5, 6)})


def toy(spark: SparkSession) -> Points:
    df: DataFrame = spark.createDataFrame(TOY, "id bigint, x bigint, y bigint")
    return as_points(df, "id", ["x", "y"])

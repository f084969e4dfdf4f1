"""Reading points: feature specifications, files, and cleaning."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, functions as F


@dataclass(frozen=True)
class Points:
    """``frame`` (id BIGINT, coord ARRAY<BIGINT or DOUBLE>), its dimension, and whether it is whole-numbered."""

    frame: DataFrame
    dim: int
    exact: bool

    def with_frame(self, frame: DataFrame) -> Points:
        return Points(frame, self.dim, self.exact)


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_points(spark: SparkSession, path: str, fmt: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    """A frame from Parquet, ORC, CSV or JSON files."""
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def write_result(df: DataFrame, path: str, fmt: str = "parquet", partition_by: list[str] | None = None, mode: str = "errorifexists") -> None:
    writer = df.write.format(fmt).mode(mode)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def as_points(df: DataFrame, id_col: str | Column, features: list[str | Column], exact: bool = True, null_policy: str = "fail") -> Points:
    """Packs feature columns into ``coord``; dates count days, timestamps seconds, booleans 0 and 1.

    Null, NaN and infinite coordinates raise an error when the row is read
    (``fail``) or lose their row (``drop``).
    """
    kind = "bigint" if exact else "double"
    typed = df.select(F.expr(id_col).alias("id") if isinstance(id_col, str) else id_col.alias("id"), *[(F.expr(f) if isinstance(f, str) else f).alias(f"x{i}") for i, f in enumerate(features)])
    cols = []
    for i, t in enumerate(t for c, t in typed.dtypes if c != "id"):
        x = F.col(f"x{i}")
        if t == "date":
            x = F.datediff(x, F.to_date(F.lit("1970-01-01")))
        elif t.startswith("timestamp"):
            x = F.unix_timestamp(x.cast("timestamp"))
        cols.append(x.cast("double") if t != "bigint" and not exact else x)
    frame = typed.select(F.col("id").cast("bigint").alias("id"), F.array(*[c.cast(kind) for c in cols]).alias("coord"))
    return clean(Points(frame, len(features), exact), null_policy)


def from_array(df: DataFrame, id_col: str, array_col: str, dim: int, scale: float | None = None, null_policy: str = "fail") -> Points:
    """The first ``dim`` elements of an array column; with ``scale`` rounded to whole numbers."""
    coord = F.slice(F.col(array_col), 1, dim)
    coord = F.transform(coord, lambda x: F.round(x.cast("double") * scale).cast("bigint") if scale else x.cast("double"))
    return clean(Points(df.select(F.col(id_col).cast("bigint").alias("id"), coord.alias("coord")), dim, scale is not None), null_policy)


def clean(points: Points, null_policy: str) -> Points:
    bad = F.col("id").isNull() | (F.size("coord") != points.dim) | F.exists("coord", lambda x: x.isNull() | F.isnan(x.cast("double")) | (F.abs(x.cast("double")) == float("inf")))
    if null_policy == "drop":
        return points.with_frame(points.frame.where(~F.coalesce(bad, F.lit(True))))
    checked = F.when(F.coalesce(bad, F.lit(True)), F.raise_error(F.lit("null or non-finite id or coordinate"))).otherwise(F.col("coord"))
    return points.with_frame(points.frame.withColumn("coord", checked))


def scale_features(points: Points, factors: list[float], origin: list[float] | None = None) -> Points:
    """Each coordinate less its origin, times its factor; the result is real-valued."""
    shift = origin or [0.0] * points.dim
    coord = F.array(*[(F.col("coord")[i].cast("double") - F.lit(float(shift[i]))) * F.lit(float(factors[i])) for i in range(points.dim)])
    return Points(points.frame.select("id", coord.alias("coord")), points.dim, False)


def fold_duplicates(points: Points) -> DataFrame:
    """(coord, weight, id): one row per distinct coordinate, id the smallest."""
    return points.frame.groupBy("coord").agg(F.count("*").alias("weight"), F.min("id").alias("id"))

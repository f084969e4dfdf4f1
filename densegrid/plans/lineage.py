"""Cutting lineage through files that every executor can read."""

from __future__ import annotations

import contextlib
import tempfile
import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The cluster's ``spark.checkpoint.dir``; a local folder only where it is unset and the master local."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        found = spark.sparkContext.getCheckpointDir() or "file://" + tempfile.mkdtemp(prefix="densegrid-")
        spark.conf.set("spark.densegrid.shared.dir", spark.conf.get("spark.densegrid.shared.dir", found))
        found = spark.conf.get("spark.densegrid.shared.dir")
    return found.rstrip("/")


#: Spark deletes a run's shuffle files as it ends, not when the driver happens to collect its plan.
CLEAN = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


@contextlib.contextmanager
def clean_shuffles(spark: SparkSession) -> Iterator[None]:
    before = spark.conf.get(CLEAN, None)
    spark.conf.set(CLEAN, "true")
    try:
        yield
    finally:
        spark.conf.unset(CLEAN) if before is None else spark.conf.set(CLEAN, before)


class Cut:
    """A frame written once to shared files; ``frame`` reads them again.

    Unlike ``DataFrame.checkpoint`` this runs the plan once, keeps the columns
    prunable and leaves Spark real file sizes to plan with. The shuffle files of
    the run go with its end, so that a chain of cuts needs the room of one.
    """

    def __init__(self, df: DataFrame):
        self.spark = df.sparkSession
        self.path = f"{shared_dir(self.spark)}/cut-{uuid.uuid4().hex}"
        with clean_shuffles(self.spark):
            df.write.parquet(self.path)
        self.frame = self.spark.read.schema(df.schema).parquet(self.path)

    def drop(self) -> None:
        """Deletes the files; only once nothing lazy refers to them."""
        jvm = self.spark._jvm
        path = jvm.org.apache.hadoop.fs.Path(self.path)
        path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)


def cut(df: DataFrame) -> DataFrame:
    return Cut(df).frame

"""Clustering of event streams: window counts, clusters of closed windows, dense cells as they appear."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from densegrid.params import ClusterParams
from densegrid.plans.engine import cluster
from densegrid.plans.lineage import cut
from densegrid.sources.points import as_points


def event_stream(spark: SparkSession, sf_dir: str, name: str = "events", files_per_trigger: int | None = None) -> DataFrame:
    """The table as a stream, its zone-less times read as UTC."""
    schema = spark.read.parquet(f"{sf_dir}/{name}.parquet").schema
    reader = spark.readStream.schema(schema)
    if files_per_trigger:
        reader = reader.option("maxFilesPerTrigger", files_per_trigger)
    return reader.parquet(f"{sf_dir}/{name}.parquet*").withColumn("ts", F.col("ts").cast("timestamp"))


def window_cell_counts(events: DataFrame, window: str = "1 day", side: int = 5000, late: str = "1 hour", slide: str | None = None) -> DataFrame:
    """start, cell, n: events by window and by cell of their value in cents; batch and stream alike."""
    at = F.window("ts", window, slide) if slide else F.window("ts", window)
    rows = events.withWatermark("ts", late) if events.isStreaming else events
    cell = F.floor(F.round(F.col("value") * 100) / side)
    return rows.groupBy(at.alias("w"), cell.alias("cell")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "cell", "n")


def session_counts(events: DataFrame, gap: str = "6 hours", late: str = "1 hour") -> DataFrame:
    """user_id, start, n: events by user and session."""
    rows = events.withWatermark("ts", late) if events.isStreaming else events
    return rows.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def dense_cells(events: DataFrame, min_pts: int, side: int = 5000) -> DataFrame:
    """cell, n: a row once a cell of values reaches ``min_pts`` events; the state is a count that stops there."""

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        had = state.get[0] if state.exists else 0
        n = min(min_pts, had + sum(len(b) for b in batches))
        state.update((n,))
        if had < min_pts <= n:
            yield pd.DataFrame({"cell": [key[0]], "n": [n]})

    keyed = events.select(F.floor(F.round(F.col("value") * 100) / side).alias("cell"))
    return keyed.groupBy("cell").applyInPandasWithState(step, "cell long, n long", "n long", "append", GroupStateTimeout.NoTimeout)


def cluster_windows(events: DataFrame, prm: ClusterParams, out: str, checkpoint: str, window: str = "7 days", late: str = "1 hour"):
    """Clusters every closed window's points (minute, cents) into Parquet files at ``out``; a started query.

    Rows go to files by window as they come; a window is clustered once the latest
    time seen is past its end by ``late``, all that close at once in one run: their
    number is a third coordinate, wider apart than eps. Rows that come for a window
    already clustered are counted in ``out``_late. A batch that is run again writes
    the same files again.
    """
    spark, held = events.sparkSession, f"{checkpoint}/held"
    at = F.window("ts", window)

    def kept(path: str) -> DataFrame | None:
        hadoop = spark._jvm.org.apache.hadoop.fs.Path(path)
        return spark.read.parquet(path) if hadoop.getFileSystem(spark._jsc.hadoopConfiguration()).exists(hadoop) else None

    def step(batch: DataFrame, epoch: int) -> None:
        rows = batch.select("event_id", "ts", "value", at["start"].alias("start"), at["end"].alias("end"))
        done = kept(f"{checkpoint}/done")
        if done is not None:
            done = done.where(F.col("epoch") < epoch).select("start").distinct()
            rows.join(F.broadcast(done), "start", "left_semi").groupBy("start").agg(F.count("*").alias("late")).write.mode("overwrite").parquet(f"{out}_late/epoch={epoch}")
            rows = rows.join(F.broadcast(done), "start", "left_anti")
        rows.write.mode("overwrite").parquet(f"{held}/epoch={epoch}")
        every = spark.read.parquet(held).where(F.col("epoch") <= epoch)
        closing = every.groupBy("start", "end").agg(F.max("ts").alias("ts")).crossJoin(F.broadcast(every.agg(F.max("ts").alias("latest")))).where(F.col("end") <= F.col("latest") - F.expr(f"interval {late}")).select("start")
        if done is not None:
            closing = closing.join(F.broadcast(done), "start", "left_anti")
        closing = cut(closing.distinct())
        if not closing.isEmpty():  # windows are told by their own count of seconds, so that their order doesn't matter
            points = every.join(F.broadcast(closing), "start", "left_semi").withColumn("gap", F.unix_timestamp("start") * (2 * int(prm.eps) + 2))
            found = cluster(as_points(points, "event_id", [F.floor(F.unix_timestamp("ts") / 60), F.round(F.col("value") * 100), F.col("gap")]), prm)
            found.labels.join(points.select(F.col("event_id").alias("id"), "start"), "id").write.mode("overwrite").parquet(f"{out}/epoch={epoch}")
        closing.write.mode("overwrite").parquet(f"{checkpoint}/done/epoch={epoch}")

    return events.writeStream.foreachBatch(step).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def late_rows(query) -> int:
    """Rows that a finished or running query has dropped since they came after its watermark, as its progress reports them."""
    return sum(int(s["numRowsDroppedByWatermark"]) for p in query.recentProgress for s in p["stateOperators"])


def drain(stream: DataFrame, name: str, mode: str = "complete") -> DataFrame:
    """Runs a stream over what is there and gives its result as a batch frame."""
    query = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination()
    return stream.sparkSession.table(name)

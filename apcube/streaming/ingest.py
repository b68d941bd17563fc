"""Structured Streaming over the event table: cell ingest and windowed operators.

Every run drains what there is (``availableNow``) into a Parquet table of the shared scratch folder; what is drained
equals the batch answer on the closed windows.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from apcube.operators.boxtree import Nodes
from apcube.operators.index import assign, merge_cells, to_cells


def read_stream(spark: SparkSession, sf_dir: str, table: str = "events", per_batch: int = 1) -> DataFrame:
    """The table's files as a stream, time stamps in UTC."""
    schema = spark.read.parquet(f"{sf_dir}/{table}.parquet").schema
    df = spark.readStream.schema(schema).option("pathGlobFilter", f"{table}.parquet" if not sf_dir.endswith(".parquet") else "*.parquet").option("maxFilesPerTrigger", per_batch).parquet(sf_dir)
    naive = [f.name for f in schema if f.dataType.typeName() == "timestamp_ntz"]
    return df.withColumns({c: F.to_timestamp(c) for c in naive})


def drain(df: DataFrame, path: str, mode: str = "append") -> DataFrame:
    """Runs a stream to its end into Parquet files and reads them."""
    query = df.writeStream.format("parquet").option("path", f"{path}/out").option("checkpointLocation", f"{path}/log").outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination()
    return df.sparkSession.read.schema(df.schema).parquet(f"{path}/out")


def drain_batches(df: DataFrame, path: str, each: Callable[[DataFrame, int], None], mode: str = "append") -> None:
    query = df.writeStream.foreachBatch(each).option("checkpointLocation", f"{path}/log").outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination()


def ingest_cells(points: DataFrame, path: str, dims, nodes: Nodes, widths, cells_per) -> DataFrame:
    """Cells of a stream of points (dims, m) on a frozen skeleton. Each micro-batch adds a run of partial cells under its
    own number, so that a batch that is run again replaces its run; readers merge the runs."""

    def each(batch: DataFrame, number: int) -> None:
        placed = assign(batch.select(*dims, "m"), dims, nodes, nodes.leaves, widths)
        to_cells(placed, dims, cells_per).write.mode("overwrite").parquet(f"{path}/runs/batch={number}")

    drain_batches(points, path, each)
    return merge_cells(points.sparkSession.read.parquet(f"{path}/runs").drop("batch"), dims)


def windows(events: DataFrame, length: str, slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """start, n, s per closed window: counts and cents."""
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    return events.withWatermark("ts", late).groupBy(w).agg(F.count("*").alias("n"), F.sum(F.round(F.col("value") * 100).cast("long")).alias("s")).select(F.col("window.start").alias("start"), "n", "s")


def sessions(events: DataFrame, gap: str, late: str = "1 hour") -> DataFrame:
    """user_id, start, n per closed session."""
    got = events.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n"))
    return got.select("user_id", F.col("w.start").alias("start"), "n")


def growing_boxes(points: DataFrame) -> DataFrame:
    """leaf, n, lo_x, hi_x, ... of a stream with leaf, x, y: state per leaf that grows with late points. Output: the state
    after each micro-batch in which the leaf had points."""
    state = "n bigint, lo_x bigint, hi_x bigint, lo_y bigint, hi_y bigint"

    def grow(key: tuple, batches: Iterator[pd.DataFrame], held) -> Iterator[pd.DataFrame]:
        n, lx, hx, ly, hy = held.get if held.exists else (0, 1 << 60, -1, 1 << 60, -1)
        for b in batches:
            n, lx, hx, ly, hy = n + len(b), min(lx, int(b.x.min())), max(hx, int(b.x.max())), min(ly, int(b.y.min())), max(hy, int(b.y.max()))
        held.update((n, lx, hx, ly, hy))
        yield pd.DataFrame([(key[0], n, lx, hx, ly, hy)], columns=["leaf", "n", "lo_x", "hi_x", "lo_y", "hi_y"])

    return points.groupBy("leaf").applyInPandasWithState(grow, f"leaf bigint, {state}", state, "update", "NoTimeout")

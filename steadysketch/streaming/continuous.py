"""Sketches and reports over update streams."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.layouts import Layout
from ..operators.sketch import CELL, build, estimates, merge
from ..sources.io import last_batch


def stream_updates(spark: SparkSession, path: str, schema, key: Column, value: Column, ts: str = "ts", files_per_trigger: int = 1) -> DataFrame:
    """(ts, key, value) from files that arrive in a folder; times are cast to zoned timestamps."""
    raw = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
    rows = raw.withColumn(ts, F.col(ts).cast("timestamp"))
    return rows.select(F.col(ts).alias("ts"), key.cast("bigint").alias("key"), value.cast("bigint").alias("value")).where("key is not null and value is not null")


def windowed_cells(updates: DataFrame, window: Column, layout: Layout, late: str | None = None) -> DataFrame:
    """Cells of each time window; with ``late`` a watermark bounds the state, and later rows are dropped."""
    rows = updates.withWatermark("ts", late) if late else updates
    spread = layout.participation(rows.select("ts", "key", "value"))
    return spread.groupBy(window.alias("w"), "row", "bucket").agg(F.sum(F.col("sign") * F.col("value")).alias("c"))


def session_vectors(updates: DataFrame, gap: str) -> DataFrame:
    """Sums by key and session of activity."""
    return updates.groupBy("key", F.session_window("ts", gap).alias("w")).agg(F.sum("value").alias("value"))


class RunningSketch:
    """Cells kept by ``foreachBatch``: a batch adds its delta, and a repeated batch id changes nothing.

    The last committed batch is read from the folder at the start, so a restarted job goes on where the one
    before it stopped. A batch's folder counts once the writer's own success mark is in it; what a lost
    driver left half written is overwritten when the batch comes again.
    """

    def __init__(self, spark: SparkSession, path: str, layout: Layout):
        self.spark, self.path, self.layout = spark, path, layout
        self.done = last_batch(spark, path)

    def _at(self, batch_id: int) -> str:
        return f"{self.path}/batch={batch_id}"

    def cells(self) -> DataFrame | None:
        return self.spark.read.parquet(self._at(self.done)) if self.done >= 0 else None

    def __call__(self, rows: DataFrame, batch_id: int) -> None:
        if batch_id <= self.done:
            return
        delta = build(rows.select(F.lit(0).cast("bigint").alias("query_id"), "key", "value"), self.layout)
        before = self.cells()
        after = merge(before.select(*CELL, "c"), delta) if before is not None else delta
        after.write.mode("overwrite").parquet(self._at(batch_id))
        self.done = batch_id


def reporting_batches(running: RunningSketch, keys: Callable[[], DataFrame], report: Callable[[int, DataFrame], None]) -> Callable[[DataFrame, int], None]:
    """A ``foreachBatch`` function that updates the sketch and hands the wanted keys' estimates to ``report``."""

    def on_batch(rows: DataFrame, batch_id: int) -> None:
        if batch_id <= running.done:
            return
        running(rows, batch_id)
        wanted = keys().select(F.lit(0).cast("bigint").alias("query_id"), "key")
        report(batch_id, estimates(wanted, running.cells(), running.layout, 1))

    return on_batch

"""Choices of the physical plan that Catalyst cannot make from what it knows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Most rows of a side that is broadcast on purpose.
BROADCAST_ROWS = 2_000_000
#: Queries of a task that expands each into a row for every key and sketch row.
QUERIES_A_TASK = 1_000


def sized_broadcast(df: DataFrame, rows: int | None) -> DataFrame:
    """Broadcast a side whose row bound is known and small; leave every other side to the planner."""
    return F.broadcast(df) if rows is not None and rows <= BROADCAST_ROWS else df


def unbroadcast(df: DataFrame) -> DataFrame:
    """Join this side by a shuffle: the planner estimates it from file sizes, which do not see the rows that explode makes."""
    return df.hint("merge")


def by_query(df: DataFrame, query: str, a_task: int = QUERIES_A_TASK) -> DataFrame:
    """Each query's rows in one task, and a bounded number of queries in each: what is summed or joined by query later needs no shuffle.

    ``df`` has a row, still unexpanded, for each query or a few.
    """
    known = df.where(F.col(query).isNotNull())
    cores = df.sparkSession.sparkContext.defaultParallelism
    return known.repartition(max(cores, -(-known.count() // a_task)), query)


def spread(df: DataFrame) -> DataFrame:
    """Deal rows out over all cores where the scan has fewer partitions than cores; larger scans stay as they are."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(cores) if df.rdd.getNumPartitions() < cores else df


def prune_keys(vec: DataFrame, keys: DataFrame, rows: int | None = None) -> DataFrame:
    """Keep the rows of the wanted keys, below any expansion into buckets."""
    return vec.join(sized_broadcast(keys.select("key").distinct(), rows), "key", "left_semi")


def rollup_cells(cells: DataFrame, groups: list[str]) -> DataFrame:
    """Totals of grouped cells at every level of ``groups``, from the cells and not from the rows."""
    return cells.rollup(*groups, "row", "bucket").agg(F.sum("c").alias("c"), F.grouping_id().alias("level")).where("row is not null and bucket is not null")

"""Building, combining and reading linear sketches kept as cells (query_id, row, bucket, c)."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.physical import sized_broadcast, unbroadcast
from .layouts import Layout, RowHashed

CELL = ["query_id", "row", "bucket"]


def build(vec: DataFrame, layout: Layout, sum_keys: bool = True) -> DataFrame:
    """Signed sums of (query_id, key, value).

    ``sum_keys`` adds up each key before hashing it, which pays where rows repeat keys; the cells are
    partial sums in every task first, so what is shuffled is at most tasks x cells, hot keys or not.
    """
    if sum_keys:
        vec = vec.groupBy("query_id", "key").agg(F.sum("value").alias("value"))
    spread = layout.participation(vec.select("query_id", "key", "value"))
    return spread.groupBy(*CELL).agg(F.sum(F.col("sign") * F.col("value")).alias("c"))


def build_by(rows: DataFrame, groups: list[str], layout: Layout) -> DataFrame:
    """One sketch for each group of (groups..., key, value) rows."""
    summed = rows.groupBy(*groups, "key").agg(F.sum("value").alias("value"))
    return layout.participation(summed).groupBy(*groups, "row", "bucket").agg(F.sum(F.col("sign") * F.col("value")).alias("c"))


def merge(*parts: DataFrame) -> DataFrame:
    """Sketch of the sum of the vectors behind ``parts`` (of one layout)."""
    stacked = reduce(DataFrame.unionByName, parts)
    return stacked.groupBy(*CELL).agg(F.sum("c").alias("c"))


def scale(cells: DataFrame, by: float | int) -> DataFrame:
    return cells.withColumn("c", F.col("c") * by)


def update(cells: DataFrame, changes: DataFrame, layout: Layout) -> DataFrame:
    """Cells after the (query_id, key, value) changes; only touched buckets are computed."""
    return merge(cells, build(changes, layout))


def estimates(keys: DataFrame, cells: DataFrame, layout: Layout, queries: int | None = None) -> DataFrame:
    """The unbiased estimate in every bucket of every key: (query_id, key, row, bucket, est).

    ``keys`` has query_id and key. With the number of queries known, cells of checked size are broadcast;
    otherwise they are joined on the cell.
    """
    spread = layout.participation(keys.select("query_id", "key"))
    held = cells.select(*CELL, "c")
    side = sized_broadcast(held, layout.size * queries) if queries else unbroadcast(held)
    joined = spread.join(side, CELL, "left")
    return joined.select("query_id", "key", "row", "bucket", (F.col("sign") * F.coalesce("c", F.lit(0))).alias("est"))


def own_estimates(vec: DataFrame, layout: Layout) -> DataFrame:
    """The estimates of a vector's own keys, for very many queries: cells are summed where their keys are, without a join.

    Same rows as ``estimates(vec, build(vec, layout), layout)``; ``vec`` has a row for each key. Where its rows lie by
    query (``by_query``) nothing is shuffled.
    """
    spread = layout.participation(vec.select("query_id", "key", "value")).select(*CELL, "key", "sign", (F.col("sign") * F.col("value")).alias("signed"))
    summed = spread.withColumn("c", F.sum("signed").over(Window.partitionBy(*CELL)))
    return summed.select("query_id", "key", "row", "bucket", (F.col("sign") * F.col("c")).alias("est"))


def inner_product(a: DataFrame, b: DataFrame) -> DataFrame:
    """Median over the rows of the products of two row-hashed sketches: (query_id, product)."""
    joined = a.join(b.withColumnRenamed("c", "other"), CELL)
    by_row = joined.groupBy("query_id", "row").agg(F.sum(F.col("c") * F.col("other")).alias("p"))
    return by_row.groupBy("query_id").agg(F.median("p").alias("product"))


def norm2(cells: DataFrame) -> DataFrame:
    """Median over the rows of the sums of squares: an estimate of the squared norm."""
    by_row = cells.groupBy("query_id", "row").agg(F.sum(F.col("c") * F.col("c")).alias("p"))
    return by_row.groupBy("query_id").agg(F.median("p").alias("norm2"))


def embed(cells: DataFrame, layout: RowHashed) -> DataFrame:
    """Each query's cells as one dense array, the feature-hashing use: (query_id, features)."""
    spot: Column = F.col("row") * layout.width + F.col("bucket")
    held = cells.groupBy("query_id").agg(F.map_from_entries(F.collect_list(F.struct(spot, "c"))).alias("m"))
    dense = F.transform(F.sequence(F.lit(0), F.lit(layout.size - 1)), lambda i: F.coalesce(F.element_at("m", i), F.lit(0)).cast("double"))
    return held.select("query_id", dense.alias("features"))


def save(cells: DataFrame, path: str, layout: Layout) -> None:
    cells.withColumn("layout", F.lit(layout.fingerprint)).write.mode("overwrite").parquet(path)


def load(spark, path: str, layout: Layout) -> DataFrame:
    """Cells of a file; refuses those of another layout."""
    stored = spark.read.parquet(path)
    other = stored.where(F.col("layout") != layout.fingerprint).select("layout").first()
    if other:
        raise ValueError(f"cells of layout {other[0]}, not {layout.fingerprint}")
    return stored.drop("layout")

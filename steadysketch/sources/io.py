"""Other sources and the sinks of cells, reports and ledgers."""

from __future__ import annotations

from collections.abc import Callable, Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

FORMATS = ("parquet", "orc", "json", "csv", "text")


def read_rows(spark: SparkSession, path: str, kind: str = "parquet", schema=None, columns: Sequence[str] | None = None, **options) -> DataFrame:
    """Rows of files of any supported kind; a schema is required where files carry none, so nothing is inferred."""
    if kind not in FORMATS:
        raise ValueError(f"{kind} is none of {', '.join(FORMATS)}")
    if kind in ("json", "csv") and schema is None:
        raise ValueError(f"{kind} files need a schema")
    reader = spark.read.options(**options)
    if schema is not None:
        reader = reader.schema(schema)
    df = reader.format(kind).load(path)
    return df.select(*columns) if columns else df


def write_cells(cells: DataFrame, path: str, sketch_id: str, mode: str = "append") -> None:
    """Cells partitioned by sketch, so that a read of one sketch prunes the others."""
    cells.withColumn("sketch_id", F.lit(sketch_id)).write.mode(mode).partitionBy("sketch_id").parquet(path)


def read_cells(spark: SparkSession, path: str, sketch_id: str) -> DataFrame:
    return spark.read.parquet(path).where(F.col("sketch_id") == sketch_id).drop("sketch_id")


def write_report(report: DataFrame, path: str, day: str) -> None:
    report.withColumn("day", F.lit(day)).write.mode("append").partitionBy("day").parquet(path)


def _marked(spark: SparkSession, path: str, mark: str) -> list[int]:
    """Batch ids whose folder under ``path`` holds the mark, on whatever file system it is."""
    folder = spark._jvm.org.apache.hadoop.fs.Path(path)
    files = folder.getFileSystem(spark._jsc.hadoopConfiguration())
    found = files.globStatus(spark._jvm.org.apache.hadoop.fs.Path(f"{path}/batch=*/{mark}"))
    return sorted(int(f.getPath().getParent().getName().split("=")[1]) for f in found or [])


def last_batch(spark: SparkSession, path: str) -> int:
    """The newest batch that was written whole under ``path``, or -1."""
    return max(_marked(spark, path, "_SUCCESS"), default=-1)


def once_per_batch(spark: SparkSession, path: str, prepare: Callable[[DataFrame, int], DataFrame] | None = None) -> Callable[[DataFrame, int], None]:
    """A ``foreachBatch`` function that writes each batch id once, also over restarts: batches that are whole are left alone."""

    def on_batch(df: DataFrame, batch_id: int) -> None:
        if batch_id not in _marked(spark, path, "_SUCCESS"):
            (prepare(df, batch_id) if prepare else df).write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    return on_batch


def from_array(df: DataFrame, query: str, array: str) -> DataFrame:
    """(query_id, key, value) of an array column: the position is the key."""
    return df.select(F.col(query).cast("bigint").alias("query_id"), F.posexplode(array).alias("key", "value")).where("value is not null and value <> 0").withColumn("key", F.col("key").cast("bigint"))


def from_map(df: DataFrame, query: str, mapping: str) -> DataFrame:
    return df.select(F.col(query).cast("bigint").alias("query_id"), F.explode(mapping).alias("key", "value")).where("value is not null and value <> 0")


def from_json(df: DataFrame, query: str, text: str, path: str) -> DataFrame:
    """Counts by an integer field of a JSON text."""
    key = F.get_json_object(text, path).cast("bigint")
    return df.select(F.col(query).cast("bigint").alias("query_id"), key.alias("key")).where("key is not null").groupBy("query_id", "key").agg(F.count("*").alias("value"))


def contrast(df: DataFrame, query: Column, key: Column, sign: Column) -> DataFrame:
    """Signed counts by key."""
    return df.select(query.cast("bigint").alias("query_id"), key.alias("key"), sign.cast("bigint").alias("value")).groupBy("query_id", "key").agg(F.sum("value").alias("value")).where("value <> 0")

"""What the operators share: reading tables, whole-text batches and the word pattern."""

from __future__ import annotations

import ctypes
import gc
import threading
from collections.abc import Callable, Iterator
from typing import Any

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..runtime import bounded_batches, ship

#: Words are runs of anything but ASCII white space.
SPACE = r"[\x20\x09-\x0D]+"
WORD = r"[^\x20\x09-\x0D]+"
#: What a worker keeps from task to task, by operator.
KEPT: dict[str, Any] = {}
#: The C library's number of that setting, and the least bytes of what it maps on its own.
M_MMAP_THRESHOLD, MAPPED = -3, 1 << 20
#: Seconds after a task at which its worker hands back what the task held to its end.
IDLE_S = 1.0
LATER: list[threading.Timer] = []


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def texts(docs: DataFrame, *more: str) -> DataFrame:
    """doc_id, text and the named columns alone, so that no other column of the input can clash."""
    return docs.select("doc_id", "text", *more)


def map_batches(df: DataFrame, fn: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema: str, rows: int = 1000, keeps: str | None = None) -> DataFrame:
    """mapInArrow with small batches, with this package sent to the workers.

    Workers outlive their tasks, so a task hands back what it no longer needs when it ends. It does so when it begins
    too, and soon after: what it still held as it ended (its last group's rows, above all) is free only then. ``keeps``
    names what this operator's tasks leave in KEPT for the next; what others left there is dropped.
    """
    ship(df.sparkSession)
    bounded_batches(df.sparkSession, rows)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        begin(keeps)
        gc.disable()  # the operators make millions of small objects and hardly any cycles
        try:
            yield from fn(batches)
        finally:
            gc.enable()
            give_back()
            give_back_later()

    return df.mapInArrow(run, schema)


def begin(keeps: str | None = None) -> None:
    """At the start of a task: hand back what earlier ones held, and drop what tasks of other operators have kept here."""
    while LATER:
        LATER.pop().cancel()
    for owner in [k for k in KEPT if k != keeps]:
        del KEPT[owner]
    give_back()


def give_back_later() -> None:
    """Hand back soon, when the task has ended and let go of its last rows: stages without Python find workers small."""
    LATER.append(threading.Timer(IDLE_S, give_back))
    LATER[-1].daemon = True
    LATER[-1].start()


def give_back() -> None:
    """Return freed memory of this process to the system: that of the collector, of Arrow and of the C library."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    library = ctypes.CDLL(None)
    if hasattr(library, "malloc_trim"):
        # From now on Arrow takes its memory from the C library, and that maps what is large on its own and unmaps it at once.
        pa.set_memory_pool(pa.system_memory_pool())
        library.mallopt(M_MMAP_THRESHOLD, MAPPED)
        library.malloc_trim(0)


def text_hash(text_col: str = "text") -> Column:
    """Seeded 64-bit hash of a document's id and text: orders rows the same way in every run."""
    return F.xxhash64(F.col("doc_id"), F.col(text_col))

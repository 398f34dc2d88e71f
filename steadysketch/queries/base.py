"""Registry of queries with their SQL, and the settings they share."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from ..operators.gate import Gate
from ..operators.layouts import IndependentBuckets, RowHashed
from ..operators.sizing import TAU_A, TAU_B, TAU_B_COMPACT, mid

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE_SQL: dict[str, str] = {}


def query(sql: str | None = None):
    """Registers a query under its function's name, with the SQL that gives the same rows."""

    def register(fn: Callable[[SparkSession, str], DataFrame]):
        QUERIES[fn.__name__] = fn
        if sql is not None:
            ORACLE_SQL[fn.__name__] = sql
        return fn

    return register


#: Layouts of the registered queries: rows are odd, widths 16 times the number of heavy keys sought or near it.
TOKENS = RowHashed(65, 160, seed=11)
PARTS = RowHashed(129, 64, seed=12)
FLAT = RowHashed(21, 64, seed=13)
USERS = RowHashed(33, 64, seed=14)
SMALL = RowHashed(5, 32, seed=15)
COMPONENTS = RowHashed(21, 64, seed=16)
BUCKETS = IndependentBuckets(4_000, 16, seed=17)
#: Enough buckets a key for counts over the expected number of them to resolve the gap of the thresholds.
INDEPENDENT = IndependentBuckets(16_000, 16, seed=18)
SKIPPING = IndependentBuckets(16_000, 16, seed=18, mode="skip")
MID = mid()
COMPACT = mid(TAU_A, TAU_B_COMPACT)
LEVELS = (TAU_A, TAU_B)
#: A gate whose noise fits sketches of this size; the scales of the analysis are thousands of times wider.
GATE = Gate(eps=0.1, delta=1e-9, limit=64, seed=4242, noise="scaled", factor=2e-5)

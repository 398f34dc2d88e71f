"""Baselines: private ensembles of whole sketches, noisy medians, a fresh sketch for each query, L1 counters."""

from __future__ import annotations

from collections.abc import Iterator
from math import ceil, sqrt

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .gate import AT_LEAST, Gate, _uniform
from .layouts import RowHashedCopies
from .sketch import CELL
from .weights import private_median


def ensemble_size(m: int, k: int) -> int:
    """Copies for m queries with k heavy keys each: the root of the number of private answers."""
    return max(1, ceil(sqrt(m * k)))


def ensemble_votes(vec: DataFrame, keys: DataFrame, copies: int, layout: RowHashedCopies, tau: float) -> DataFrame:
    """(query_id, key, copies_for): how many of the independent copies report each key, the vector read once for all copies."""
    each = F.explode(F.sequence(F.lit(0), F.lit(copies - 1))).alias("copy")
    cells = layout.participation(vec.select("query_id", "key", "value", each)).groupBy("copy", *CELL).agg(F.sum(F.col("sign") * F.col("value")).alias("c"))
    asked = layout.participation(keys.select("query_id", "key", each))
    est = asked.join(cells, ["copy", *CELL], "left").withColumn("est", F.col("sign") * F.coalesce("c", F.lit(0)))
    share = lambda cond: F.avg(F.when(cond, 1.0).otherwise(0.0)) >= tau
    reported = est.groupBy("copy", "query_id", "key").agg((share(F.col("est") > 0) | share(F.col("est") < 0)).alias("reported")).where("reported")
    return reported.groupBy("query_id", "key").agg(F.count("*").alias("copies_for"))


def private_ensemble(voted: DataFrame, copies: int, gate: Gate) -> DataFrame:
    """Keys whose noisy number of reporting copies is at least half of all copies."""
    noisy = F.col("copies_for") + gate.noise_column(0, AT_LEAST, F.col("query_id"), F.col("key"))
    return voted.withColumn("noisy", noisy).where(F.col("noisy") >= copies / 2)


def noisy_median(est: DataFrame, eps: float, grid: list[int], seed: int) -> DataFrame:
    """Each key's median of bucket estimates by the exponential mechanism over a grid of values."""
    points = np.array(sorted(grid), float)

    def of_key(rows: pd.DataFrame) -> pd.DataFrame:
        query, key = int(rows.query_id.iloc[0]), int(rows.key.iloc[0])
        return pd.DataFrame({"query_id": [query], "key": [key], "v_hat": [private_median(rows.est.to_numpy(float), eps, points, _uniform(seed, query, key))]})

    return est.select("query_id", "key", "est").groupBy("query_id", "key").applyInPandas(of_key, "query_id bigint, key bigint, v_hat double")


def fresh_copy_estimates(vec: DataFrame, keys: DataFrame, layout: RowHashedCopies) -> DataFrame:
    """Bucket estimates when every query has a sketch of its own: the trivial bound of one copy per answer."""
    own = F.col("query_id").alias("copy")
    cells = layout.participation(vec.select("query_id", "key", "value", own)).groupBy(*CELL).agg(F.sum(F.col("sign") * F.col("value")).alias("c"))
    asked = layout.participation(keys.select("query_id", "key", own))
    return asked.join(cells, CELL, "left").select("query_id", "key", "row", "bucket", (F.col("sign") * F.coalesce("c", F.lit(0))).alias("est"))


def l1_frequent(items: DataFrame, column: str, k: int) -> DataFrame:
    """Deterministic counters for keys above 1/k of all rows: (item, low) with low at most the count, at least count - rows / k.

    Each task keeps k counters (Misra-Gries) and hands them on; merging adds them and cuts back to k, so
    nothing larger than tasks x k reaches a shuffle.
    """

    def counters(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: dict = {}
        for rows in batches:
            for item, n in rows[column].dropna().value_counts().items():
                held[item] = held.get(item, 0) + int(n)
            if len(held) > k:
                cut = sorted(held.values(), reverse=True)[k]
                held = {i: n - cut for i, n in held.items() if n > cut}
        if held:  # the columns of a frame without rows have no type that Arrow could take over
            yield pd.DataFrame({"item": list(held), "low": list(held.values())})

    kind = items.schema[column].dataType.simpleString()
    local = items.select(column).mapInPandas(counters, f"item {kind}, low bigint")
    merged = local.groupBy("item").agg(F.sum("low").alias("low"))
    cut = merged.orderBy(F.desc("low")).limit(k + 1).agg(F.when(F.count("*") > k, F.min("low")).otherwise(0).alias("cut"))
    return merged.crossJoin(F.broadcast(cut)).select("item", (F.col("low") - F.col("cut")).alias("low")).where("low > 0")

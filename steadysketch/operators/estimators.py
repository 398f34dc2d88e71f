"""Estimates and reports that use a sketch's cells without protecting its randomness."""

from __future__ import annotations

from math import ceil

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.physical import sized_broadcast, unbroadcast

PER_KEY = ["query_id", "key"]


# -- medians --------------------------------------------------------------------------------------
def median_estimate(est: DataFrame) -> DataFrame:
    """Exact median of the bucket estimates of every key; keys without buckets are absent."""
    ordered = F.sort_array(F.collect_list("est"))
    held = est.groupBy(*PER_KEY).agg(ordered.alias("e"))
    at = lambda shift: F.element_at("e", F.floor((F.size("e") + shift) / 2).cast("int"))
    return held.select(*PER_KEY, ((at(1) + at(2)) / 2).cast("double").alias("v_hat"))


def quantile_estimate(est: DataFrame, q: float) -> DataFrame:
    return est.groupBy(*PER_KEY).agg(F.percentile("est", F.lit(q)).alias("v_hat"))


def report_size(k: int, alpha: float) -> int:
    """Keys a median report needs so that every heavy key is among them."""
    return ceil(k * (1 + 1 / (1 - 2 * alpha)))


def top_by_magnitude(values: DataFrame, k_out: int) -> DataFrame:
    """The k_out keys of largest estimate in each query, ties to the smaller key."""
    order = Window.partitionBy("query_id").orderBy(F.abs("v_hat").desc(), "key")
    return values.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k_out)


def median_report(est: DataFrame, k_out: int) -> DataFrame:
    return top_by_magnitude(median_estimate(est), k_out)


# -- sign agreement -------------------------------------------------------------------------------
def votes(est: DataFrame) -> DataFrame:
    """Buckets that agree with plus, with minus, with neither, and all buckets of each key."""
    count = lambda cond: F.sum(F.when(cond, 1).otherwise(0))
    return est.groupBy(*PER_KEY).agg(count(F.col("est") > 0).alias("pos"), count(F.col("est") < 0).alias("neg"), count(F.col("est") == 0).alias("zero"), F.count("*").alias("part"))


def agreement(counted: DataFrame, per_key: float, normalize: str = "expected") -> DataFrame:
    """Adds p_plus and p_minus: votes over the expected number of buckets, or over the realized one."""
    base: Column = F.lit(float(per_key)) if normalize == "expected" else F.col("part").cast("double")
    return counted.withColumns({"p_plus": F.col("pos") / base, "p_minus": F.col("neg") / base})


def threshold_report(agreed: DataFrame, tau: float) -> DataFrame:
    """Keys whose agreement reaches tau for either sign; nothing heavy gives nothing."""
    sign = F.when(F.col("p_plus") >= tau, 1).when(F.col("p_minus") >= tau, -1)
    best = F.greatest("p_plus", "p_minus")
    return agreed.select(*PER_KEY, sign.alias("sign"), best.alias("p_hat")).where("sign is not null")


def hysteresis_report(agreed: DataFrame, tau_a: float, tau_b: float) -> DataFrame:
    """Reported keys of every step of a sequence: enter near tau_b, leave near tau_a, keep in between.

    ``agreed`` has a row for each step and key to follow. The last step that said enter or leave decides.
    """
    gap = tau_b - tau_a
    best = F.greatest("p_plus", "p_minus")
    signal = F.when(best >= tau_b - gap / 5, 1).when(best < tau_a + gap / 5, 0)
    past = Window.partitionBy("key").orderBy("query_id").rowsBetween(Window.unboundedPreceding, 0)
    state = F.last(signal, ignorenulls=True).over(past)
    return agreed.withColumn("inside", F.coalesce(state, F.lit(0))).where("inside = 1").select(*PER_KEY, best.alias("p_hat"))


def hysteresis_step(previous: DataFrame, agreed: DataFrame, tau_a: float, tau_b: float) -> DataFrame:
    """One step: keys of ``previous`` that stay and keys that enter."""
    gap = tau_b - tau_a
    best = F.greatest("p_plus", "p_minus")
    both = agreed.withColumn("best", best).join(previous.select("key", F.lit(True).alias("was")), "key", "full_outer")
    stays = F.col("was") & ~(F.coalesce("best", F.lit(0.0)) < tau_a + gap / 5)
    enters = F.col("best") >= tau_b - gap / 5
    return both.where(F.coalesce(stays, F.lit(False)) | F.coalesce(enters, F.lit(False))).select("key")


# -- ground truth ---------------------------------------------------------------------------------
def _sums(vec: DataFrame, summed: bool) -> DataFrame:
    return vec if summed else vec.groupBy(*PER_KEY).agg(F.sum("value").alias("value")).where("value <> 0")


def exact_heavy(vec: DataFrame, k: int, norm: str = "tail", summed: bool = False, queries: int | None = None) -> DataFrame:
    """Keys with v^2 above 1/k of the squared norm: of all but the k largest entries, or of all.

    Up to 2 k keys of a query can pass. ``summed`` says that each key has one row already, which saves a
    shuffle; ``queries`` bounds the number of vectors, whose norms are then broadcast, one row each.
    """
    summed_rows = _sums(vec, summed)
    square = F.col("value") * F.col("value")
    norms = tail_norm2(summed_rows, k if norm == "tail" else 0, True, queries).withColumnRenamed("tail2", "norm2")
    joined = summed_rows.join(sized_broadcast(norms, queries) if queries else unbroadcast(norms), "query_id")
    return joined.where(square * k > F.col("norm2")).select(*PER_KEY, "value", "norm2")


def exact_topk(vec: DataFrame, k: int, summed: bool = False) -> DataFrame:
    order = Window.partitionBy("query_id").orderBy(F.abs("value").desc(), "key")
    return _sums(vec, summed).withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


def tail_norm2(vec: DataFrame, k: int, summed: bool = False, queries: int | None = None) -> DataFrame:
    """(query_id, tail2): squared norm without the k largest entries; a top-k of each task comes before any shuffle."""
    rows = _sums(vec, summed)
    order = Window.partitionBy("query_id").orderBy(F.abs("value").desc(), "key")
    square = F.col("value") * F.col("value")
    top = rows.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).groupBy("query_id").agg(F.sum(square).alias("top2"))
    whole = rows.groupBy("query_id").agg(F.sum(square).alias("all2")).join(sized_broadcast(top, queries) if queries else unbroadcast(top), "query_id", "left")
    return whole.select("query_id", (F.col("all2") - F.coalesce("top2", F.lit(0))).alias("tail2"))


def true_agreement(vec: DataFrame, keys: DataFrame, width: int, spread: int) -> DataFrame:
    """Exact p_plus and p_minus of integer vectors: the law of the other keys' signed sum in a bucket is convolved.

    ``spread`` bounds the sum of magnitudes of a query's entries; meant for small vectors, each in one task.
    """
    import numpy as np
    import pandas as pd

    wanted = keys.select(*PER_KEY).distinct().withColumn("wanted", F.lit(True))
    marked = vec.groupBy(*PER_KEY).agg(F.sum("value").alias("value")).join(wanted, PER_KEY, "full_outer").fillna({"value": 0})

    def of_query(rows: pd.DataFrame) -> pd.DataFrame:
        out = []
        # Keys of one value have one law, so it is convolved once for each value of the wanted keys.
        values = rows.value.to_numpy("int64")
        laws: dict[int, tuple[float, float]] = {}
        for own in sorted(set(rows.value[rows.wanted.fillna(False).astype(bool)])):
            others = list(values[values != 0])
            if own:
                others.remove(own)
            law = np.zeros(2 * spread + 1)
            law[spread] = 1
            for v in others:
                shift = abs(int(v))
                moved = np.zeros_like(law)
                moved[shift:] += law[:-shift]
                moved[:-shift] += law[shift:]
                law = law * (1 - 1 / width) + moved / (2 * width)
            at = np.arange(-spread, spread + 1) + int(own)
            laws[own] = float(law[at > 0].sum()), float(law[at < 0].sum())
        for key, own in rows.loc[rows.wanted.fillna(False).astype(bool), ["key", "value"]].itertuples(index=False):
            out.append((rows.query_id.iloc[0], key, *laws[own]))
        return pd.DataFrame(out, columns=["query_id", "key", "p_plus", "p_minus"])

    return marked.groupBy("query_id").applyInPandas(of_query, "query_id bigint, key bigint, p_plus double, p_minus double")


def normal_agreement(vec: DataFrame, width: int, queries: int | None = None) -> DataFrame:
    """p_plus and p_minus if the other keys' sum in a bucket were normal with deviation sqrt(norm2 / width).

    The normal distribution's tail by a polynomial (absolute error below 1e-7), so it stays in the plan.
    """
    square = F.sum(F.col("value").cast("double") * F.col("value").cast("double"))
    norms = vec.groupBy("query_id").agg(square.alias("all2"))
    own2 = F.col("value").cast("double") * F.col("value").cast("double")
    z = F.col("value") / F.sqrt(F.greatest((F.col("all2") - own2) / width, F.lit(1e-300)))
    t = 1 / (1 + 0.2316419 * F.abs(z))
    # Coefficients of the published approximation of the normal tail.
    series = t * (0.319381530 + t * (-0.356563782 + t * (1.781477937 + t * (-1.821255978 + t * 1.330274429))))
    upper = F.exp(-z * z / 2) * 0.3989422804014327 * series
    p = F.when(z >= 0, 1 - upper).otherwise(upper)
    return vec.join(sized_broadcast(norms, queries), "query_id").select(*PER_KEY, p.alias("p_plus"), (1 - p).alias("p_minus"))


def sampled_agreement(counted: DataFrame, per_key: float) -> DataFrame:
    """p_plus and p_minus by sampling: the votes of a sketch with fresh randomness and very many buckets for each key."""
    return agreement(counted, per_key, "realized").select(*PER_KEY, "p_plus", "p_minus")


def heavy_set(truth: DataFrame, tau_b: float) -> DataFrame:
    """Keys that every right report holds, from their true agreement."""
    return truth.where(F.greatest("p_plus", "p_minus") >= tau_b).select(*PER_KEY)


def suspect_set(truth: DataFrame, tau_a: float) -> DataFrame:
    """Keys that a right report may hold."""
    return truth.where(F.greatest("p_plus", "p_minus") >= tau_a).select(*PER_KEY)

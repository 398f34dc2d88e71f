"""Measures of reports and attacks, and the budgets that input sequences cost."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.physical import unbroadcast
from .sizing import TAU_A, TAU_B


# -- reports --------------------------------------------------------------------------------------
def report_quality(report: DataFrame, heavy: DataFrame, queries: DataFrame) -> DataFrame:
    """Per query: reported, heavy and found keys, recall and precision (1 where there is nothing to find or to report)."""
    found = report.select("query_id", "key").join(unbroadcast(heavy.select("query_id", "key")), ["query_id", "key"], "left_semi").groupBy("query_id").agg(F.count("*").alias("found"))
    sizes = report.groupBy("query_id").agg(F.count("*").alias("reported"))
    truth = heavy.groupBy("query_id").agg(F.count("*").alias("heavy"))
    out = queries.select("query_id").distinct().join(unbroadcast(sizes), "query_id", "left").join(unbroadcast(truth), "query_id", "left").join(unbroadcast(found), "query_id", "left").fillna(0)
    share = lambda a, b: F.when(F.col(b) > 0, F.col(a) / F.col(b)).otherwise(1.0)
    return out.withColumns({"recall": share("found", "heavy"), "precision": share("found", "reported")})


def is_correct(report: DataFrame, heavy: DataFrame, suspect: DataFrame | None = None, cap: int | None = None) -> DataFrame:
    """(query_id, missed, excess): heavy keys not reported, and reported keys that are no suspects or beyond the cap."""
    missed = heavy.join(report, ["query_id", "key"], "left_anti").groupBy("query_id").agg(F.count("*").alias("missed"))
    if suspect is not None:
        excess = report.join(suspect, ["query_id", "key"], "left_anti").groupBy("query_id").agg(F.count("*").alias("excess"))
    else:
        excess = report.groupBy("query_id").agg(F.greatest(F.count("*") - F.lit(cap or 0), F.lit(0)).alias("excess"))
    return missed.join(excess, "query_id", "full_outer").fillna(0)


def value_correct(report: DataFrame, vec: DataFrame, tail2: DataFrame, alpha: float, k: int) -> DataFrame:
    """Per query the reported values and how many lie within sqrt(alpha / k) of the tail norm."""
    joined = report.select("query_id", "key", "v_hat").join(vec.select("query_id", "key", "value"), ["query_id", "key"], "left").join(tail2, "query_id")
    near = F.pow(F.col("v_hat") - F.coalesce("value", F.lit(0)), 2) * k <= alpha * F.col("tail2")
    return joined.groupBy("query_id").agg(F.count("*").alias("values"), F.sum(F.when(near, 1).otherwise(0)).alias("within"))


def linf_l2_error(estimates: DataFrame, vec: DataFrame, tail2: DataFrame, k: int) -> DataFrame:
    """Per query the largest squared error of all keys, and that error as a multiple of tail^2 / k."""
    joined = estimates.join(unbroadcast(vec.select("query_id", "key", "value")), ["query_id", "key"], "left")
    worst = joined.groupBy("query_id").agg(F.max(F.pow(F.col("v_hat") - F.coalesce("value", F.lit(0)), 2)).alias("worst2"))
    return worst.join(unbroadcast(tail2), "query_id").select("query_id", "worst2", (F.col("worst2") * k / F.col("tail2")).alias("alpha"))


def agreement_error(agreed: DataFrame, truth: DataFrame) -> DataFrame:
    """Per query the largest deviation of measured from true agreement over keys and signs."""
    t = truth.select("query_id", "key", F.col("p_plus").alias("t_plus"), F.col("p_minus").alias("t_minus"))
    both = agreed.join(t, ["query_id", "key"])
    gap = F.greatest(F.abs(F.col("p_plus") - F.col("t_plus")), F.abs(F.col("p_minus") - F.col("t_minus")))
    return both.groupBy("query_id").agg(F.max(gap).alias("worst"))


def generalization_gap(counted: DataFrame, truth: DataFrame, buckets: int, width: int) -> DataFrame:
    """Mean of each key's two predicates over all buckets less their expectation p / width."""
    t = truth.select("query_id", "key", F.col("p_plus").alias("t_plus"), F.col("p_minus").alias("t_minus"))
    both = counted.join(t, ["query_id", "key"])
    gap = lambda n, p: F.abs(F.col(n) / buckets - F.col(p) / width)
    return both.select("query_id", "key", F.greatest(gap("pos", "t_plus"), gap("neg", "t_minus")).alias("gap"))


def churn(reports: DataFrame) -> DataFrame:
    """(key, changes): entries and exits of each key over the steps of a continuous report (query_id, key)."""
    steps = Window.partitionBy("key").orderBy("query_id")
    last = reports.agg(F.max("query_id")).first()[0]
    marked = reports.select("query_id", "key").distinct().withColumns({"before": F.lag("query_id").over(steps), "after": F.lead("query_id").over(steps)})
    enters = F.when(F.col("before").isNull() | (F.col("before") < F.col("query_id") - 1), 1).otherwise(0)
    leaves = F.when((F.col("after").isNull() | (F.col("after") > F.col("query_id") + 1)) & (F.col("query_id") < F.lit(last)), 1).otherwise(0)
    return marked.groupBy("key").agg(F.sum(enters + leaves).alias("changes"))


# -- budgets --------------------------------------------------------------------------------------
def budget_threshold(suspects: DataFrame, width: int, c_a: float) -> DataFrame:
    """Both forms of the sequence's cost over (query_id, key) suspects: one row.

    ``budget_min`` is the smaller of the largest count of a key and the total over c_a x width, as the
    definition is printed; ``budget_safe`` the larger, which the proofs need.
    """
    per_key = suspects.groupBy("key").agg(F.count("*").alias("n"))
    largest, total = F.coalesce(F.max("n"), F.lit(0)).cast("double"), F.coalesce(F.sum("n"), F.lit(0)) / (c_a * width)
    return per_key.agg(largest.alias("most_of_a_key"), total.alias("spread_total")).withColumns({"budget_min": F.least("most_of_a_key", "spread_total"), "budget_safe": F.greatest("most_of_a_key", "spread_total")})


def flips(agreed: DataFrame, tau_a: float = TAU_A, tau_b: float = TAU_B) -> DataFrame:
    """(key, flips): alternations between low and high agreement along the sequence; the neutral band is skipped.

    A key starts low, so its first high step counts.
    """
    gap = tau_b - tau_a
    best = F.greatest("p_plus", "p_minus")
    signal = F.when(best <= tau_a + 2 * gap / 5, 0).when(best >= tau_b - 2 * gap / 5, 1)
    said = agreed.select("query_id", "key", signal.alias("signal")).where("signal is not null")
    before = F.coalesce(F.lag("signal").over(Window.partitionBy("key").orderBy("query_id")), F.lit(0))
    return said.withColumn("before", before).groupBy("key").agg(F.sum(F.when(F.col("signal") != F.col("before"), 1).otherwise(0)).alias("flips"))


def useful_buckets(participation: DataFrame, cost: DataFrame, limit: int) -> DataFrame:
    """Per key its buckets and how many are useful: those whose keys cost at most ``limit`` together.

    ``participation`` is (key, row, bucket), ``cost`` (key, cost) per key of the sequence.
    """
    costs = participation.join(cost, "key", "left").groupBy("row", "bucket").agg(F.coalesce(F.sum("cost"), F.lit(0)).alias("total"))
    marked = participation.join(costs, ["row", "bucket"])
    return marked.groupBy("key").agg(F.count("*").alias("part"), F.sum(F.when(F.col("total") <= limit, 1).otherwise(0)).alias("useful")).withColumn("share", F.col("useful") / F.col("part"))


# -- attacks --------------------------------------------------------------------------------------
def bnr(tail_estimates: DataFrame, norm2: DataFrame, width: int) -> DataFrame:
    """Bias-to-noise ratio of keys: median bucket estimate of the attack tail over its deviation sqrt(norm2 / width)."""
    medians = tail_estimates.groupBy("query_id", "key").agg(F.median("est").alias("bias"))
    return medians.join(norm2, "query_id").select("query_id", "key", (F.col("bias") / F.sqrt(F.col("norm2") / width)).alias("bnr"))


def rounds_to(curve: DataFrame, targets: list[float]) -> DataFrame:
    """(seed, target, rounds): first round at which the ratio reaches each target, from (seed, round, bnr)."""
    wanted = F.explode(F.array(*map(F.lit, targets))).alias("target")
    return curve.select("*", wanted).where(F.col("bnr") >= F.col("target")).groupBy("seed", "target").agg(F.min("round").alias("rounds"))


def fit_rounds(reached: DataFrame) -> DataFrame:
    """Per target: mean factor rounds / (target^2 rows) and the slope of log rounds on log rows."""
    log = reached.withColumns({"x": F.log("rows"), "y": F.log("rounds"), "factor": F.col("rounds") / (F.col("target") * F.col("target") * F.col("rows"))})
    return log.groupBy("target").agg(F.avg("factor").alias("factor"), F.regr_slope("y", "x").alias("slope"))


def fit_growth(curves: DataFrame) -> DataFrame:
    """(rows, factor, runs, slope) from whole curves (seed, rows, round, bnr).

    The square of the ratio grows in proportion to the rounds; its rate, fitted through the origin in each
    run, gives rounds = factor x bnr^2 x rows, and the slope of log rounds on log rows at equal ratio.
    """
    square = F.col("bnr") * F.col("bnr")
    rates = curves.groupBy("rows", "seed").agg((F.sum(F.col("round") * square) / F.sum(F.col("round") * F.col("round"))).alias("rate"))
    by_rows = rates.groupBy("rows").agg(F.avg("rate").alias("rate"), F.count("*").alias("runs"))
    slope = by_rows.agg(F.regr_slope(-F.log("rate"), F.log("rows")).alias("slope"))
    return by_rows.crossJoin(F.broadcast(slope)).select("rows", (1 / (F.col("rate") * F.col("rows"))).alias("factor"), "runs", "slope")


def band(curve: DataFrame, by: list[str], value: str) -> DataFrame:
    return curve.groupBy(*by).agg(F.avg(value).alias("mean"), F.min(value).alias("least"), F.max(value).alias("most"))


def collection_rate(collected: DataFrame) -> DataFrame:
    """(rounds, collected, rate) over (tail_id, sign), sign 0 meaning not collected."""
    taken = F.sum(F.when(F.col("sign") != 0, 1).otherwise(0))
    return collected.agg(F.count("*").alias("rounds"), taken.alias("collected"), (taken / F.count("*")).alias("rate"))


def cost(layout, queries: int, keys: int, asks: int = 0, passes: int = 0) -> dict[str, float]:
    """Cells and bytes of a sketch, buckets touched by an update and a query, and what the gate did."""
    return {"cells": layout.size, "bytes": 8 * layout.size, "update_work": layout.per_key, "query_work": layout.per_key * keys * queries, "asks": asks, "passes": passes}


def rounds_survived(correct: DataFrame) -> int:
    """Rounds before the first wrong output, over (query_id, missed, excess)."""
    wrong = correct.where("missed > 0 or excess > 0").agg(F.min("query_id")).first()[0]
    return int(wrong) if wrong is not None else int(correct.agg(F.count("*")).first()[0])

"""Black-box attacks that collect tails on which a borderline key is reported, and the game they play.

All rounds but the last are fixed in advance, so they run as one batch with query_id = tail_id. Linearity
keeps the cost down: a query is a few special keys plus or minus a tail, so its estimates at the special
keys are the tail's estimates there plus constants of the special keys, and only the buckets that hold a
special key are ever computed.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .layouts import RowHashed


@dataclass(frozen=True)
class Probe:
    """Special keys and their weights: the designated key, an equal twin, control keys of weight 0, very heavy others."""

    layout: RowHashed
    designated: int
    twin: int
    control: int
    heavy: tuple[int, ...]
    border: int
    very: int

    @property
    def weights(self) -> dict[int, int]:
        return {self.designated: self.border, self.twin: self.border, **dict.fromkeys(self.heavy, self.very)}

    @staticmethod
    def make(layout: RowHashed, k_out: int, first_key: int, border: int, very: int) -> Probe:
        """``k_out - 1`` very heavy keys beside the two borderline ones."""
        return Probe(layout, first_key, first_key + 1, first_key + 2, tuple(range(first_key + 3, first_key + 2 + k_out)), border, very)


def special_participation(spark: SparkSession, probe: Probe) -> DataFrame:
    """(key, row, bucket, sign, weight) of all special keys: a few times the rows."""
    rows = [(k, w) for k, w in probe.weights.items()] + [(probe.control, 0)]
    return probe.layout.participation(spark.createDataFrame(rows, "key bigint, weight bigint"))


def probe_estimates(tails: DataFrame, probe: Probe, keys: list[int]) -> DataFrame:
    """(tail_id, key, row, special, noise): each wanted key's estimate from the special keys and from the tail, by row."""
    spark = tails.sparkSession
    special = special_participation(spark, probe)
    held = special.select("row", "bucket", F.col("sign").alias("s2"), "weight")
    wanted = special.where(F.col("key").isin(keys)).select("key", "row", "bucket", "sign")
    fixed = wanted.join(held, ["row", "bucket"]).groupBy("key", "row", "bucket", "sign").agg(F.sum(F.col("sign") * F.col("s2") * F.col("weight")).alias("special"))
    spread = probe.layout.participation(tails)
    cells = spread.join(F.broadcast(fixed.select("row", "bucket").distinct()), ["row", "bucket"], "left_semi").groupBy("tail_id", "row", "bucket").agg(F.sum(F.col("sign") * F.col("value")).alias("c"))
    every = tails.select("tail_id").distinct().join(F.broadcast(fixed))
    return every.join(cells, ["tail_id", "row", "bucket"], "left").select("tail_id", "key", "row", "special", (F.col("sign") * F.coalesce("c", F.lit(0))).alias("noise"))


def median_rounds(est: DataFrame, probe: Probe) -> DataFrame:
    """(tail_id, reported): whether the designated key's median magnitude beats its twin's; null for a tie.

    The very heavy keys fill all places of the report but one, for which these two compete.
    """
    medians = est.where(F.col("key").isin(probe.designated, probe.twin)).groupBy("tail_id", "key").agg(F.median(F.col("special") + F.col("noise")).alias("v_hat"))
    own = F.max(F.when(F.col("key") == probe.designated, F.abs("v_hat")))
    other = F.max(F.when(F.col("key") == probe.twin, F.abs("v_hat")))
    return medians.groupBy("tail_id").agg(F.when(own > other, True).when(own < other, False).alias("reported"))


def value_rounds(est: DataFrame, probe: Probe) -> DataFrame:
    """(tail_id, reported): the variant that sees values; the sign of the reported value less the true weight."""
    own = est.where(F.col("key") == probe.designated).groupBy("tail_id").agg(F.median(F.col("special") + F.col("noise")).alias("v_hat"))
    return own.select("tail_id", F.when(F.col("v_hat") > probe.border, True).when(F.col("v_hat") < probe.border, False).alias("reported"))


def collect(rounds: DataFrame, how: str) -> DataFrame:
    """(tail_id, sign): +1, -1 or 0. ``signed`` takes the tail or its negation; ``missed`` takes the tail when the key is missed."""
    hit = F.col("reported")
    sign = F.when(hit, 1).when(~hit, -1) if how == "signed" else F.when(~hit, 1)
    return rounds.select("tail_id", F.coalesce(sign, F.lit(0)).alias("sign"))


def agreement_rounds(est: DataFrame, probe: Probe, tau: float) -> DataFrame:
    """(tail_id, plus, minus, sign): reports of the sign-agreement rule with the tail and with its negation; one report alone decides."""
    own = est.where(F.col("key") == probe.designated)
    rows = float(probe.layout.rows)
    agrees = lambda sign: F.sum(F.when(F.lit(probe.border) + sign * F.col("noise") > 0, 1).otherwise(0)) / rows >= tau
    both = own.groupBy("tail_id").agg(agrees(1).alias("plus"), agrees(-1).alias("minus"))
    return both.withColumn("sign", F.when(F.col("plus") & ~F.col("minus"), 1).when(F.col("minus") & ~F.col("plus"), -1).otherwise(0))


def robust_rounds(est: DataFrame, probe: Probe, level: float, noise: Callable[[int, int, int], float], repeats: int) -> list[tuple[int, int, int]]:
    """(tail_id, sign, queries) of the attack on the noisy report: each tail and its negation asked ``repeats`` times.

    The asks of one tail are sequential in the gate, so the counts come to the driver: two numbers a tail.
    """
    own = est.where(F.col("key") == probe.designated)
    votes = lambda sign: F.sum(F.when(F.lit(probe.border) + sign * F.col("noise") > 0, 1).otherwise(0))
    counts = own.groupBy("tail_id").agg(votes(1).alias("plus"), votes(-1).alias("minus")).orderBy("tail_id").collect()
    out = []
    for tail_id, plus, minus in counts:
        hits = [sum(n + noise(tail_id, side, j) >= level for j in range(repeats)) for side, n in enumerate((plus, minus))]
        out.append((tail_id, (hits[0] > hits[1]) - (hits[0] < hits[1]), 2 * repeats))
    return out


def attack_tail(tails: DataFrame, collected: DataFrame) -> DataFrame:
    """The vector (key, value) the attack ends with: collected tails with their signs."""
    signs = collected.where("sign <> 0")
    return tails.join(signs, "tail_id").select("key", (F.col("sign") * F.col("value")).alias("value"))


def bnr_curve(est: DataFrame, collected: DataFrame, tails: DataFrame, probe: Probe) -> DataFrame:
    """(round, key, bnr) after each round that collected a tail, from the rounds' own estimates by linearity."""
    signs = collected.where("sign <> 0").withColumn("round", F.row_number().over(Window.orderBy("tail_id")))
    moved = est.join(F.broadcast(signs), "tail_id").select("round", "key", "row", (F.col("sign") * F.col("noise")).alias("x"))
    sums = moved.withColumn("bias", F.sum("x").over(Window.partitionBy("key", "row").orderBy("round")))
    medians = sums.groupBy("round", "key").agg(F.median("bias").alias("bias"))
    energy = tails.join(signs, "tail_id").groupBy("round").agg(F.sum(F.col("value") * F.col("value")).alias("e"))
    norm2 = energy.withColumn("norm2", F.sum("e").over(Window.orderBy("round"))).select("round", "norm2")
    return medians.join(norm2, "round").select("round", "key", (F.col("bias") / F.sqrt(F.col("norm2") / probe.layout.width)).alias("bnr"))


def final_vector(tail: DataFrame, probe: Probe, mode: str, weight: int) -> DataFrame:
    """(query_id, key, value) of the last query: ``mask`` hides a heavy designated key, ``phantom`` has it at weight 0."""
    at = weight if mode == "mask" else 0
    sign = -1 if mode == "mask" else 1
    spark = tail.sparkSession
    head = spark.createDataFrame([(probe.designated, at)], "key bigint, value bigint").where("value <> 0")
    body = tail.select("key", (F.lit(sign) * F.col("value")).alias("value"))
    return head.unionAll(body).select(F.lit(0).cast("bigint").alias("query_id"), "key", "value")


def calibrate_weight(rate_at: Callable[[int], float], low: int, high: int, target: float = 0.5, steps: int = 12) -> int:
    """The weight at which the designated key is reported at about the target rate, by bisection on the rate."""
    for _ in range(steps):
        middle = (low + high) // 2
        if rate_at(middle) < target:
            low = middle + 1
        else:
            high = middle
        if low >= high:
            break
    return high


def search_border(ask: Callable[[int, int], bool], first: int = 1, asks: int = 9, most: int = 1 << 40) -> list[tuple[int, int]]:
    """The search for a borderline weight by one who knows no parameters: (weight, reports out of ``asks``) of each step.

    ``ask(weight, j)`` is whether the key is reported at that weight beside tail j. The weight is doubled until
    the key is reported every time, then halved into the interval until the answers are mixed.
    """
    steps: list[tuple[int, int]] = []

    def rate(weight: int) -> int:
        steps.append((weight, sum(ask(weight, j) for j in range(asks))))
        return steps[-1][1]

    high = first
    while rate(high) < asks and high < most:
        high *= 2
    low = high // 2
    while high - low > 1 and not 0 < steps[-1][1] < asks:
        middle = (low + high) // 2
        low, high = (middle, high) if rate(middle) == 0 else (low, middle)
    return steps


def as_updates(tails: DataFrame, probe: Probe) -> DataFrame:
    """(seq, key, value): the attack as single-key updates, each tail put in and then taken out, 2 m updates a swap.

    The special keys rise by one with every tail, so that they stay reported while the tail changes.
    """
    put = tails.select("tail_id", F.lit(0).alias("phase"), "key", "value")
    take = tails.select("tail_id", F.lit(2).alias("phase"), "key", (-F.col("value")).alias("value"))
    keep = tails.select("tail_id").distinct().select("tail_id", F.lit(1).alias("phase"), F.lit(probe.designated).cast("bigint").alias("key"), F.lit(1).cast("bigint").alias("value"))
    ordered = put.unionAll(keep).unionAll(take)
    # Numbered within each tail and moved by what the tails before it have: no window holds all updates.
    own = F.row_number().over(Window.partitionBy("tail_id").orderBy("phase", "key")) - 1
    sizes = ordered.groupBy("tail_id").agg(F.count("*").alias("n"))
    before = F.coalesce(F.sum("n").over(Window.orderBy("tail_id").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    starts = sizes.select("tail_id", before.alias("start"))
    return ordered.withColumn("own", own).join(starts, "tail_id").select((F.col("start") + F.col("own")).alias("seq"), "key", "value")


def feedback_tail(vec: DataFrame, labels: DataFrame) -> DataFrame:
    """Natural feedback: the sum of the queries that share a label, by (label, key)."""
    return vec.join(labels, "query_id").groupBy("label", "key").agg(F.sum("value").alias("value"))


def with_margin(agreed: DataFrame, low: float, high: float) -> DataFrame:
    """Drops the (query, key) pairs between two agreements: inputs that keep away from the boundary."""
    best = F.greatest("p_plus", "p_minus")
    return agreed.where((best <= low) | (best >= high))


def play(analyst: Callable[[list], DataFrame | None], system: Callable[[int, DataFrame], list], rounds: int) -> list[list]:
    """The adaptive game: the analyst sees the reports so far and picks the next vector, or None to stop."""
    said: list[list] = []
    for q in range(rounds):
        vector = analyst(said)
        if vector is None:
            break
        said.append(system(q, vector))
    return said

"""Many initializations of a sketch under attack in one plan.

A spot is a bucket of a special key in one sketch. Whether a tail key falls into it, and with which sign,
are polynomials whose coefficients are columns of the spot, so sketches of any sizes, seeds and layouts go
through one join of the tails with a small table of spots. The rounds of an attack on a rule without
memory are a batch; the gate's are played in order, one group of rows for each sketch.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass
from math import sqrt

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.hashing import PRIME, coefficients
from ..plans.physical import sized_broadcast
from .gate import AT_LEAST, Gate
from .layouts import IndependentBuckets, Layout, RowHashed

#: Roles of special keys.
DESIGNATED, TWIN, CONTROL = 1, -1, 0
_POWERS = 5


@dataclass(frozen=True)
class Contender:
    """A sketch under attack and the weights of its special keys, in deviations of the noise of a tail."""

    sketch: int
    layout: Layout
    k_out: int = 1
    border: float = 2.0
    very: float = 40.0


def _value(coefs: Sequence[Sequence[int]], key: int, at: int) -> int:
    out = 0
    for c in reversed(coefs):
        out = (out * key + c[at]) % PRIME
    return out


def _pad(coefs: Sequence[Sequence[int]], at: int) -> list[int]:
    return [c[at] for c in coefs] + [0] * (_POWERS - len(coefs))


def _own_spots(layout: Layout, key: int) -> dict[tuple[int, int], tuple[int, list[int], list[int]]]:
    """(row, bucket) -> sign, coefficients of the place and of the sign, for each bucket of a key."""
    if isinstance(layout, RowHashed):
        places, signs = coefficients(layout.seed, 0, layout.rows, layout.degree), coefficients(layout.seed, 1, layout.rows, layout.degree)
        return {(r, _value(places, key, r) % layout.width): (1 - 2 * (_value(signs, key, r) % 2), _pad(places, r), _pad(signs, r)) for r in range(layout.rows)}
    places, signs = coefficients(layout.seed, 2, layout.buckets, 2), coefficients(layout.seed, 3, layout.buckets, 4)
    held = [t for t in range(layout.buckets) if _value(places, key, t) < PRIME // layout.width]
    return {(0, t): (1 - 2 * (_value(signs, key, t) % 2), _pad(places, t), _pad(signs, t)) for t in held}


def spots(spark: SparkSession, contenders: Sequence[Contender], first_key: int, deviation: float) -> DataFrame:
    """(sketch, role, spot, own_sign, border, special, width, bucket, p0.., s0..) for the designated key, its twin and a control key.

    ``special`` is the estimate that the special keys alone give there. ``deviation`` is that of a tail's
    values times the root of its keys; a bucket's is that over the root of the width.
    """
    out = []
    for c in contenders:
        layout = c.layout
        noise = deviation / sqrt(layout.width)
        border, very = max(1, int(c.border * noise)), max(2, int(c.very * noise))
        weights = {first_key: border, first_key + 1: border, first_key + 2: 0, **{first_key + 3 + j: very for j in range(c.k_out - 1)}}
        if c.k_out < 2:
            weights[first_key + 1] = 0  # rules without competition have the designated key alone
        own = {key: _own_spots(layout, key) for key in weights}
        cells: dict[tuple[int, int], int] = {}
        for key, held in own.items():
            for at, (sign, _, _) in held.items():
                cells[at] = cells.get(at, 0) + sign * weights[key]
        for key, role in ((first_key, DESIGNATED), (first_key + 1, TWIN), (first_key + 2, CONTROL)):
            for (row, bucket), (sign, place, signs) in own[key].items():
                row_hashed = isinstance(layout, RowHashed)
                out.append((c.sketch, role, row if row_hashed else bucket, sign, border, sign * cells[row, bucket], layout.width, bucket if row_hashed else -1, *place, *signs))
    powers = ", ".join([f"p{j} bigint" for j in range(_POWERS)] + [f"s{j} bigint" for j in range(_POWERS)])
    return spark.createDataFrame(out, f"sketch int, role int, spot int, own_sign int, border bigint, special bigint, width int, bucket int, {powers}")


def _poly(prefix: str) -> Column:
    out = F.col(f"{prefix}{_POWERS - 1}")
    for j in range(_POWERS - 2, -1, -1):
        out = (out * F.col("key") + F.col(f"{prefix}{j}")) % PRIME
    return out


def spot_noise(tails: DataFrame, held: DataFrame, count: int) -> DataFrame:
    """(sketch, role, tail_id, spot, border, special, noise): what each tail (tail_id, key, value) adds to each of ``count`` spots."""
    place = _poly("p")
    inside = F.when(F.col("bucket") >= 0, place % F.col("width") == F.col("bucket")).otherwise(place < F.floor(F.lit(PRIME) / F.col("width")))
    met = tails.crossJoin(sized_broadcast(held, count)).where(inside)
    sign = (1 - 2 * (_poly("s") % 2)) * F.col("own_sign")
    sums = met.groupBy("sketch", "role", "tail_id", "spot").agg(F.sum(sign * F.col("value")).alias("noise"))
    every = tails.select("tail_id").distinct().crossJoin(sized_broadcast(held.select("sketch", "role", "spot", "border", "special", "width"), count))
    return every.join(sums, ["sketch", "role", "tail_id", "spot"], "left").fillna({"noise": 0})


# -- rules without memory -------------------------------------------------------------------------
def median_signs(noise: DataFrame, how: str = "signed") -> DataFrame:
    """(sketch, tail_id, sign): +1 to collect the tail, -1 its negation, 0 neither (ties, and rounds not wanted by ``missed``)."""
    by_key = noise.where(F.col("role") != CONTROL).groupBy("sketch", "tail_id", "role").agg(F.abs(F.median(F.col("special") + F.col("noise"))).alias("v"))
    own, twin = F.max(F.when(F.col("role") == DESIGNATED, F.col("v"))), F.max(F.when(F.col("role") == TWIN, F.col("v")))
    lead = F.signum(own - twin)
    return by_key.groupBy("sketch", "tail_id").agg((lead if how == "signed" else F.when(lead < 0, 1).otherwise(0)).cast("int").alias("sign"))


def agreement_signs(noise: DataFrame, tau: float) -> DataFrame:
    """Signs from asking each tail and its negation of the plain sign-agreement rule, two queries a tail."""
    own = noise.where(F.col("role") == DESIGNATED)
    says = lambda sign: F.avg(F.when(F.col("border") + sign * F.col("noise") > 0, 1.0).otherwise(0.0)) >= tau
    both = own.groupBy("sketch", "tail_id").agg(says(1).cast("int").alias("plus"), says(-1).cast("int").alias("minus"))
    return both.select("sketch", "tail_id", (F.col("plus") - F.col("minus")).alias("sign"))


def curves(noise: DataFrame, signs: DataFrame, tails: DataFrame, role: Column | None = None) -> DataFrame:
    """(sketch, role, round, bnr) after each collected tail, from the rounds' own numbers by linearity."""
    in_order = Window.partitionBy("sketch").orderBy("tail_id")
    energy = tails.groupBy("tail_id").agg(F.sum(F.col("value") * F.col("value")).alias("e"))
    taken = signs.where("sign <> 0").withColumn("round", F.row_number().over(in_order)).join(energy, "tail_id").withColumn("norm2", F.sum("e").over(in_order))
    rows = (noise if role is None else noise.where(role)).join(taken, ["sketch", "tail_id"])
    upto = F.sum(F.col("sign") * F.col("noise")).over(Window.partitionBy("sketch", "role", "spot").orderBy("round"))
    return rows.withColumn("bias", upto).groupBy("sketch", "role", "round").agg((F.median("bias") / F.sqrt(F.max("norm2") / F.max("width"))).alias("bnr"))


# -- the game against the gate --------------------------------------------------------------------
@dataclass(frozen=True)
class Rule:
    """A rule to play against: the plain agreement (no gate), or the gate with noise, access limit or both."""

    name: str
    gate: Gate | None
    repeats: int = 1


class _Session:
    """The designated key's buckets behind one rule, as an attacker meets them: asks in order, answers only."""

    def __init__(self, rule: Rule, buckets: int, tau: float, sketch: int):
        # Few buckets vary much in number, so the level is a share of those the key really has.
        self.rule, self.level, self.sketch = rule, tau * buckets, sketch
        self.accesses = np.zeros(buckets, np.int64)
        self.active = np.ones(buckets, bool)
        self.asks = 0

    def ask(self, estimates: np.ndarray) -> bool:
        """Whether the key is reported; a pass charges the buckets that agree."""
        agreeing = (estimates > 0) & self.active
        count = float(agreeing.sum())
        gate = self.rule.gate
        if gate is not None:
            count += gate.noise_value(0, AT_LEAST, self.sketch, self.asks)
        self.asks += 1
        reported = count >= self.level
        if reported and gate is not None and gate.limit is not None:
            self.accesses += agreeing
            self.active &= self.accesses < gate.limit
        return reported

    @property
    def retired(self) -> float:
        return 1 - float(self.active.mean()) if len(self.active) else 1.0


def play_rules(noise: DataFrame, tails: DataFrame, rules: Sequence[Rule], tau: float, weight: float, most_retired: float) -> DataFrame:
    """The adaptive game of every sketch against every rule, to the first wrong report or to the end of the tails.

    Each tail and its negation are asked ``repeats`` times and the likelier sign is collected. After each
    collected tail the analyst asks for the designated key at ``weight`` deviations of the tails collected so
    far, less those tails: the key is heavy, so a report without it is wrong. ``exhausted`` is the query at
    which more than ``most_retired`` of its buckets had been retired, where the guarantee ends by itself.
    (sketch, rule, queries, collected, wrong_at, exhausted, bnr), the last at the end of the game.
    """
    energy = tails.groupBy("tail_id").agg(F.sum(F.col("value") * F.col("value")).alias("e"))
    rows = noise.where(F.col("role") == DESIGNATED).join(energy, "tail_id").select("sketch", "tail_id", "spot", "border", "width", F.col("noise").cast("double").alias("noise"), F.col("e").cast("double").alias("e"))

    def of_sketch(frame: pd.DataFrame) -> pd.DataFrame:
        frame = frame.sort_values(["tail_id", "spot"])
        sketch, border, width = int(frame.sketch.iloc[0]), float(frame.border.iloc[0]), float(frame.width.iloc[0])
        matrix = frame.pivot(index="tail_id", columns="spot", values="noise").to_numpy()
        energies = frame.groupby("tail_id").e.first().to_numpy()
        out = []
        for rule in rules:
            session = _Session(rule, matrix.shape[1], tau, sketch)
            bias, norm2, collected, wrong, exhausted = np.zeros(matrix.shape[1]), 0.0, 0, None, None
            for tail, e in zip(matrix, energies):
                hits = [sum(session.ask(border + sign * tail) for _ in range(rule.repeats)) for sign in (1, -1)]
                sign = (hits[0] > hits[1]) - (hits[0] < hits[1])
                if exhausted is None and session.retired > most_retired:
                    exhausted = session.asks
                if not sign:
                    continue
                bias, norm2, collected = bias + sign * tail, norm2 + e, collected + 1
                if wrong is None and not session.ask(weight * sqrt(norm2 / width) - bias):
                    wrong = session.asks
                if wrong is not None or exhausted is not None:
                    break
            ratio = float(np.median(bias) / sqrt(norm2 / width)) if norm2 else 0.0
            out.append((sketch, rule.name, session.asks, collected, wrong, exhausted, ratio))
        return pd.DataFrame(out, columns=["sketch", "rule", "queries", "collected", "wrong_at", "exhausted", "bnr"]).astype({"wrong_at": "Int64", "exhausted": "Int64"})

    return rows.groupBy("sketch").applyInPandas(of_sketch, "sketch int, rule string, queries bigint, collected bigint, wrong_at bigint, exhausted bigint, bnr double")

"""Reports that stay right under adaptive inputs: sign agreement behind the noisy gate.

The serial rule asks about the keys in order, and an early pass may retire a bucket and lower later
counts. For tests of the at-least kind retiring can only lower counts, and the noise of a test is fixed
by its identity. So a key that fails with the buckets active at the start fails serially too: the
distributed pass leaves the few keys that pass there, and only those, with their buckets, are replayed
serially on the driver. The result equals the serial one exactly.
"""

from __future__ import annotations

import warnings
from collections.abc import Iterable
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.physical import sized_broadcast
from .gate import AT_LEAST, AT_MOST, Accesses, Gate, _uniform
from .layouts import Layout
from .sizing import TAU_A, TAU_B, mid, step_levels
from .weights import weight_of

#: Kinds of tests, part of a test's identity.
PLUS, MINUS, LEAVE, WEIGHT, VALID = 0, 1, 2, 3, 4
REPORT = "query_id bigint, key bigint, sign int, count int, noise_mode string"


class BudgetExhausted(RuntimeError):
    """Too many buckets of a key are retired for the guarantee to hold."""


class UnprovenLayout(UserWarning):
    """The guarantee needs independent buckets; on other layouts the report runs without it."""


@dataclass
class RobustReporter:
    """The robust threshold report over a sequence of queries; holds the gate's memory between them."""

    layout: Layout
    gate: Gate
    tau_a: float = TAU_A
    tau_b: float = TAU_B
    short_circuit: bool = True
    weights_up_to: int | None = None
    #: Largest share of a tested key's buckets that may be retired; beyond it the report stops with BudgetExhausted.
    most_retired: float | None = None
    accesses: Accesses = field(init=False)

    def __post_init__(self) -> None:
        self.accesses = Accesses(self.gate.limit)
        if not self.layout.proven:
            warnings.warn(f"{self.layout.fingerprint}: the guarantee is proven for independent buckets only", UnprovenLayout, stacklevel=3)

    def _healthy(self, query_id: int, key: int, buckets: list) -> None:
        if self.most_retired is not None and buckets:
            gone = sum((r, b) in self.accesses.retired for r, b, _ in buckets) / len(buckets)
            if gone > self.most_retired:
                raise BudgetExhausted(f"query {query_id}: {gone:.0%} of the buckets of key {key} are retired")

    @property
    def level(self) -> float:
        return self.layout.per_key * mid(self.tau_a, self.tau_b)

    def active(self, est: DataFrame) -> DataFrame:
        """Estimates of buckets that are not retired."""
        gone = sorted(self.accesses.retired)
        if not gone:
            return est
        side = est.sparkSession.createDataFrame(gone, "row int, bucket int")
        return est.join(sized_broadcast(side, len(gone)), ["row", "bucket"], "left_anti")

    def asked(self, est: DataFrame, level: float | None = None) -> DataFrame:
        """Noisy counts of both tests of every key over active buckets, and whether they pass the level."""
        level = self.level if level is None else level
        counted = self.active(est).groupBy("query_id", "key").agg(F.sum(F.when(F.col("est") > 0, 1).otherwise(0)).alias("pos"), F.sum(F.when(F.col("est") < 0, 1).otherwise(0)).alias("neg"))
        for name, kind in (("pos", PLUS), ("neg", MINUS)):
            noise = self.gate.noise_column(kind, AT_LEAST, F.col("query_id"), F.col("key"))
            counted = counted.withColumn(f"{name}_noisy", F.col(name) + noise).withColumn(f"{name}_pass", F.col(f"{name}_noisy") >= level)
        return counted

    def candidates(self, est: DataFrame, level: float | None = None) -> list[tuple[int, list[tuple[int, int, float]]]]:
        """The keys that pass either test at the start, in order, with their buckets: O(k) keys reach the driver."""
        passing = self.asked(est, level).where("pos_pass or neg_pass").select("query_id", "key")
        held = self.active(est).join(passing, ["query_id", "key"], "left_semi")
        rows = held.groupBy("key").agg(F.collect_list(F.struct("row", "bucket", "est")).alias("b")).orderBy("key").collect()
        return [(r["key"], [(b["row"], b["bucket"], b["est"]) for b in r["b"]]) for r in rows]

    def step(self, query_id: int, est: DataFrame) -> list[tuple[int, int, int, int | None]]:
        """Report one query: (key, sign, count, weight) of the keys that pass in serial order."""
        return self.replay(query_id, self.candidates(est), self.level)

    def run(self, est: DataFrame) -> dict[int, list[tuple[int, int, int, int | None]]]:
        """Report a whole sequence that is fixed in advance, in order of query_id: one distributed pass, one replay.

        Retiring only lowers counts, so what passes anywhere in the sequence passes with the buckets active
        now: the candidates of all queries come from one job.
        """
        passing = self.asked(est).where("pos_pass or neg_pass").select("query_id", "key")
        held = self.active(est).join(passing, ["query_id", "key"], "left_semi")
        rows = held.groupBy("query_id", "key").agg(F.collect_list(F.struct("row", "bucket", "est")).alias("b")).orderBy("query_id", "key")
        by_query: dict[int, list] = {}
        for r in rows.toLocalIterator():
            by_query.setdefault(r["query_id"], []).append((r["key"], [(b["row"], b["bucket"], b["est"]) for b in r["b"]]))
        return {q: self.replay(q, found, self.level) for q, found in by_query.items()}

    def replay(self, query_id: int, candidates: Iterable[tuple[int, list]], level: float) -> list[tuple[int, int, int, int | None]]:
        out = []
        for key, buckets in candidates:
            found = None
            self._healthy(query_id, key, buckets)
            for sign, kind in ((1, PLUS), (-1, MINUS)):
                agreeing = [(r, b) for r, b, est in buckets if est * sign > 0 and (r, b) not in self.accesses.retired]
                self.accesses.asks += 1
                if len(agreeing) + self.gate.noise_value(kind, AT_LEAST, query_id, key) >= level:
                    self.accesses.charge(agreeing)
                    found = found or (key, sign, len(agreeing))
                    if self.short_circuit:
                        break
            if found:
                out.append((*found, self.weigh(query_id, key, buckets)))
        return out

    def weigh(self, query_id: int, key: int, buckets: list) -> int | None:
        """The key's weight through the gate, at one more charge; None if weights are not asked for."""
        if self.weights_up_to is None:
            return None
        live = [(r, b, est) for r, b, est in buckets if (r, b) not in self.accesses.retired]
        values = np.array([est for _, _, est in live], float)
        weight, charged = weight_of(values, self.layout.per_key, self.weights_up_to, self.gate, lambda cell: _uniform(self.gate.seed, query_id, key, 100 + cell))
        self.accesses.charge([live[i][:2] for i in np.nonzero(charged)[0]])
        return weight

    def retired_share(self, keys: DataFrame) -> DataFrame:
        """(key, part, retired, share): health of each key's buckets."""
        spread = self.layout.participation(keys.select("key").distinct())
        gone = sorted(self.accesses.retired) or [(-1, -1)]
        side = keys.sparkSession.createDataFrame(gone, "row int, bucket int").withColumn("gone", F.lit(1))
        joined = spread.join(F.broadcast(side), ["row", "bucket"], "left")
        return joined.groupBy("key").agg(F.count("*").alias("part"), F.coalesce(F.sum("gone"), F.lit(0)).alias("retired")).withColumn("share", F.col("retired") / F.col("part"))

    def check_health(self, keys: DataFrame, most: float) -> None:
        worst = self.retired_share(keys).agg(F.max("share")).first()[0]
        if worst is not None and worst > most:
            raise BudgetExhausted(f"{worst:.0%} of a key's buckets are retired")

    def state(self, spark: SparkSession) -> DataFrame:
        rows = [(r, b, n, (r, b) not in self.accesses.retired) for (r, b), n in sorted(self.accesses.counts.items())]
        return spark.createDataFrame(rows, "row int, bucket int, accesses int, active boolean")


@dataclass
class ContinuousReporter(RobustReporter):
    """The robust hysteresis report: keys enter at the higher level and leave at the lower one.

    Weights, when asked for, are estimated on entry, follow the exact changes while a key is inside and
    are replaced when the gate finds them outside the noisy quantiles of the bucket estimates.
    """

    inside: dict[int, int] = field(default_factory=dict)
    weight: dict[int, int | None] = field(default_factory=dict)
    entries: int = 0
    exits: int = 0
    refreshed: int = 0

    def advance(self, query_id: int, est: DataFrame, changes: dict[int, int] | None = None) -> dict[int, tuple[int, int | None]]:
        """One step: ``est`` are the estimates after the step's changes, of the keys to ask and of all that are inside.

        Returns key -> (sign, weight). Only the buckets of keys that pass or are inside reach the driver.
        """
        low, high = (self.layout.per_key * t for t in step_levels(self.tau_a, self.tau_b))
        for key, by in (changes or {}).items():
            if self.weight.get(key) is not None:
                self.weight[key] += by
        est = est.persist()
        outside = est.join(self._inside(est), "key", "left_anti") if self.inside else est
        for key, sign, _, weight in self.replay(query_id, self.candidates(outside, high), high):
            self.inside[key], self.weight[key] = sign, weight
            self.entries += 1
        held = est.join(self._inside(est), "key", "left_semi").collect() if self.inside else []
        est.unpersist()
        buckets: dict[int, list] = {}
        for r in held:
            buckets.setdefault(r["key"], []).append((r["row"], r["bucket"], r["est"]))
        for wanted in (1, -1):
            for key in [k for k in sorted(self.inside) if self.inside[k] == wanted]:
                agreeing = [(r, b) for r, b, e in buckets.get(key, []) if e * wanted > 0 and (r, b) not in self.accesses.retired]
                self.accesses.asks += 1
                if len(agreeing) + self.gate.noise_value(LEAVE, AT_MOST, query_id, key) <= low:
                    self.accesses.charge(agreeing)
                    del self.inside[key], self.weight[key]
                    self.exits += 1
        if self.weights_up_to is not None:
            for key in sorted(self.inside):
                self._validate(query_id, key, buckets.get(key, []))
        return {k: (s, self.weight[k]) for k, s in self.inside.items()}

    def _inside(self, est: DataFrame) -> DataFrame:
        side = est.sparkSession.createDataFrame([(k,) for k in sorted(self.inside)], "key bigint")
        return sized_broadcast(side, len(self.inside))

    def wanted(self, candidates: DataFrame) -> DataFrame:
        """(query_id, key) of the candidates and of the keys that are inside, who must be able to leave."""
        if not self.inside:
            return candidates.select("query_id", "key")
        queries = candidates.select("query_id").distinct()
        return candidates.select("query_id", "key").unionAll(queries.crossJoin(self._inside(candidates)).select("query_id", "key")).distinct()

    def _validate(self, query_id: int, key: int, buckets: list) -> None:
        """Replace a kept weight when at most a tenth, or at least nine tenths, of the buckets lie below it."""
        kept = self.weight[key]
        live = [(r, b, e) for r, b, e in buckets if (r, b) not in self.accesses.retired]
        below = [(r, b) for r, b, e in live if kept is not None and e <= kept]
        self.accesses.asks += 2
        few = len(below) + self.gate.noise_value(VALID, AT_MOST, query_id, key) <= 0.1 * self.layout.per_key
        many = len(below) + self.gate.noise_value(VALID + 1, AT_LEAST, query_id, key) >= 0.9 * self.layout.per_key
        if kept is None or few or many:
            if kept is not None:
                self.accesses.charge(below)
            self.weight[key] = self.weigh(query_id, key, buckets)
            self.refreshed += 1


def serial_report(query_id: int, estimates: dict[int, list[tuple[int, int, float]]], reporter: RobustReporter) -> list[tuple]:
    """The rule as a plain loop over all keys in order: the reference that the distributed form must equal."""
    return reporter.replay(query_id, sorted(estimates.items()), reporter.level)

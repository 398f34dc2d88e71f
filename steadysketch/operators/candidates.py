"""A fast non-adaptive prefilter: keys that may be heavy, from signed sketches of key prefixes.

Level j sketches the vector whose entry at a prefix is the sum, with a random sign for each key, of the
keys that begin with it, so a prefix's square is about the sum of its keys' squares. A query walks down
the levels and keeps the prefixes of largest estimate; a key with a large share of the norm has a large
prefix on all levels. Levels are few and a step handles a bounded number of children for each kept
prefix, so a query costs O(kept x levels), not a pass over the keys.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import coefficients, poly_hash
from .estimators import median_estimate, top_by_magnitude
from .layouts import RowHashed
from .sketch import build, estimates


@dataclass(frozen=True)
class CandidateSketch:
    bits: int
    keep: int
    rows: int = 7
    width: int = 512
    seed: int = 77
    first: int = 8
    stride: int = 3

    def level(self, j: int) -> RowHashed:
        return RowHashed(self.rows, self.width, self.seed * 1000 + j)

    @property
    def levels(self) -> range:
        first = min(self.first, self.bits)
        return range(first + (self.bits - first) % self.stride, self.bits + 1, self.stride)

    def prefixes(self, vec: DataFrame, j: int) -> DataFrame:
        """The vector by prefix; at the last level, of the keys themselves, no sign is needed."""
        sign = 1 - 2 * (poly_hash(F.col("key"), [F.lit(c[0]).cast("bigint") for c in self.signs(j)]) % 2)
        value = F.col("value") if j == self.bits else sign * F.col("value")
        return vec.select("query_id", F.shiftright("key", self.bits - j).alias("key"), value.alias("value"))

    def signs(self, j: int) -> list[list[int]]:
        return coefficients(self.seed * 1000 + j, 5, 1, 3)

    def build(self, vec: DataFrame) -> dict[int, DataFrame]:
        return {j: build(self.prefixes(vec, j), self.level(j)) for j in self.levels}

    def query(self, cells: dict[int, DataFrame], queries: DataFrame) -> DataFrame:
        """(query_id, key): at most ``keep`` candidates for each query."""
        first = self.levels[0]
        alive = queries.select("query_id").distinct().withColumn("key", F.explode(F.sequence(F.lit(0), F.lit((1 << first) - 1)))).withColumn("key", F.col("key").cast("bigint"))
        for j in self.levels:
            if j > first:
                children = F.sequence(F.shiftleft("key", self.stride), F.shiftleft(F.col("key") + 1, self.stride) - 1)
                alive = alive.select("query_id", F.explode(children).alias("key"))
            v_hat = median_estimate(estimates(alive, cells[j], self.level(j)))
            alive = top_by_magnitude(v_hat, self.keep).select("query_id", "key")
        return alive


def keys_of(vec: DataFrame) -> DataFrame:
    """The exact alternative: the distinct keys of the input."""
    return vec.select("query_id", "key").distinct()

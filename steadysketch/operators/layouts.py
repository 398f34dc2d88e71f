"""Sketch layouts: which signed buckets a key takes part in.

Row-hashed: ``rows`` rows of ``width`` buckets, each key in one bucket of each row. Independent: ``size``
buckets, each key in each with probability 1/width, independently enough for the proofs (3-wise for the
choice, 5-wise for the sign); ``mode='skip'`` draws the buckets of a key by geometric jumps from a
counter-based generator, the law with full independence, at the cost of the expected rows / width draws
instead of a pass over all buckets.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import PRIME, coefficients, mix64, pick, poly_hash, sql_poly
from ..runtime import bounded_batches, ship


@dataclass(frozen=True)
class RowHashed:
    rows: int
    width: int
    seed: int = 1
    degree: int = 2
    proven: bool = False
    #: ``poly``: k-wise independent and portable; ``fast``: the engine's own 64-bit hash, for use without proofs.
    family: str = "poly"

    @property
    def per_key(self) -> int:
        """Expected buckets of a key."""
        return self.rows

    @property
    def size(self) -> int:
        return self.rows * self.width

    @property
    def fingerprint(self) -> str:
        return f"row-{self.rows}x{self.width}-{f'd{self.degree}' if self.family == 'poly' else self.family}-s{self.seed}"

    def participation(self, keyed: DataFrame) -> DataFrame:
        """Adds row, bucket and sign: ``rows`` rows for each key."""
        buckets, signs = coefficients(self.seed, 0, self.rows, self.degree), coefficients(self.seed, 1, self.rows, self.degree)
        row = F.col("row")
        spread = keyed.withColumn("row", F.explode(F.sequence(F.lit(0), F.lit(self.rows - 1))))
        if self.family == "fast":
            drawn = F.xxhash64(F.lit(self.seed), row, "key")
            return spread.withColumns({"bucket": F.pmod(drawn, F.lit(self.width)).cast("int"), "sign": F.lit(1).cast("bigint") - 2 * F.shiftrightunsigned(drawn, 63)})
        bucket = poly_hash(F.col("key"), [pick(c, row) for c in buckets]) % self.width
        sign = 1 - 2 * (poly_hash(F.col("key"), [pick(c, row) for c in signs]) % 2)
        return spread.withColumns({"bucket": bucket.cast("int"), "sign": sign.cast("bigint")})

    def sql(self, keyed: str) -> str:
        """SQL for the same frame over a relation with a key column."""
        bucket = sql_poly("key", coefficients(self.seed, 0, self.rows, self.degree), "r.row")
        sign = sql_poly("key", coefficients(self.seed, 1, self.rows, self.degree), "r.row")
        return f"SELECT t.*, CAST(r.row AS INTEGER) AS row, CAST(({bucket}) % {self.width} AS INTEGER) AS bucket, CAST(1 - 2 * (({sign}) % 2) AS BIGINT) AS sign FROM {keyed} t, (SELECT unnest(range(0, {self.rows})) AS row) r"


@dataclass(frozen=True)
class RowHashedCopies:
    """Independent copies of a row-hashed layout in one plan: copy c has the randomness of number c of its family.

    Coefficients are polynomials of the copy and row, so any number of copies needs no literals.
    """

    rows: int
    width: int
    seed: int = 1

    @property
    def size(self) -> int:
        return self.rows * self.width

    def _coefficients(self, role: int) -> list[list[list[int]]]:
        return [coefficients(self.seed * 100 + role * 10 + power, 7, 1, 3) for power in range(3)]

    def participation(self, keyed: DataFrame) -> DataFrame:
        """Adds row, bucket and sign to rows with a key and a copy."""
        place = F.col("copy") * 4096 + F.col("row")

        def own(role: int) -> Column:
            drawn = [poly_hash(place, [F.lit(c[0]).cast("bigint") for c in coefs]) for coefs in self._coefficients(role)]
            return poly_hash(F.col("key"), drawn)

        spread = keyed.withColumn("row", F.explode(F.sequence(F.lit(0), F.lit(self.rows - 1))))
        return spread.withColumns({"bucket": (own(0) % self.width).cast("int"), "sign": (1 - 2 * (own(1) % 2)).cast("bigint")})

    def sql(self, keyed: str) -> str:
        def own(role: int) -> str:
            drawn = ["(" + sql_poly("t.copy * 4096 + r.row", coefs, "0") + ")" for coefs in self._coefficients(role)]
            out = drawn[-1]
            for c in reversed(drawn[:-1]):
                out = f"(({out}) * key + {c}) % {PRIME}"
            return out

        return f"SELECT t.*, CAST(r.row AS INTEGER) AS row, CAST(({own(0)}) % {self.width} AS INTEGER) AS bucket, CAST(1 - 2 * (({own(1)}) % 2) AS BIGINT) AS sign FROM {keyed} t, (SELECT unnest(range(0, {self.rows})) AS row) r"


@dataclass(frozen=True)
class IndependentBuckets:
    buckets: int
    width: int
    seed: int = 1
    mode: str = "scan"
    proven: bool = True

    @property
    def per_key(self) -> float:
        return self.buckets / self.width

    @property
    def size(self) -> int:
        return self.buckets

    @property
    def fingerprint(self) -> str:
        return f"ind-{self.buckets}/{self.width}-{self.mode}-s{self.seed}"

    def participation(self, keyed: DataFrame) -> DataFrame:
        """Adds row (always 0), bucket and sign for the buckets each key takes part in; a key in none has no row."""
        if self.mode == "skip":
            return self._jump(keyed)
        choose, signs = coefficients(self.seed, 2, self.buckets, 2), coefficients(self.seed, 3, self.buckets, 4)
        t = F.col("bucket")
        spread = keyed.withColumn("bucket", F.explode(F.sequence(F.lit(0), F.lit(self.buckets - 1))))
        chosen = spread.where(poly_hash(F.col("key"), [pick(c, t) for c in choose]) < PRIME // self.width)
        sign = 1 - 2 * (poly_hash(F.col("key"), [pick(c, t) for c in signs]) % 2)
        return chosen.withColumns({"row": F.lit(0), "sign": sign.cast("bigint")})

    def sql(self, keyed: str) -> str:
        choose = sql_poly("key", coefficients(self.seed, 2, self.buckets, 2), "r.bucket")
        sign = sql_poly("key", coefficients(self.seed, 3, self.buckets, 4), "r.bucket")
        return f"SELECT t.*, 0 AS row, CAST(r.bucket AS INTEGER) AS bucket, CAST(1 - 2 * (({sign}) % 2) AS BIGINT) AS sign FROM {keyed} t, (SELECT unnest(range(0, {self.buckets})) AS bucket) r WHERE ({choose}) < {PRIME // self.width}"

    def _jump(self, keyed: DataFrame) -> DataFrame:
        """Each distinct key's buckets once, joined back to the rows: no shuffle of the expanded frame."""
        spark = keyed.sparkSession
        ship(spark)
        bounded_batches(spark, 2_000)
        size, width, seed = self.buckets, self.width, self.seed
        columns = keyed.columns

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                at, buckets, signs = [], [], []
                for i, key in enumerate(batch.column("key").to_pylist()):
                    spots, sign = jump(key, size, width, seed)
                    at.append(np.full(len(spots), i))
                    buckets.append(spots)
                    signs.append(sign)
                if at:
                    spread = batch.take(pa.array(np.concatenate(at)))
                    n = spread.num_rows
                    extra = [pa.array(np.concatenate(buckets), pa.int32()), pa.array(np.zeros(n), pa.int32()), pa.array(np.concatenate(signs), pa.int64())]
                    yield pa.RecordBatch.from_arrays([*spread.columns, *extra], [*columns, "bucket", "row", "sign"])

        kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in keyed.schema)
        return keyed.mapInArrow(run, f"{kinds}, bucket int, row int, sign bigint")


def jump(key: int, size: int, width: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    """Buckets and signs of a key: geometric gaps of success chance 1/width, a fixed function of (seed, key)."""
    rng = np.random.Generator(np.random.Philox(key=[mix64(seed), mix64(key & ((1 << 64) - 1))]))
    expected = size / width
    gaps = rng.geometric(1 / width, int(expected + 6 * expected**0.5 + 16))
    spots = np.cumsum(gaps) - 1
    while spots[-1] < size:
        spots = np.concatenate((spots, spots[-1] + np.cumsum(rng.geometric(1 / width, 64))))
    spots = spots[spots < size]
    return spots, 1 - 2 * rng.integers(0, 2, len(spots))


Layout = RowHashed | IndependentBuckets

"""Functions for SQL: hashing, agreement, and table functions that expand keys and report L2-heavy ones."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ..operators.layouts import RowHashed
from ..runtime import ship
from .hashing import PRIME, coefficients


def register(spark: SparkSession, layout: RowHashed) -> None:
    """Temporary SQL functions of a layout: row_bucket, row_sign, agreement (expressions that are inlined),
    and the table functions participation(key) and l2_heavy(TABLE t, k)."""
    ship(spark)

    def poly(role: int) -> str:
        coefs = coefficients(layout.seed, role, layout.rows, layout.degree)
        entry = lambda c: f"element_at(cast(split('{','.join(map(str, c))}', ',') as array<bigint>), r + 1)"
        out = entry(coefs[-1])
        for c in reversed(coefs[:-1]):
            out = f"(({out}) * k + {entry(c)}) % {PRIME}"
        return out

    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION row_bucket(k BIGINT, r INT) RETURNS INT RETURN cast(({poly(0)}) % {layout.width} AS INT)")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION row_sign(k BIGINT, r INT) RETURNS BIGINT RETURN 1 - 2 * (({poly(1)}) % 2)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION agreement(votes BIGINT, per_key DOUBLE) RETURNS DOUBLE RETURN votes / per_key")
    buckets, signs = coefficients(layout.seed, 0, layout.rows, layout.degree), coefficients(layout.seed, 1, layout.rows, layout.degree)
    rows, width = layout.rows, layout.width

    def value(coefs: list[list[int]], key: int, row: int) -> int:
        out = coefs[-1][row]
        for c in reversed(coefs[:-1]):
            out = (out * key + c[row]) % PRIME
        return out

    class Participation:
        def eval(self, key: int) -> Iterator[tuple[int, int, int]]:
            for row in range(rows):
                yield row, value(buckets, key, row) % width, 1 - 2 * (value(signs, key, row) % 2)

    class Heavy:
        """Exact L2-heavy keys of one partition's (query_id, key, value) rows; call it PARTITION BY query_id."""

        def __init__(self) -> None:
            self.sums: dict[int, int] = {}
            self.k, self.query_id = 1, None

        def eval(self, row, k: int) -> None:
            self.k, self.query_id = k, row["query_id"]
            self.sums[row["key"]] = self.sums.get(row["key"], 0) + row["value"]

        def terminate(self) -> Iterator[tuple[int | None, int, int]]:
            order = sorted(self.sums.items(), key=lambda x: (-abs(x[1]), x[0]))
            tail = sum(v * v for _, v in order[self.k :])
            for key, v in order[: self.k]:
                if v * v * self.k > tail:
                    yield self.query_id, key, v

    spark.udtf.register("participation", F.udtf(Participation, returnType="row int, bucket int, sign int"))
    spark.udtf.register("l2_heavy", F.udtf(Heavy, returnType="query_id bigint, key bigint, value bigint"))

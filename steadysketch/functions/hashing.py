"""Portable k-wise independent hashing: polynomials over the prime 2^31 - 1, the same in Spark and in SQL."""

from __future__ import annotations

from collections.abc import Callable, Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Modulus of the hash polynomials; keys must be below it.
PRIME = 2147483647
_MASK = (1 << 64) - 1


def mix64(x: int) -> int:
    """A mixing of 64-bit integers, for coefficients that look random for any seeds."""
    x = (x + 0x9E3779B97F4A7C15) & _MASK
    x = ((x ^ x >> 30) * 0xBF58476D1CE4E5B9) & _MASK
    x = ((x ^ x >> 27) * 0x94D049BB133111EB) & _MASK
    return x ^ x >> 31


def coefficients(seed: int, role: int, rows: int, degree: int) -> list[list[int]]:
    """``degree + 1`` lists, lowest power first, with a coefficient below PRIME for each row."""
    draw = lambda power, row: mix64(mix64(mix64(seed) ^ mix64(role << 32 | power)) + row) % PRIME
    return [[draw(power, row) for row in range(rows)] for power in range(degree + 1)]


def rowcoef(spark: SparkSession, seed: int, rows: int, roles: Sequence[str], degree: int) -> DataFrame:
    """The coefficients as a small table (row, role, a), lowest power first."""
    out = [(row, name, [c[row] for c in coefficients(seed, k, rows, degree)]) for k, name in enumerate(roles) for row in range(rows)]
    return spark.createDataFrame(out, "row int, role string, a array<bigint>")


def poly_hash(key: Column, coefs: Sequence[Column]) -> Column:
    """Value below PRIME of the polynomial at ``key``; products stay below 2^62."""
    out = coefs[-1]
    for c in reversed(coefs[:-1]):
        out = (out * key + c) % PRIME
    return out


def pick(values: Sequence[int], row: Column) -> Column:
    """Entry of a literal list by a 0-based row column."""
    if len(values) == 1:
        return F.lit(values[0]).cast("bigint")
    # One string that the optimizer folds to an array: thousands of literals are slow to analyse.
    return F.element_at(F.split(F.lit(",".join(map(str, values))), ",").cast("array<bigint>"), (row + 1).cast("int"))


def key_from_string(col: Column) -> Column:
    """28 bits of the MD5 digest: small enough for the polynomials, equal in other SQL engines."""
    return F.conv(F.substring(F.md5(col), 1, 7), 16, 10).cast("bigint")


def _cube(c: int) -> Callable[[Column], Column]:
    return lambda s: (s * s % PRIME * s + F.lit(c)) % PRIME


def uniform(seed: int, *parts: Column) -> Column:
    """A number strictly between 0 and 1 that is a fixed function of a secret seed and the given columns."""
    state = F.lit(mix64(seed) % PRIME).cast("bigint")
    for k, part in enumerate(parts):
        a, b, c = (mix64(seed * 31 + k * 7 + j) % PRIME for j in range(3))
        state = ((state * a + F.pmod(part.cast("bigint"), F.lit(PRIME))) % PRIME * b + c) % PRIME
        # Bound to a name once: written out, a cube of a cube repeats its expression nine times.
        state = F.element_at(F.transform(F.array(state), _cube(c)), 1)
    return (state.cast("double") + 0.5) / float(PRIME)


# -- the same as SQL text, for engines that check the results -------------------------------------
def sql_list(values: Sequence[int]) -> str:
    return "CAST([" + ",".join(map(str, values)) + "] AS BIGINT[])"


def sql_poly(key: str, coefs: Sequence[Sequence[int]], row: str) -> str:
    entry = lambda c: f"{sql_list(c)}[({row}) + 1]" if len(c) > 1 else f"CAST({c[0]} AS BIGINT)"
    out = entry(coefs[-1])
    for c in reversed(coefs[:-1]):
        out = f"(({out}) * ({key}) + {entry(c)}) % {PRIME}"
    return out


def sql_key(text: str) -> str:
    return f"CAST('0x' || substr(md5({text}), 1, 7) AS BIGINT)"

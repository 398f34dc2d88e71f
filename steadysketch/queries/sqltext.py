"""SQL text of the building blocks, for the engines that check the results."""

from __future__ import annotations

from ..functions.hashing import PRIME, mix64
from ..operators.candidates import CandidateSketch
from ..operators.gate import AT_LEAST, Gate
from ..operators.layouts import Layout
from ..sources.vectors import SQL as VECTOR_SQL


def with_(*steps: tuple[str, str], then: str) -> str:
    """Steps are computed once each, however often they are read."""
    return "WITH " + ", ".join(f"{name} AS MATERIALIZED ({text})" for name, text in steps) + " " + then


def vector(name: str) -> str:
    return VECTOR_SQL[name]


def cells(vec: str, layout: Layout) -> str:
    return f"SELECT query_id, row, bucket, CAST(sum(sign * value) AS BIGINT) AS c FROM ({layout.sql(vec)}) GROUP BY ALL"


def estimates(keys: str, cells_: str, layout: Layout) -> str:
    return f"SELECT p.query_id, p.key, p.row, p.bucket, CAST(p.sign * coalesce(c.c, 0) AS BIGINT) AS est FROM ({layout.sql(keys)}) p LEFT JOIN {cells_} c ON p.query_id = c.query_id AND p.row = c.row AND p.bucket = c.bucket"


def votes(est: str) -> str:
    return f"SELECT query_id, key, CAST(count(*) FILTER (est > 0) AS BIGINT) AS pos, CAST(count(*) FILTER (est < 0) AS BIGINT) AS neg, CAST(count(*) FILTER (est = 0) AS BIGINT) AS zero, count(*) AS part FROM {est} GROUP BY ALL"


def agreement(votes_: str, per_key: float | None) -> str:
    base = "CAST(part AS DOUBLE)" if per_key is None else f"CAST({per_key} AS DOUBLE)"
    return f"SELECT *, pos / {base} AS p_plus, neg / {base} AS p_minus FROM {votes_}"


def threshold(agreed: str, tau: float) -> str:
    return f"SELECT query_id, key, CASE WHEN p_plus >= {tau!r} THEN 1 ELSE -1 END AS sign, greatest(p_plus, p_minus) AS p_hat FROM {agreed} WHERE p_plus >= {tau!r} OR p_minus >= {tau!r}"


def medians(est: str) -> str:
    return f"SELECT query_id, key, CAST(median(est) AS DOUBLE) AS v_hat FROM {est} GROUP BY ALL"


def top(values: str, k: int) -> str:
    return f"SELECT * FROM (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY abs(v_hat) DESC, key) AS INTEGER) AS rank FROM {values}) WHERE rank <= {k}"


def heavy(vec: str, k: int, norm: str = "tail") -> str:
    ranked = f"SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY abs(value) DESC, key) AS rank FROM {vec}"
    base = f"FILTER (rank > {k})" if norm == "tail" else ""
    return f"SELECT r.query_id, r.key, r.value, a.norm2 FROM {vec} r JOIN (SELECT query_id, CAST(coalesce(sum(value * value) {base}, 0) AS BIGINT) AS norm2 FROM ({ranked}) GROUP BY ALL) a ON r.query_id = a.query_id WHERE r.value * r.value * {k} > a.norm2"


def tail2(vec: str, k: int) -> str:
    return f"SELECT query_id, CAST(coalesce(sum(value * value) FILTER (rank > {k}), 0) AS BIGINT) AS tail2 FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY abs(value) DESC, key) AS rank FROM {vec}) GROUP BY ALL"


def uniform(seed: int, *parts: str) -> str:
    state = f"CAST({mix64(seed) % PRIME} AS BIGINT)"
    for k, part in enumerate(parts):
        a, b, c = (mix64(seed * 31 + k * 7 + j) % PRIME for j in range(3))
        state = f"(((({state}) * {a} + (({part}) % {PRIME})) % {PRIME}) * CAST({b} AS BIGINT) + {c}) % {PRIME}"
        state = f"(list_transform([CAST({state} AS BIGINT)], lambda s: ((s * s % {PRIME}) * s + {c}) % {PRIME}))[1]"
    return f"((CAST({state} AS DOUBLE) + 0.5) / {float(PRIME)})"


def laplace(u: str, scale: float) -> str:
    return f"(list_transform([{u} - 0.5], lambda s: -({scale!r}) * sign(s) * ln(1 - 2 * abs(s))))[1]"


def noise(gate: Gate, kind: int, direction: int, *parts: str) -> str:
    wide, narrow = gate.scales
    a = laplace(uniform(gate.seed, *parts, str(2 * kind)), wide)
    b = laplace(uniform(gate.seed, *parts, str(2 * kind + 1)), narrow)
    capped = f"least({gate.cap!r}, {b})" if direction == AT_LEAST else f"greatest({-gate.cap!r}, {b})"
    return f"({a} + {capped})"


def candidates(vec: str, sketch: CandidateSketch) -> tuple[list[tuple[str, str]], str]:
    """Steps that end with a relation of (query_id, key) candidates, and its name."""
    from ..functions.hashing import sql_poly

    steps, alive = [], ""
    for j in sketch.levels:
        sign = f"1 - 2 * (({sql_poly('key', sketch.signs(j), '0')}) % 2)" if j < sketch.bits else "1"
        down = 1 << (sketch.bits - j)
        steps.append((f"prefix{j}", f"SELECT query_id, key // {down} AS key, CAST(sum(({sign}) * value) AS BIGINT) AS value FROM {vec} GROUP BY ALL"))
        steps.append((f"cells{j}", cells(f"prefix{j}", sketch.level(j))))
        if alive:
            wide = 1 << sketch.stride
            steps.append((f"tried{j}", f"SELECT query_id, key * {wide} + c AS key FROM {alive}, (SELECT unnest(range(0, {wide})) AS c)"))
        else:
            steps.append((f"tried{j}", f"SELECT query_id, CAST(c AS BIGINT) AS key FROM (SELECT DISTINCT query_id FROM {vec}), (SELECT unnest(range(0, {1 << j})) AS c)"))
        steps.append((f"est{j}", estimates(f"tried{j}", f"cells{j}", sketch.level(j))))
        steps.append((f"alive{j}", f"SELECT query_id, key FROM ({top('(' + medians(f'est{j}') + ')', sketch.keep)})"))
        alive = f"alive{j}"
    return steps, alive

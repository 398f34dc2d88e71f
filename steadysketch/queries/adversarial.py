"""Attacks, their measures, budgets and the experiment workloads."""

from __future__ import annotations

from math import sqrt

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import arena as R
from ..operators import attacks as A
from ..operators import estimators as E
from ..operators import metrics as M
from ..operators import sketch as S
from ..operators.gate import AT_LEAST, Gate, gate_delta
from ..operators.layouts import IndependentBuckets, RowHashed
from ..operators.sizing import C_A
from ..runtime import materialise
from ..sources import vectors as V
from . import sqltext as T
from .base import GATE, LEVELS, MID, PARTS, SMALL, USERS, query
from .sketches import HOURLY, agreed, agreed_sql, estimated, hourly_agreement, keys

#: Tails of the registered attacks: m keys each, at least five times the width; probe keys lie above all order keys.
M_KEYS, TAILS, FIRST = 60, 250, 1_500_000_000
ATTACKED = RowHashed(25, 10, seed=21, degree=4)
NOISE = 1000 * sqrt(M_KEYS / ATTACKED.width)
PROBE = A.Probe.make(ATTACKED, 3, FIRST, int(2 * NOISE), int(40 * NOISE))
LONE = A.Probe(ATTACKED, FIRST, FIRST + 1, FIRST + 2, (), int(1.2 * NOISE), 0)
TAU = 0.85


def _tails(spark: SparkSession, sf_dir: str) -> DataFrame:
    return V.tails(spark, sf_dir, M_KEYS, TAILS)


def _est_sql(probe: A.Probe) -> list[tuple[str, str]]:
    """Steps up to ``noise`` and ``special`` of each special key by tail and row."""
    weights = ", ".join(f"({k}::BIGINT, {w}::BIGINT)" for k, w in [*probe.weights.items(), (probe.control, 0)])
    return [
        ("tails", V.sql_tails(M_KEYS, TAILS)),
        ("specials", f"SELECT * FROM (VALUES {weights}) AS t(key, weight)"),
        ("sp", probe.layout.sql("specials")),
        ("fixed", "SELECT a.key, a.row, a.bucket, a.sign, CAST(sum(a.sign * b.sign * b.weight) AS BIGINT) AS special FROM sp a JOIN sp b ON a.row = b.row AND a.bucket = b.bucket GROUP BY ALL"),
        ("tp", probe.layout.sql("tails")),
        ("tc", "SELECT tail_id, row, bucket, CAST(sum(sign * value) AS BIGINT) AS c FROM tp GROUP BY ALL"),
        ("est", "SELECT t.tail_id, f.key, f.row, f.special, CAST(f.sign * coalesce(c.c, 0) AS BIGINT) AS noise FROM (SELECT DISTINCT tail_id FROM tails) t CROSS JOIN fixed f LEFT JOIN tc c ON c.tail_id = t.tail_id AND c.row = f.row AND c.bucket = f.bucket"),
    ]


def _rounds_sql(probe: A.Probe) -> list[tuple[str, str]]:
    med = f"SELECT tail_id, median(special + noise) FILTER (key = {probe.designated}) AS own, median(special + noise) FILTER (key = {probe.twin}) AS twin FROM est GROUP BY ALL"
    return [*_est_sql(probe), ("med", med), ("rounds", "SELECT tail_id, CASE WHEN abs(own) > abs(twin) THEN true WHEN abs(own) < abs(twin) THEN false END AS reported FROM med")]


_SIGNED = "SELECT tail_id, CASE WHEN reported THEN 1 WHEN NOT reported THEN -1 ELSE 0 END AS sign FROM rounds"
_MISSED = "SELECT tail_id, CASE WHEN NOT reported THEN 1 ELSE 0 END AS sign FROM rounds"


def special_keys(probe: A.Probe) -> list[int]:
    return [probe.designated, probe.twin, probe.control]


def _collected(spark: SparkSession, sf_dir: str, how: str = "signed") -> tuple[DataFrame, DataFrame, DataFrame]:
    """(tails, estimates of the special keys, signs) of the median attack."""
    tails = _tails(spark, sf_dir)
    est = A.probe_estimates(tails, PROBE, special_keys(PROBE))
    return tails, est, A.collect(A.median_rounds(est, PROBE), how)


@query(V.sql_tails(M_KEYS, TAILS))
def attack_tails(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _tails(spark, sf_dir)


@query(T.with_(*_rounds_sql(PROBE), then=_SIGNED))
def attack_median_rounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All rounds of the median attack in one batch: which tails, or negations of them, are collected."""
    return _collected(spark, sf_dir)[2]


@query(T.with_(*_rounds_sql(PROBE), then=_MISSED))
def attack_missed_rounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _collected(spark, sf_dir, "missed")[2]


@query(T.with_(*_est_sql(PROBE), ("med", f"SELECT tail_id, median(special + noise) AS own FROM est WHERE key = {PROBE.designated} GROUP BY ALL"), then=f"SELECT tail_id, CASE WHEN own > {PROBE.border} THEN 1 WHEN own < {PROBE.border} THEN -1 ELSE 0 END AS sign FROM med"))
def attack_values(spark: SparkSession, sf_dir: str) -> DataFrame:
    est = A.probe_estimates(_tails(spark, sf_dir), PROBE, special_keys(PROBE))
    return A.collect(A.value_rounds(est, PROBE), "signed")


_AGREE = f"SELECT tail_id, count(*) FILTER ({LONE.border} + noise > 0) / {float(ATTACKED.rows)} >= {TAU} AS plus, count(*) FILTER ({LONE.border} - noise > 0) / {float(ATTACKED.rows)} >= {TAU} AS minus FROM est WHERE key = {LONE.designated} GROUP BY ALL"


@query(T.with_(*_est_sql(LONE), ("said", _AGREE), then="SELECT tail_id, plus, minus, CASE WHEN plus AND NOT minus THEN 1 WHEN minus AND NOT plus THEN -1 ELSE 0 END AS sign FROM said"))
def attack_agreement_rounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    est = A.probe_estimates(_tails(spark, sf_dir), LONE, special_keys(LONE))
    return A.agreement_rounds(est, LONE, TAU)


@query(T.with_(*_est_sql(LONE), ("said", _AGREE), then="SELECT count(*) AS rounds, CAST(count(*) FILTER (plus <> minus) AS BIGINT) AS collected, round(count(*) FILTER (plus <> minus) / count(*), 6) AS rate FROM said"))
def collection_rate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return M.collection_rate(attack_agreement_rounds(spark, sf_dir)).withColumn("rate", F.round("rate", 6))


@query()
def attack_robust(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The robust report under repeated asks: signs learned per tail, queries spent, and whether they are right."""
    est = A.probe_estimates(_tails(spark, sf_dir), LONE, special_keys(LONE))
    gate = Gate(GATE.eps, GATE.delta, None, 77, "scaled", 4 * GATE.factor)
    noise = lambda tail, side, j: gate.noise_value(side, AT_LEAST, tail, j)
    learned = A.robust_rounds(est, LONE, ATTACKED.rows * TAU, noise, ATTACKED.rows)
    rows = spark.createDataFrame(learned, "tail_id bigint, sign int, queries int")
    bias = est.where(F.col("key") == LONE.designated).groupBy("tail_id").agg(F.sum(F.signum("noise")).alias("bias"))
    return rows.join(bias, "tail_id").select("tail_id", "sign", "queries", (F.col("sign") * F.col("bias") >= 0).alias("right"))


# -- bias-to-noise --------------------------------------------------------------------------------
_CURVE = [
    *_rounds_sql(PROBE), ("signs", f"SELECT *, CAST(row_number() OVER (ORDER BY tail_id) AS INTEGER) AS round FROM ({_SIGNED}) WHERE sign <> 0"),
    ("moved", "SELECT s.round, e.key, e.row, sum(s.sign * e.noise) OVER (PARTITION BY e.key, e.row ORDER BY s.round) AS bias FROM est e JOIN signs s ON e.tail_id = s.tail_id"),
    ("energy", "SELECT round, sum(e) OVER (ORDER BY round) AS norm2 FROM (SELECT s.round, sum(t.value * t.value) AS e FROM tails t JOIN signs s ON t.tail_id = s.tail_id GROUP BY ALL)"),
    ("curve", f"SELECT m.round, m.key, median(CAST(m.bias AS BIGINT)) / sqrt(any_value(n.norm2) / {ATTACKED.width}) AS bnr FROM moved m JOIN energy n ON m.round = n.round WHERE m.key IN ({PROBE.designated}, {PROBE.twin}, {PROBE.control}) GROUP BY ALL"),
]


def _curve(spark: SparkSession, sf_dir: str) -> DataFrame:
    tails, est, signs = _collected(spark, sf_dir)
    return A.bnr_curve(est, signs, tails, PROBE)


@query(T.with_(*_CURVE, then="SELECT round, key, round(bnr, 6) AS bnr FROM curve"))
def bnr_curve(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bias-to-noise ratio of the two special keys and a control key after every collected tail."""
    return _curve(spark, sf_dir).withColumn("bnr", F.round("bnr", 6))


_TARGETS = (0.25, 0.5, 0.75, 1.0)


@query(T.with_(*_CURVE, then=f"SELECT CAST(1 AS INTEGER) AS seed, CAST(t AS DOUBLE) AS target, min(round) AS rounds FROM curve, (SELECT unnest({list(_TARGETS)}::DOUBLE[]) AS t) WHERE key = {PROBE.designated} AND bnr >= t GROUP BY ALL"))
def rounds_to_bnr(spark: SparkSession, sf_dir: str) -> DataFrame:
    own = _curve(spark, sf_dir).where(F.col("key") == PROBE.designated).withColumn("seed", F.lit(1))
    return M.rounds_to(own, list(_TARGETS))


def play_field(spark: SparkSession, sf_dir: str, contenders: list[R.Contender], m: int, count: int, kind: str = "gaussian", seed: int = 5, roles: tuple[int, ...] = (1, -1)) -> tuple[DataFrame, DataFrame]:
    """The tails, and what they add at the special keys of every contender: one plan for all of them."""
    tails = V.tails(spark, sf_dir, m, count, seed, kind)
    held = R.spots(spark, contenders, FIRST, (1000 if kind == "gaussian" else 1) * sqrt(m)).where(F.col("role").isin(*roles))
    size = len(contenders) * 3 * max(int(c.layout.per_key * 2) for c in contenders)
    return tails, R.spot_noise(tails, held, size)


def contenders(rows: tuple[int, ...], seeds: int, width: int, k_out: int, first_seed: int) -> list[R.Contender]:
    """Row-hashed sketches of each number of rows, ``seeds`` of each; the number tells rows and seed."""
    return [R.Contender(r * 100 + s, RowHashed(r, width, first_seed + 100 * r + s, 4), k_out) for r in rows for s in range(seeds)]


def _rows_of() -> Column:
    return F.floor(F.col("sketch") / 100).cast("int")


def median_curves(spark: SparkSession, sf_dir: str, field: list[R.Contender], m: int, count: int, how: str = "signed", kind: str = "gaussian", control: bool = False) -> DataFrame:
    """(sketch, role, round, bnr) of the median attack on every contender."""
    tails, noise = play_field(spark, sf_dir, field, m, count, kind, roles=(1, -1, 0) if control else (1, -1))
    noise = materialise(noise, "noise")
    return R.curves(noise, R.median_signs(noise, how), tails)


def _reached(curves: DataFrame, targets: list[float]) -> DataFrame:
    """(rows, seed, target, rounds): rounds after which the mean of the two special keys reaches each target."""
    both = curves.groupBy("sketch", "round").agg(F.avg(F.col("role") * F.col("bnr")).alias("bnr"))
    return M.rounds_to(both.withColumnRenamed("sketch", "seed"), targets).withColumn("rows", F.floor(F.col("seed") / 100).cast("int"))


@query()
def bnr_band(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean, least and most of the ratio over ten initializations after every round, for both special keys and a control key."""
    curves = median_curves(spark, sf_dir, contenders((25,), 10, 10, 3, 3100), M_KEYS, TAILS, control=True)
    return M.band(curves, ["round", "role"], "bnr")


@query()
def bnr_band_signs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same with tails of +1 and -1, whose keys are many to a bucket, so that ties are rare."""
    curves = median_curves(spark, sf_dir, contenders((25,), 10, 10, 3, 3200), 600, TAILS, kind="sign", control=True)
    return M.band(curves, ["round", "role"], "bnr")


@query()
def missed_band(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The form that collects only the tails on which the designated key is missed, over ten initializations."""
    curves = median_curves(spark, sf_dir, contenders((25,), 10, 10, 3, 3300), M_KEYS, 2 * TAILS, how="missed")
    return M.band(curves, ["round", "role"], "bnr")


def _rounds_fit(spark: SparkSession, sf_dir: str) -> DataFrame:
    one = _reached(median_curves(spark, sf_dir, contenders((9, 17, 25, 49), 20, 10, 3, 4000), M_KEYS, 700), [1.0])
    four = _reached(median_curves(spark, sf_dir, contenders((9, 17), 5, 10, 3, 5000), M_KEYS, 2_500), [4.0])
    return materialise(one.unionAll(four), "reached")


@query()
def rounds_reached(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rounds to a ratio of 1 (20 runs a size) and 4 (5 runs) by rows of the sketch: mean, least, most, runs that came there, factor."""
    reached = _rounds_fit(spark, sf_dir)
    factor = F.avg(F.col("rounds") / (F.col("target") * F.col("target") * F.col("rows")))
    return reached.groupBy("target", "rows").agg(F.avg("rounds").alias("mean"), F.min("rounds").alias("least"), F.max("rounds").alias("most"), F.count("*").alias("runs"), factor.alias("factor"))


@query()
def rounds_fit(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Factor and log-log slope of the measured rounds against rows, by target ratio: about 5 and 1 are published."""
    return M.fit_rounds(_rounds_fit(spark, sf_dir))


@query()
def width_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rounds to a ratio of 1 for widths 30 to 300 at 100 rows, a third of the width very heavy keys; two runs a width."""
    out = None
    for width in (30, 100, 300):
        field = [R.Contender(s, RowHashed(100, width, 6000 + width + s, 4), width // 3) for s in range(2)]
        part = _reached(median_curves(spark, sf_dir, field, 5 * width, 900), [1.0])
        part = part.agg(F.lit(width).alias("width"), F.lit(width // 3).alias("heavy"), F.avg("rounds").alias("mean"), F.count("*").alias("runs"), (F.avg("rounds") / 100).alias("factor"))
        out = part if out is None else out.unionAll(part)
    return out


@query()
def heavy_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rounds to a ratio of 1 for 2, 5 and 10 places in the report at width 30 and 25 rows; five runs each."""
    field = [R.Contender(100 * k + s, RowHashed(25, 30, 7000 + 10 * k + s, 4), k) for k in (2, 5, 10) for s in range(5)]
    reached = _reached(median_curves(spark, sf_dir, field, 150, 600), [1.0])
    return reached.groupBy(F.col("rows").alias("heavy")).agg(F.avg("rounds").alias("mean"), F.min("rounds").alias("least"), F.max("rounds").alias("most"), F.count("*").alias("runs"), (F.avg("rounds") / 25).alias("factor"))


# -- the game -------------------------------------------------------------------------------------
GAME_ROWS, GAME_SEEDS, GAME_WIDTH = (17, 33, 65), 5, 16
#: The designated key's weight in deviations: reported about half the time, and heavy by its true agreement.
BORDERLINE, HEAVY = 1.31, 2.6


def _game_gate(rows: int, noise: bool, limited: bool) -> Gate:
    limit = max(8, rows * rows // 8)
    return Gate(1 / sqrt(limit), 1e-9, limit if limited else None, 808, "scaled" if noise else "none", 0.01 * rows / (10 * gate_delta(1 / sqrt(limit), 1e-9)))


def game_rules(rows: int) -> list[R.Rule]:
    """The plain rule, the gate whole, its parts alone, and the gate under repeated asks."""
    return [
        R.Rule("plain", None), R.Rule("gate", _game_gate(rows, True, True)), R.Rule("noise only", _game_gate(rows, True, False)), R.Rule("limit only", _game_gate(rows, False, True)),
        R.Rule("gate, repeated", _game_gate(rows, True, True), 5), R.Rule("noise only, repeated", _game_gate(rows, True, False), 5),
    ]


def games(spark: SparkSession, sf_dir: str, count: int = 500) -> DataFrame:
    """The adaptive game on independent buckets: every size and seed against every rule, to the first wrong report."""
    out = None
    for rows in GAME_ROWS:
        field = [R.Contender(rows * 100 + s, IndependentBuckets(rows * GAME_WIDTH, GAME_WIDTH, 8000 + 10 * rows + s), 1, BORDERLINE) for s in range(GAME_SEEDS)]
        tails, noise = play_field(spark, sf_dir, field, 5 * GAME_WIDTH, count, roles=(1,))
        part = R.play_rules(noise, tails, game_rules(rows), MID, HEAVY, 1 / 3)
        out = part if out is None else out.unionAll(part)
    return out


@query()
def survival_by_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Queries to the first wrong report, by rule and expected buckets of a key; runs that were wrong, exhausted, or neither."""
    played = games(spark, sf_dir).withColumn("rows", _rows_of())
    wrong, exhausted = F.col("wrong_at").isNotNull(), F.col("wrong_at").isNull() & F.col("exhausted").isNotNull()
    count = lambda c: F.sum(F.when(c, 1).otherwise(0))
    return played.groupBy("rule", "rows").agg(F.avg("queries").alias("queries"), F.avg("collected").alias("collected"), F.avg("bnr").alias("bnr"), count(wrong).alias("wrong"), count(exhausted).alias("exhausted"), count(~wrong & ~exhausted).alias("survived"))


@query()
def minimal_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The fewest buckets a key needs, of those tried, to answer a number of attacking queries rightly on average, by rule."""
    played = games(spark, sf_dir).withColumn("rows", _rows_of()).groupBy("rule", "rows").agg(F.avg("queries").alias("queries"))
    wanted = F.explode(F.array(*map(F.lit, (25, 50, 100, 200, 400)))).alias("wanted")
    return played.select("rule", "rows", "queries", wanted).groupBy("rule", "wanted").agg(F.min(F.when(F.col("queries") >= F.col("wanted"), F.col("rows"))).alias("rows"))


@query()
def margin_defeats_attack(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The attack on the plain rule with the designated key at the border, far above it and far below: tails collected and final ratio."""
    weights = {0: 0.2, 1: BORDERLINE, 2: 6.0}
    field = [R.Contender(100 * k + s, RowHashed(33, GAME_WIDTH, 8600 + s, 4), 1, w) for k, w in weights.items() for s in range(5)]
    tails, noise = play_field(spark, sf_dir, field, 5 * GAME_WIDTH, 300, roles=(1,))
    noise = materialise(noise, "noise")
    signs = R.agreement_signs(noise, MID)
    rates = signs.groupBy("sketch").agg(F.avg(F.abs("sign")).alias("rate"))
    last = R.curves(noise, signs, tails).groupBy("sketch").agg(F.max_by("bnr", "round").alias("bnr"))
    named = F.element_at(F.create_map(*[F.lit(x) for k, w in weights.items() for x in (k, w)]), F.floor(F.col("sketch") / 100).cast("int"))
    return rates.join(last, "sketch", "left").groupBy(named.alias("weight")).agg(F.avg("rate").alias("rate"), F.avg(F.coalesce("bnr", F.lit(0.0))).alias("bnr"))


@query()
def streaming_attack(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The attack through a continuous report: tails and their negations as the states of one stream; what counts is the flip number."""
    field = contenders((33,), 5, GAME_WIDTH, 1, 8700)
    tails, noise = play_field(spark, sf_dir, [R.Contender(c.sketch, c.layout, 1, BORDERLINE) for c in field], 5 * GAME_WIDTH, 300, roles=(1,))
    side = F.explode(F.array(F.lit(0), F.lit(1))).alias("side")
    share = lambda sign: F.avg(F.when(F.col("border") + sign * F.col("noise") > 0, 1.0).otherwise(0.0))
    both = noise.groupBy("sketch", "tail_id").agg(share(1).alias("up"), share(-1).alias("down")).select("*", side)
    states = both.select((2 * F.col("tail_id") + F.col("side")).alias("query_id"), F.col("sketch").cast("bigint").alias("key"), F.when(F.col("side") == 0, F.col("up")).otherwise(F.col("down")).alias("p_plus"), F.lit(0.0).alias("p_minus"))
    states = materialise(states, "states")
    changes = M.churn(E.hysteresis_report(states, *LEVELS))
    steps = states.groupBy("key").agg(F.count("*").alias("states"))
    return steps.join(M.flips(states, *LEVELS), "key", "left").join(changes, "key", "left").select(F.col("key").alias("sketch"), "states", (F.col("states") * 5 * GAME_WIDTH).alias("updates"), "flips", "changes")


def _needed(spark: SparkSession, sf_dir: str) -> list[float]:
    """For each tail the weight from which the designated key of one sketch is reported beside it."""
    field = [R.Contender(0, RowHashed(33, GAME_WIDTH, 8800, 4), 1, BORDERLINE)]
    _, noise = play_field(spark, sf_dir, field, 5 * GAME_WIDTH, 300, roles=(1,))
    ordered = F.sort_array(F.collect_list(-F.col("noise")))
    return [float(r[0]) for r in noise.groupBy("tail_id").agg(F.element_at(ordered, int(MID * 33) + 1).alias("w")).orderBy("tail_id").select("w").collect()]


@query()
def borderline_weight(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The weight at which the key is reported about half the time, by bisection, and the rates around it."""
    needed = _needed(spark, sf_dir)
    rate = lambda w: sum(w > n for n in needed) / len(needed)
    deviation = 1000 * sqrt(5.0)
    found = A.calibrate_weight(rate, 0, int(6 * deviation))
    return spark.createDataFrame([(name, int(w), w / deviation, rate(w)) for name, w in (("half of it", found / 2), ("found", found), ("twice", 2 * found))], "weight_is string, weight bigint, deviations double, rate double")


@query()
def attack_unknown(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The search for the border without the parameters of sketch and rule: weights tried, reports, queries so far."""
    needed = _needed(spark, sf_dir)
    steps = A.search_border(lambda w, j: w > needed[j % len(needed)])
    return spark.createDataFrame([(i, w, hits, 9 * (i + 1)) for i, (w, hits) in enumerate(steps)], "step int, weight bigint, reports int, queries int")


# -- final queries --------------------------------------------------------------------------------
_FINAL = [
    *_rounds_sql(PROBE), ("signs", _SIGNED), ("tail", "SELECT t.key, s.sign * t.value AS value FROM tails t JOIN signs s ON t.tail_id = s.tail_id WHERE s.sign <> 0"),
    ("norm", f"SELECT CAST(floor(sqrt(sum(value * value) / {ATTACKED.width})) AS BIGINT) AS w FROM tail"),
    ("vec", f"SELECT 0 AS query_id, key, -value AS value FROM tail UNION ALL SELECT 0, {PROBE.designated}, w FROM norm UNION ALL SELECT 1, key, value FROM tail"),
    ("asked", f"SELECT q AS query_id, CAST({PROBE.designated} AS BIGINT) AS key FROM (SELECT unnest([0, 1]) AS q)"),
    ("cells", T.cells("vec", ATTACKED)), ("fest", T.estimates("asked", "cells", ATTACKED)),
]


@query(T.with_(*_FINAL, then="SELECT query_id, key, (SELECT w FROM norm) AS deviation, CAST(median(est) AS DOUBLE) AS v_hat FROM fest GROUP BY ALL"))
def attack_median_final(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The last queries: a key of one deviation hidden by the attack tail (0), and the tail alone (1)."""
    tails, _, signs = _collected(spark, sf_dir)
    tail = A.attack_tail(tails, signs)
    deviation = tail.agg(F.floor(F.sqrt(F.sum(F.col("value") * F.col("value")) / ATTACKED.width))).first()[0]
    masked = A.final_vector(tail, PROBE, "mask", int(deviation))
    phantom = A.final_vector(tail, PROBE, "phantom", 0).withColumn("query_id", F.lit(1).cast("bigint"))
    asked = spark.range(2).select(F.col("id").alias("query_id"), F.lit(PROBE.designated).cast("bigint").alias("key"))
    est = S.estimates(asked, S.build(masked.unionAll(phantom), ATTACKED, sum_keys=False), ATTACKED, 2)
    return E.median_estimate(est).select("query_id", "key", F.lit(int(deviation)).cast("bigint").alias("deviation"), "v_hat")


@query()
def attack_comparison(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bias-to-noise ratio that the tails collected from each rule give, and the queries spent."""
    tails = _tails(spark, sf_dir)
    rows = []
    for name, probe, collected, queries in (
        ("median", PROBE, attack_median_rounds(spark, sf_dir), 1),
        ("agreement", LONE, attack_agreement_rounds(spark, sf_dir).select("tail_id", "sign"), 2),
        ("robust_once", LONE, _robust_signs(spark, sf_dir, 1), 2),
        ("robust_repeated", LONE, attack_robust(spark, sf_dir).select("tail_id", "sign"), 2 * ATTACKED.rows),
    ):
        est = A.probe_estimates(tails, probe, [probe.designated])
        sums = est.join(collected, "tail_id").groupBy("row").agg(F.sum(F.col("sign") * F.col("noise")).alias("x"))
        energy = tails.join(collected.where("sign <> 0"), "tail_id").agg(F.sum(F.col("value") * F.col("value")).alias("e"))
        one = sums.agg(F.median("x").alias("bias")).crossJoin(energy)
        rows.append(one.select(F.lit(name).alias("rule"), F.lit(queries * TAILS).alias("queries"), (F.col("bias") / F.sqrt(F.col("e") / ATTACKED.width)).alias("bnr")))
    out = rows[0]
    for more in rows[1:]:
        out = out.unionAll(more)
    return out


def _robust_signs(spark: SparkSession, sf_dir: str, repeats: int) -> DataFrame:
    est = A.probe_estimates(_tails(spark, sf_dir), LONE, special_keys(LONE))
    gate = Gate(GATE.eps, GATE.delta, None, 77, "scaled", 4 * GATE.factor)
    learned = A.robust_rounds(est, LONE, ATTACKED.rows * TAU, lambda tail, side, j: gate.noise_value(side, AT_LEAST, tail, j), repeats)
    return spark.createDataFrame([r[:2] for r in learned], "tail_id bigint, sign int")


@query(
    f"SELECT CAST(row_number() OVER (ORDER BY tail_id, phase, key) - 1 AS INTEGER) AS seq, key, value FROM (SELECT tail_id, 0 AS phase, key, value FROM ({V.sql_tails(M_KEYS, 20)}) UNION ALL SELECT tail_id, 2, key, -value FROM ({V.sql_tails(M_KEYS, 20)}) UNION ALL SELECT DISTINCT tail_id, 1, CAST({FIRST} AS BIGINT), CAST(1 AS BIGINT) FROM ({V.sql_tails(M_KEYS, 20)}))"
)
def updates_of_attack(spark: SparkSession, sf_dir: str) -> DataFrame:
    return A.as_updates(V.tails(spark, sf_dir, M_KEYS, 20), PROBE)


@query(T.with_(("vec", T.vector("embedding_rows")), then="SELECT e.label, v.key, CAST(sum(v.value) AS BIGINT) AS value FROM vec v JOIN embeddings e ON v.query_id = e.vec_id GROUP BY ALL"))
def feedback_by_label(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Natural feedback: inputs that share a label, summed."""
    labels = V.read_table(spark, sf_dir, "embeddings", ["vec_id", "label"]).select(F.col("vec_id").alias("query_id"), "label")
    return A.feedback_tail(V.embedding_rows(spark, sf_dir), labels)


# -- budgets and quality --------------------------------------------------------------------------
_BEST = "greatest(p_plus, p_minus)"


@query(
    T.with_(
        *HOURLY, ("sus", f"SELECT key, count(*) AS n FROM agreed WHERE {_BEST} >= {LEVELS[0]!r} GROUP BY ALL"), ("tot", f"SELECT CAST(coalesce(max(n), 0) AS DOUBLE) AS most_of_a_key, coalesce(sum(n), 0) / {C_A * USERS.width} AS spread_total FROM sus"),
        then="SELECT most_of_a_key, round(spread_total, 6) AS spread_total, round(least(most_of_a_key, spread_total), 6) AS budget_min, round(greatest(most_of_a_key, spread_total), 6) AS budget_safe FROM tot",
    )
)
def budget_threshold(spark: SparkSession, sf_dir: str) -> DataFrame:
    suspects = hourly_agreement(spark, sf_dir)[1].where(F.greatest("p_plus", "p_minus") >= LEVELS[0]).select("query_id", "key")
    out = M.budget_threshold(suspects, USERS.width, C_A)
    return out.select("most_of_a_key", *[F.round(c, 6).alias(c) for c in ("spread_total", "budget_min", "budget_safe")])


_GAP = LEVELS[1] - LEVELS[0]


@query(
    T.with_(
        *HOURLY,
        ("said", f"SELECT query_id, key, CASE WHEN {_BEST} <= {LEVELS[0] + 2 * _GAP / 5!r} THEN 0 WHEN {_BEST} >= {LEVELS[1] - 2 * _GAP / 5!r} THEN 1 END AS signal FROM agreed"),
        ("alt", "SELECT key, signal, coalesce(lag(signal) OVER (PARTITION BY key ORDER BY query_id), 0) AS before FROM said WHERE signal IS NOT NULL"),
        then="SELECT key, CAST(count(*) FILTER (signal <> before) AS BIGINT) AS flips FROM alt GROUP BY ALL",
    )
)
def budget_flips(spark: SparkSession, sf_dir: str) -> DataFrame:
    return M.flips(hourly_agreement(spark, sf_dir)[1], *LEVELS)


_COST = 40


@query(
    T.with_(
        *HOURLY, ("cost", f"SELECT key, count(*) FILTER ({_BEST} >= {LEVELS[0]!r}) AS cost FROM agreed GROUP BY ALL"), ("allkeys", "SELECT key FROM cost"), ("sp", USERS.sql("allkeys")),
        ("tot", "SELECT sp.row, sp.bucket, sum(c.cost) AS total FROM sp JOIN cost c ON sp.key = c.key GROUP BY ALL"),
        then=f"SELECT sp.key, count(*) AS part, CAST(count(*) FILTER (t.total <= {_COST}) AS BIGINT) AS useful, round(count(*) FILTER (t.total <= {_COST}) / count(*), 6) AS share FROM sp JOIN tot t ON sp.row = t.row AND sp.bucket = t.bucket GROUP BY ALL",
    )
)
def useful_buckets(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = hourly_agreement(spark, sf_dir)[1]
    cost = rows.groupBy("key").agg(F.count(F.when(F.greatest("p_plus", "p_minus") >= LEVELS[0], 1)).alias("cost"))
    return M.useful_buckets(USERS.participation(cost.select("key")), cost, _COST).withColumn("share", F.round("share", 6))


@query(
    T.with_(
        *agreed_sql(T.vector("embedding_rows"), USERS, 33), ("report", T.threshold("agreed", MID)), ("h", T.heavy("vec", 10)),
        then="SELECT q.query_id, coalesce(r.n, 0) AS reported, coalesce(t.n, 0) AS heavy, coalesce(f.n, 0) AS found, round(CASE WHEN t.n > 0 THEN coalesce(f.n, 0) / t.n ELSE 1 END, 6) AS recall, round(CASE WHEN r.n > 0 THEN coalesce(f.n, 0) / r.n ELSE 1 END, 6) AS precision FROM (SELECT DISTINCT query_id FROM vec) q LEFT JOIN (SELECT query_id, count(*) AS n FROM report GROUP BY ALL) r USING (query_id) LEFT JOIN (SELECT query_id, count(*) AS n FROM h GROUP BY ALL) t USING (query_id) LEFT JOIN (SELECT r.query_id, count(*) AS n FROM report r JOIN h ON r.query_id = h.query_id AND r.key = h.key GROUP BY ALL) f USING (query_id)",
    )
)
def report_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    vec = V.embedding_rows(spark, sf_dir)
    est = S.own_estimates(vec, USERS)
    report = E.threshold_report(E.agreement(E.votes(est), USERS.per_key), MID)
    out = M.report_quality(report, E.exact_heavy(vec, 10, summed=True), vec)
    return out.withColumns({c: F.round(c, 6) for c in ("recall", "precision")})


@query(
    T.with_(
        *agreed_sql(T.vector("embedding_rows"), USERS, 33)[:3], ("med", T.medians("est")), ("t", T.tail2("vec", 10)),
        ("worst", "SELECT v.query_id, max((m.v_hat - v.value) * (m.v_hat - v.value)) AS worst2 FROM med m JOIN vec v ON m.query_id = v.query_id AND m.key = v.key GROUP BY ALL"),
        then="SELECT w.query_id, w.worst2, round(w.worst2 * 10 / t.tail2, 6) AS alpha FROM worst w JOIN t ON w.query_id = t.query_id",
    )
)
def linf_l2_error(spark: SparkSession, sf_dir: str) -> DataFrame:
    vec = V.embedding_rows(spark, sf_dir)
    med = E.median_estimate(S.own_estimates(vec, USERS))
    return M.linf_l2_error(med, vec, E.tail_norm2(vec, 10, summed=True), 10).withColumn("alpha", F.round("alpha", 6))


@query(
    T.with_(
        *agreed_sql(T.vector("skewed_parts"), PARTS, 129)[:3], ("med", T.medians("est")), ("top", T.top("med", 12)), ("t", T.tail2("vec", 4)),
        then="SELECT p.query_id, count(*) AS \"values\", CAST(count(*) FILTER ((p.v_hat - coalesce(v.value, 0)) * (p.v_hat - coalesce(v.value, 0)) * 4 <= t.tail2) AS BIGINT) AS within FROM top p LEFT JOIN vec v ON p.query_id = v.query_id AND p.key = v.key JOIN t ON p.query_id = t.query_id GROUP BY ALL",
    )
)
def value_correctness(spark: SparkSession, sf_dir: str) -> DataFrame:
    vec = V.skewed_parts(spark, sf_dir)
    return M.value_correct(E.median_report(estimated(vec, PARTS), 12), vec, E.tail_norm2(vec, 4, summed=True, queries=1), 1.0, 4)


@query()
def agreement_error(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Largest deviation of measured agreement from the exact one for several numbers of rows: falls as their root."""
    vec = V.html_tags(spark, sf_dir)
    spread = int(vec.agg(F.sum(F.abs("value"))).first()[0] or 1)
    truth = E.true_agreement(vec, keys(vec), SMALL.width, spread)
    out = None
    for rows in (25, 101, 401):
        part = M.agreement_error(agreed(vec, RowHashed(rows, SMALL.width, 70 + rows, 4)), truth).withColumn("rows", F.lit(rows))
        out = part if out is None else out.unionAll(part)
    return out


@query()
def generalization_gaps(spark: SparkSession, sf_dir: str) -> DataFrame:
    vec = V.html_tags(spark, sf_dir)
    spread = int(vec.agg(F.sum(F.abs("value"))).first()[0] or 1)
    layout = RowHashed(201, SMALL.width, 81, 4)
    truth = E.true_agreement(vec, keys(vec), layout.width, spread)
    return M.generalization_gap(E.votes(estimated(vec, layout)), truth, layout.size, layout.width)


@query(T.with_(*agreed_sql(T.vector("embedding_rows"), USERS, 33), then=f"SELECT CASE WHEN {_BEST} <= 0.7 THEN 'low' ELSE 'high' END AS side, count(*) AS pairs FROM agreed WHERE {_BEST} <= 0.7 OR {_BEST} >= 0.99 GROUP BY ALL"))
def pairs_with_margin(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Inputs that keep away from the boundary, which defeats the attacks."""
    vec = V.embedding_rows(spark, sf_dir)
    est = S.own_estimates(vec, USERS)
    far = A.with_margin(E.agreement(E.votes(est), USERS.per_key), 0.7, 0.99)
    return far.groupBy(F.when(F.greatest("p_plus", "p_minus") <= 0.7, "low").otherwise("high").alias("side")).agg(F.count("*").alias("pairs"))


_OBLIVIOUS = {rows: RowHashed(rows, 64, 90 + rows) for rows in (17, 65, 129)}


@query(
    T.with_(
        ("vec", T.vector("skewed_parts")), ("h", T.heavy("vec", 4)),
        *[step for rows, layout in _OBLIVIOUS.items() for step in (
            (f"cells{rows}", T.cells("vec", layout)), (f"est{rows}", T.estimates("vec", f"cells{rows}", layout)), (f"votes{rows}", T.votes(f"est{rows}")), (f"agreed{rows}", T.agreement(f"votes{rows}", rows)),
            (f"med{rows}", T.medians(f"est{rows}")), (f"median{rows}", f"SELECT query_id, key FROM ({T.top(f'med{rows}', 8)})"), (f"agreement{rows}", f"SELECT query_id, key FROM ({T.threshold(f'agreed{rows}', MID)})"),
        )],
        then=" UNION ALL ".join(
            f"SELECT {rows} AS rows, '{name}' AS report, r.n AS reported, h.n AS heavy, CASE WHEN h.n > 0 THEN f.n / h.n ELSE 1.0 END AS recall, CASE WHEN r.n > 0 THEN f.n / r.n ELSE 1.0 END AS precision FROM (SELECT count(*) AS n FROM {name}{rows}) r, (SELECT count(*) AS n FROM h) h, (SELECT count(*) AS n FROM {name}{rows} x JOIN h ON x.key = h.key) f"
            for rows in _OBLIVIOUS for name in ("median", "agreement")
        ),
    )
)
def oblivious_accuracy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recall and size of the median and the sign-agreement report by sketch rows, inputs fixed in advance."""
    vec = V.skewed_parts(spark, sf_dir)
    heavy = E.exact_heavy(vec, 4, summed=True, queries=1)
    out = None
    for rows, layout in _OBLIVIOUS.items():
        est = estimated(vec, layout)
        for name, report in (("median", E.median_report(est, 8)), ("agreement", E.threshold_report(E.agreement(E.votes(est), rows), MID))):
            part = M.report_quality(report.select("query_id", "key"), heavy, vec).select(F.lit(rows).alias("rows"), F.lit(name).alias("report"), "reported", "heavy", "recall", "precision")
            out = part if out is None else out.unionAll(part)
    return out


_POWER = RowHashed(65, 10, 95, 4)
_DEVIATIONS = (0.0, 0.5, 1.0, 2.0, 3.0, 5.0)
_PLANTED = [(c, int(c * 1000 * sqrt(M_KEYS / _POWER.width))) for c in _DEVIATIONS]


@query(
    T.with_(
        ("tails", V.sql_tails(M_KEYS, TAILS)), ("w", "SELECT * FROM (VALUES " + ", ".join(f"({c}::DOUBLE, {w}::BIGINT)" for c, w in _PLANTED) + ") AS t(deviations, weight)"),
        ("tp", _POWER.sql("tails")), ("cells", "SELECT tail_id, row, bucket, CAST(sum(sign * value) AS BIGINT) AS c FROM tp GROUP BY ALL"),
        ("one", f"SELECT CAST({FIRST} AS BIGINT) AS key"), ("own", _POWER.sql("one")),
        ("est", "SELECT w.deviations, q.tail_id, o.row, w.weight + o.sign * coalesce(c.c, 0) AS est FROM w, (SELECT DISTINCT tail_id FROM tails) q, own o LEFT JOIN cells c ON c.tail_id = q.tail_id AND c.row = o.row AND c.bucket = o.bucket"),
        ("said", f"SELECT deviations, tail_id, count(*) FILTER (est > 0) / 65.0::DOUBLE >= {MID!r} OR count(*) FILTER (est < 0) / 65.0::DOUBLE >= {MID!r} AS reported FROM est GROUP BY ALL"),
        then="SELECT deviations, count(*) AS tails, CAST(count(*) FILTER (reported) AS BIGINT) AS reported FROM said GROUP BY ALL",
    )
)
def planted_power(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How often a planted key is reported, by its weight in deviations of the tail: one sketch of each tail, the key added by linearity."""
    tails = _tails(spark, sf_dir).withColumnRenamed("tail_id", "query_id")
    asked = tails.select("query_id").distinct().withColumn("key", F.lit(FIRST).cast("bigint"))
    est = S.estimates(asked, S.build(tails, _POWER, sum_keys=False), _POWER, TAILS)
    weights = F.explode(F.array(*[F.struct(F.lit(c).alias("deviations"), F.lit(w).cast("bigint").alias("weight")) for c, w in _PLANTED])).alias("w")
    planted = est.select("query_id", weights, "est").select("query_id", "w.deviations", (F.col("est") + F.col("w.weight")).alias("est"))
    share = lambda cond: F.avg(F.when(cond, 1.0).otherwise(0.0)) >= MID
    said = planted.groupBy("deviations", "query_id").agg((share(F.col("est") > 0) | share(F.col("est") < 0)).alias("reported"))
    return said.groupBy("deviations").agg(F.count("*").alias("tails"), F.sum(F.when(F.col("reported"), 1).otherwise(0)).alias("reported"))

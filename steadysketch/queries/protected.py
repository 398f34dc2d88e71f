"""The noisy gate, robust reports, weights, candidates and baselines."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import baselines as B
from ..operators import estimators as E
from ..operators import sketch as S
from ..operators.candidates import CandidateSketch
from ..operators.gate import AT_LEAST, AT_MOST, Gate
from ..operators import metrics as M
from ..operators import sizing as Z
from ..operators.layouts import IndependentBuckets, RowHashed, RowHashedCopies
from ..operators.robust import MINUS, PLUS, BudgetExhausted, ContinuousReporter, RobustReporter
from ..operators.sizing import size_baselines
from ..runtime import discard, materialise
from ..sources import vectors as V
from . import sqltext as T
from .base import GATE, INDEPENDENT, MID, PARTS, SKIPPING, USERS, query
from .sketches import HOURLY, estimated, keys

REPORT = "query_id bigint, key bigint, sign int, count int, weight bigint"


# -- gate -----------------------------------------------------------------------------------------
@query(
    f"SELECT key, round({T.noise(GATE, PLUS, AT_LEAST, '0', 'key')}, 6) AS at_least, round({T.noise(GATE, MINUS, AT_MOST, '0', 'key')}, 6) AS at_most FROM (SELECT CAST(o_orderkey AS BIGINT) AS key FROM orders)"
)
def gate_noise_sample(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The noise of both tests for every order key in the first query."""
    key = F.col("key")
    rows = V.read_table(spark, sf_dir, "orders", ["o_orderkey"]).select(F.col("o_orderkey").cast("bigint").alias("key"))
    return rows.select("key", F.round(GATE.noise_column(PLUS, AT_LEAST, F.lit(0), key), 6).alias("at_least"), F.round(GATE.noise_column(MINUS, AT_MOST, F.lit(0), key), 6).alias("at_most"))


@query()
def gate_pass_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Chance that a test passes by count, for the analysis' noise and the scaled one, and the tests of the parts at that count."""
    theory = Gate(0.1, 1e-9, 64)
    level = 129 * MID
    rows = [(n, GATE.pass_probability(n, level), theory.pass_probability(n, level)) for n in range(0, 130)]
    chances = spark.createDataFrame(rows, "count int, scaled double, theory double")
    counted = E.votes(estimated(V.skewed_parts(spark, sf_dir), PARTS))
    asked = counted.select(F.explode(F.array(F.col("pos").cast("int"), F.col("neg").cast("int"))).alias("count")).groupBy("count").agg(F.count("*").alias("tests"))
    return chances.join(asked, "count", "left").select("count", "scaled", "theory", F.coalesce("tests", F.lit(0)).alias("tests"))


def _asked_sql(gate: Gate, level: float, votes: str = "votes") -> str:
    plus = f"pos + {T.noise(gate, PLUS, AT_LEAST, 'query_id', 'key')} >= {level!r}"
    minus = f"neg + {T.noise(gate, MINUS, AT_LEAST, 'query_id', 'key')} >= {level!r}"
    return f"SELECT *, {plus} AS pos_pass, {minus} AS neg_pass FROM {votes}"


#: No bucket is retired within one query: the limit is far off, so the rule needs no order.
OPEN = Gate(GATE.eps, GATE.delta, 1_000, GATE.seed, "scaled", GATE.factor)
_LEVEL = 129 * MID
_PARTS = [("vec", T.vector("skewed_parts")), ("cells", T.cells("vec", PARTS)), ("est", T.estimates("vec", "cells", PARTS)), ("votes", T.votes("est")), ("asked", _asked_sql(OPEN, _LEVEL))]


def report_frame(spark: SparkSession, steps: dict[int, list[tuple]]) -> DataFrame:
    rows = [(q, *r) for q, found in steps.items() for r in found]
    return spark.createDataFrame(rows, REPORT)


@query(T.with_(*_PARTS, then="SELECT query_id, key, CASE WHEN pos_pass THEN 1 ELSE -1 END AS sign, CAST(CASE WHEN pos_pass THEN pos ELSE neg END AS INTEGER) AS count, 'scaled' AS noise_mode FROM asked WHERE pos_pass OR neg_pass"))
def robust_threshold_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The robust threshold report of one skewed vector."""
    reporter = RobustReporter(PARTS, OPEN)
    found = reporter.step(0, estimated(V.skewed_parts(spark, sf_dir), PARTS))
    return report_frame(spark, {0: found}).drop("weight").withColumn("noise_mode", F.lit(OPEN.noise))


@query(
    T.with_(
        *_PARTS,
        ("kept", "SELECT query_id, key, CASE WHEN pos_pass THEN 1 ELSE -1 END AS s FROM asked WHERE pos_pass OR neg_pass"),
        then="SELECT e.row, e.bucket, CAST(count(*) AS INTEGER) AS accesses FROM est e JOIN kept k ON e.query_id = k.query_id AND e.key = k.key WHERE e.est * k.s > 0 GROUP BY ALL",
    )
)
def gate_charges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Buckets charged by one robust report, and how often."""
    reporter = RobustReporter(PARTS, OPEN)
    reporter.step(0, estimated(V.skewed_parts(spark, sf_dir), PARTS))
    return reporter.state(spark).select("row", "bucket", "accesses")


_RETIRE = 8


@query()
def retired_buckets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Accesses of all hours through a gate that retires a bucket at its eighth, and which buckets are left."""
    reporter, _, est = _hourly(spark, sf_dir, Gate(GATE.eps, GATE.delta, _RETIRE, GATE.seed, "scaled", GATE.factor))
    reporter.run(est)
    return reporter.state(spark)


def _hourly(spark: SparkSession, sf_dir: str, gate: Gate, **settings) -> tuple[RobustReporter, DataFrame, DataFrame]:
    """A reporter, the vectors of all hours, and their estimates."""
    vec = V.hourly_users(spark, sf_dir)
    hours = vec.select("query_id").distinct().count()
    est = S.estimates(keys(vec), S.build(vec, USERS, sum_keys=False), USERS, hours)
    return RobustReporter(USERS, gate, **settings), vec, est


@query()
def health_enforced(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The hours through a small gate that stops once a third of a tested user's buckets are retired: how far it comes."""
    gate = Gate(GATE.eps, GATE.delta, 4, GATE.seed, "scaled", GATE.factor)
    reporter, _, est = _hourly(spark, sf_dir, gate, most_retired=1 / 3)
    try:
        reporter.run(est)
        why = "ended"
    except BudgetExhausted as stop:
        why = str(stop)
    return spark.createDataFrame([(why, reporter.accesses.asks, reporter.accesses.passes, len(reporter.accesses.retired))], "stopped string, asks int, passes int, retired int")


# -- independent buckets --------------------------------------------------------------------------
_OWN = [("vec", T.vector("skewed_parts")), ("cells", T.cells("vec", INDEPENDENT)), ("est", T.estimates("vec", "cells", INDEPENDENT)), ("votes", T.votes("est"))]
_OWN_LEVEL = INDEPENDENT.per_key * MID


@query(T.with_(*_OWN, ("asked", _asked_sql(OPEN, _OWN_LEVEL)), then="SELECT query_id, key, CASE WHEN pos_pass THEN 1 ELSE -1 END AS sign, CAST(CASE WHEN pos_pass THEN pos ELSE neg END AS INTEGER) AS count FROM asked WHERE pos_pass OR neg_pass"))
def robust_threshold_independent(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The robust threshold report on independent buckets, counts against the expected number of a key's buckets."""
    found = RobustReporter(INDEPENDENT, OPEN).step(0, estimated(V.skewed_parts(spark, sf_dir), INDEPENDENT))
    return report_frame(spark, {0: found}).drop("weight")


#: Two accesses: the buckets that two of the reported keys share retire within the query.
RETIRING = Gate(GATE.eps, GATE.delta, 2, GATE.seed, "scaled", GATE.factor)
_WALK = T.with_(
    *_OWN, ("asked", _asked_sql(RETIRING, _OWN_LEVEL)),
    ("cand", f"SELECT e.key, row_number() OVER (ORDER BY e.key) AS n, coalesce(list(e.bucket) FILTER (e.est > 0), []) AS up, coalesce(list(e.bucket) FILTER (e.est < 0), []) AS down, any_value({T.noise(RETIRING, PLUS, AT_LEAST, 'e.query_id', 'e.key')}) AS plus, any_value({T.noise(RETIRING, MINUS, AT_LEAST, 'e.query_id', 'e.key')}) AS minus FROM est e JOIN asked a ON a.key = e.key WHERE a.pos_pass OR a.neg_pass GROUP BY e.key"),
    then="",
).replace("WITH", "WITH RECURSIVE", 1) + f""", walk AS (
    SELECT CAST(0 AS BIGINT) AS n, CAST([] AS INTEGER[]) AS hits, CAST(NULL AS BIGINT) AS key, 0 AS sign, CAST(0 AS BIGINT) AS count
    UNION ALL
    SELECT n, CASE WHEN sign = 1 THEN list_concat(hits, up) WHEN sign = -1 THEN list_concat(hits, down) ELSE hits END, key, sign, CASE WHEN sign = 1 THEN len(up) WHEN sign = -1 THEN len(down) ELSE 0 END
    FROM (SELECT *, CASE WHEN len(up) + plus >= {_OWN_LEVEL!r} THEN 1 WHEN len(down) + minus >= {_OWN_LEVEL!r} THEN -1 ELSE 0 END AS sign
          FROM (SELECT c.n, c.key, w.hits, c.plus, c.minus, list_filter(c.up, lambda x: len(list_filter(w.hits, lambda y: y = x)) < {RETIRING.limit}) AS up, list_filter(c.down, lambda x: len(list_filter(w.hits, lambda y: y = x)) < {RETIRING.limit}) AS down
                FROM walk w JOIN cand c ON c.n = w.n + 1)))
    SELECT key, sign, CAST(count AS INTEGER) AS count, CAST((SELECT count(*) FROM (SELECT b FROM (SELECT unnest(hits) AS b) GROUP BY b HAVING count(*) >= {RETIRING.limit})) AS INTEGER) AS retired FROM walk WHERE sign <> 0"""  # fmt: skip


@query(_WALK)
def robust_retiring_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One robust report in which buckets retire while it is made: each key with its count over live buckets and the buckets retired by then."""
    reporter = RobustReporter(INDEPENDENT, RETIRING)
    rows = []
    for candidate in reporter.candidates(estimated(V.skewed_parts(spark, sf_dir), INDEPENDENT)):
        for key, sign, count, _ in reporter.replay(0, [candidate], reporter.level):
            rows.append((key, sign, count, len(reporter.accesses.retired)))
    return spark.createDataFrame(rows, "key bigint, sign int, count int, retired int")


@query()
def weight_scan_independent(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Weights on independent buckets through a gate whose limit is doubled for them, with the error promised."""
    vec = V.skewed_parts(spark, sf_dir)
    gate = Gate.for_reports(64, 2_000, 1_000, INDEPENDENT.width, weights=True, seed=GATE.seed, noise="scaled", factor=GATE.factor)
    reporter = RobustReporter(INDEPENDENT, gate, weights_up_to=weight_bound(vec))
    found = report_frame(spark, {0: reporter.step(0, estimated(vec, INDEPENDENT))})
    joined = found.join(vec, ["query_id", "key"]).join(E.tail_norm2(vec, 1, summed=True, queries=1), "query_id")
    near = F.sqrt(F.col("tail2"))
    return joined.select("query_id", "key", "weight", "value", near.alias("promised"), (F.abs(F.col("weight") - F.col("value")) <= near).alias("within"), F.lit(gate.limit).alias("limit"), F.lit(gate.eps).alias("eps"), F.lit(gate.delta).alias("delta"))


@query()
def robust_threshold_sequence(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Robust reports of all hours in turn through one gate whose buckets retire."""
    reporter, _, est = _hourly(spark, sf_dir, GATE)
    return report_frame(spark, reporter.run(est))


@query()
def bucket_health(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Share of each user's buckets that the reports of all hours have retired."""
    gate = Gate(GATE.eps, GATE.delta, 4, GATE.seed, "scaled", GATE.factor)
    reporter, vec, est = _hourly(spark, sf_dir, gate)
    reporter.run(est)
    return reporter.retired_share(vec)


def weight_bound(rows: DataFrame) -> int:
    """The sum of absolute values: no key's weight and no bucket's estimate is beyond it at any time."""
    return int(rows.agg(F.sum(F.abs("value"))).first()[0] or 0)


def _steps_of(rows: DataFrame, steps: int) -> DataFrame:
    """(step, key, value): (at, key, value) rows summed over steps of equal time."""
    first, last = rows.agg(F.min("at"), F.max("at")).first()
    if first is None:
        return rows.select(F.lit(0).cast("bigint").alias("step"), "key", "value")
    step_of = F.floor((F.col("at") - first) * steps / F.lit(last - first + 1)).cast("bigint")
    return rows.groupBy(step_of.alias("step"), "key").agg(F.sum("value").alias("value"))


def event_steps(spark: SparkSession, sf_dir: str, steps: int) -> DataFrame:
    """Values of users over time; four of them are planted heavy, at forty times their value."""
    events = V.read_table(spark, sf_dir, "events", ["ts", "user_id", "value"]).select(F.unix_timestamp("ts").alias("at"), F.col("user_id").alias("key"), V.cents("value").alias("value"))
    events = events.where("at is not null and key is not null and value is not null")
    return _steps_of(events.withColumn("value", F.col("value") * F.when(F.col("key") < 4, 40).otherwise(1)), steps)


def part_steps(spark: SparkSession, sf_dir: str, steps: int) -> DataFrame:
    """Quantities of the skewed part keys by date of shipping."""
    items = V.read_table(spark, sf_dir, "lineitem", ["l_shipdate", "l_partkey", "l_quantity"])
    rows = items.select(F.unix_date(F.to_date("l_shipdate")).cast("bigint").alias("at"), V.skewed_key(F.col("l_partkey")).alias("key"), F.col("l_quantity").cast("bigint").alias("value"))
    return _steps_of(rows.where("at is not null and key is not null and value is not null"), steps)


STEP_SIEVE = CandidateSketch(bits=11, keep=40, rows=7, width=256, seed=78, first=8, stride=3)
PART_STEPS = 4


def continuous(spark: SparkSession, rows: DataFrame, steps: int, reporter: ContinuousReporter, sieve: CandidateSketch | None = None, each=None) -> list[tuple]:
    """(step, key, sign, 0, weight) of a continuous report over (step, key, value) changes.

    The sketch is kept as cells and every step adds its changes to them, as to the cells of the candidate
    sketch; only candidates and the keys inside are asked.
    """
    rows, layout, out = materialise(rows, "changes"), reporter.layout, []
    cells, seen, below = None, None, {}
    for step in range(steps):
        change = rows.where(F.col("step") == step).select(F.lit(0).cast("bigint").alias("query_id"), "key", "value")
        before = cells
        cells = materialise(S.build(change, layout, sum_keys=False) if cells is None else S.update(cells, change, layout), "cells")
        if before is not None:
            discard(before)
        if sieve:
            fresh = sieve.build(change)
            below = {j: materialise(S.merge(below[j], fresh[j]) if below else fresh[j], "prefixes") for j in fresh}
            asked = sieve.query(below, change)
        else:
            seen = keys(change) if seen is None else seen.unionAll(keys(change)).distinct()
            asked = seen
        est = S.estimates(reporter.wanted(asked), cells, layout, 1)
        held = spark.createDataFrame([(k,) for k in sorted(reporter.inside)], "key bigint")
        changes = {k: v for k, v in change.join(F.broadcast(held), "key", "left_semi").select("key", "value").collect()}
        for key, (sign, weight) in reporter.advance(step, est, changes).items():
            out.append((step, key, sign, 0, weight))
        if each:
            each(step, est)
    return out


def _continuous_gate(limit: int = 256) -> Gate:
    return Gate(GATE.eps, GATE.delta, limit, GATE.seed, "scaled", GATE.factor)


@query()
def robust_hysteresis_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = continuous(spark, event_steps(spark, sf_dir, 8), 8, ContinuousReporter(PARTS, _continuous_gate()))
    return spark.createDataFrame(found, REPORT).drop("count", "weight")


@query()
def robust_hysteresis_independent(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The continuous report of part keys on independent buckets, asking only the candidates of a fast sketch and the keys inside."""
    found = continuous(spark, part_steps(spark, sf_dir, PART_STEPS), PART_STEPS, ContinuousReporter(SKIPPING, _continuous_gate()), STEP_SIEVE)
    return spark.createDataFrame(found, REPORT).drop("count", "weight")


@query()
def tracked_weights(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = event_steps(spark, sf_dir, 6)
    gate = Gate(GATE.eps, GATE.delta, 2 * 256, GATE.seed, "scaled", GATE.factor)
    return spark.createDataFrame(continuous(spark, rows, 6, ContinuousReporter(PARTS, gate, weights_up_to=weight_bound(rows))), REPORT).drop("count")


@query()
def charges_saved(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same steps through the continuous and the threshold report: asks, passing tests that are charged, and accesses."""
    stable, plain = ContinuousReporter(SKIPPING, _continuous_gate()), RobustReporter(SKIPPING, _continuous_gate())
    continuous(spark, part_steps(spark, sf_dir, PART_STEPS), PART_STEPS, stable, each=lambda step, est: plain.step(step, est))
    rows = [(name, r.accesses.asks, r.accesses.passes, sum(r.accesses.counts.values())) for name, r in (("continuous", stable), ("threshold", plain))]
    return spark.createDataFrame(rows, "report string, replayed_asks int, passes int, accesses bigint")


@query()
def weight_scan_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Weights of the robustly reported keys, beside their true values and the promised error."""
    vec = V.skewed_parts(spark, sf_dir)
    reporter = RobustReporter(PARTS, OPEN, weights_up_to=weight_bound(vec))
    found = report_frame(spark, {0: reporter.step(0, estimated(vec, PARTS))})
    joined = found.join(vec, ["query_id", "key"]).join(E.tail_norm2(vec, 4, summed=True, queries=1), "query_id")
    return joined.select("query_id", "key", "weight", "value", F.sqrt(F.col("tail2") / 4).alias("promised"), (F.abs(F.col("weight") - F.col("value")) <= F.sqrt(F.col("tail2") / 4)).alias("within"))


@query(
    T.with_(
        *_PARTS, ("t", T.tail2("vec", 4)), ("h", T.heavy("vec", 10)),
        then="SELECT e.query_id, e.key, count(*) AS part, count(*) FILTER (e.est <= h.value - sqrt(t.tail2 / 4)) AS low, count(*) FILTER (abs(e.est - h.value) < sqrt(t.tail2 / 4)) AS good, count(*) FILTER (e.est >= h.value + sqrt(t.tail2 / 4)) AS high FROM est e JOIN h ON e.query_id = h.query_id AND e.key = h.key JOIN t ON e.query_id = t.query_id GROUP BY ALL",
    )
)
def weight_certificate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Of each heavy key's buckets: how many lie within the promised error, below it and above it."""
    vec = V.skewed_parts(spark, sf_dir)
    est = estimated(vec, PARTS).join(E.exact_heavy(vec, 10, summed=True, queries=1).select("query_id", "key", "value"), ["query_id", "key"]).join(E.tail_norm2(vec, 4, summed=True, queries=1), "query_id")
    near = F.sqrt(F.col("tail2") / 4)
    count = lambda cond: F.count(F.when(cond, 1))
    off = F.col("est") - F.col("value")
    return est.groupBy("query_id", "key").agg(F.count("*").alias("part"), count(F.col("est") <= F.col("value") - near).alias("low"), count(F.abs(off) < near).alias("good"), count(F.col("est") >= F.col("value") + near).alias("high"))


# -- candidates -----------------------------------------------------------------------------------
SIEVE = CandidateSketch(bits=11, keep=40, rows=7, width=256, seed=77, first=8, stride=3)
_STEPS, _ALIVE = T.candidates("vec", SIEVE)


@query(T.with_(("vec", T.vector("skewed_parts")), *_STEPS, then=f"SELECT query_id, key FROM {_ALIVE}"))
def candidate_keys(spark: SparkSession, sf_dir: str) -> DataFrame:
    vec = V.skewed_parts(spark, sf_dir)
    return SIEVE.query(SIEVE.build(vec), vec)


@query(
    T.with_(
        ("vec", T.vector("skewed_parts")), *_STEPS, ("cells", T.cells("vec", PARTS)), ("wanted", f"SELECT query_id, key FROM {_ALIVE}"), ("est", T.estimates("wanted", "cells", PARTS)), ("votes", T.votes("est")), ("asked", _asked_sql(OPEN, _LEVEL)),
        then="SELECT query_id, key, CASE WHEN pos_pass THEN 1 ELSE -1 END AS sign, CAST(CASE WHEN pos_pass THEN pos ELSE neg END AS INTEGER) AS count FROM asked WHERE pos_pass OR neg_pass",
    )
)
def candidate_pruned_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The robust report with only the candidates tested."""
    vec = V.skewed_parts(spark, sf_dir)
    wanted = SIEVE.query(SIEVE.build(vec), vec)
    est = S.estimates(wanted, S.build(vec, PARTS, sum_keys=False), PARTS, 1)
    return report_frame(spark, {0: RobustReporter(PARTS, OPEN).step(0, est)}).drop("weight")


# -- baselines ------------------------------------------------------------------------------------
#: Copies for 16 queries of 5 heavy keys.
COPIES = B.ensemble_size(16, 5)
INNER = RowHashedCopies(25, 64, 5)
_COPIED = "(SELECT v.query_id, v.key, v.value, CAST(c AS BIGINT) AS copy FROM vec v, (SELECT unnest(range(0, {n})) AS c))"
_ENSEMBLE = [
    ("vec", T.vector("skewed_parts")), ("copied", _COPIED.format(n=COPIES)[1:-1]), ("spread", INNER.sql("copied")),
    ("cells", "SELECT copy, query_id, row, bucket, CAST(sum(sign * value) AS BIGINT) AS c FROM spread GROUP BY ALL"),
    ("est", "SELECT s.copy, s.query_id, s.key, s.sign * c.c AS est FROM spread s JOIN cells c ON s.copy = c.copy AND s.query_id = c.query_id AND s.row = c.row AND s.bucket = c.bucket"),
    ("reports", f"SELECT copy, query_id, key FROM est GROUP BY ALL HAVING avg(CASE WHEN est > 0 THEN 1.0::DOUBLE ELSE 0 END) >= {MID!r} OR avg(CASE WHEN est < 0 THEN 1.0::DOUBLE ELSE 0 END) >= {MID!r}"),
    ("voted", "SELECT query_id, key, count(*) AS copies_for FROM reports GROUP BY query_id, key"),
]


def _voted(spark: SparkSession, sf_dir: str) -> DataFrame:
    vec = V.skewed_parts(spark, sf_dir)
    return B.ensemble_votes(vec, keys(vec), COPIES, INNER, MID)


@query(T.with_(*_ENSEMBLE, then="SELECT * FROM voted"))
def ensemble_votes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _voted(spark, sf_dir)


@query(T.with_(*_ENSEMBLE, then=f"SELECT query_id, key, copies_for, round(copies_for + {T.noise(GATE, 0, AT_LEAST, 'query_id', 'key')}, 6) AS noisy FROM voted WHERE copies_for + {T.noise(GATE, 0, AT_LEAST, 'query_id', 'key')} >= {COPIES / 2}"))
def private_ensemble_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    return B.private_ensemble(_voted(spark, sf_dir), COPIES, GATE).withColumn("noisy", F.round("noisy", 6))


@query()
def noisy_median(spark: SparkSession, sf_dir: str) -> DataFrame:
    vec = V.user_values(spark, sf_dir)
    return B.noisy_median(estimated(vec, USERS), 1.0, list(range(-2_000_000, 4_000_001, 20_000)), 31)


FRESH = RowHashedCopies(33, 64, 9)
_FRESH = [
    ("vec", T.vector("hourly_users")), ("copied", "SELECT *, query_id AS copy FROM vec"), ("spread", FRESH.sql("copied")),
    ("cells", "SELECT query_id, row, bucket, CAST(sum(sign * value) AS BIGINT) AS c FROM spread GROUP BY ALL"),
    ("est", "SELECT s.query_id, s.key, CAST(s.sign * c.c AS BIGINT) AS est FROM spread s JOIN cells c ON s.query_id = c.query_id AND s.row = c.row AND s.bucket = c.bucket"),
    ("med", T.medians("est")),
]


@query(T.with_(*_FRESH, then=T.top("med", 5)))
def fresh_copy_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Median reports of all hours in which every hour has a sketch of its own."""
    vec = V.hourly_users(spark, sf_dir)
    return E.median_report(B.fresh_copy_estimates(vec, keys(vec), FRESH), 5)


@query()
def l1_frequent_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counters of the tokens above a hundredth of all, with true counts beside the lower bounds."""
    tokens = V.tokens_of(V.read_table(spark, sf_dir, "documents", ["text"])).select("token")
    total = tokens.count()
    low = B.l1_frequent(tokens, "token", 400)
    true = tokens.groupBy("token").agg(F.count("*").alias("n"))
    return true.where(F.col("n") * 100 > total).join(low, F.col("token") == F.col("item"), "left").select("token", "n", "low", ((F.col("low") <= F.col("n")) & (F.col("low") >= F.col("n") - total / 100)).alias("holds"))


@query()
def builtin_frequent_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The engine's own frequent-items sketch, for contrast."""
    tokens = V.tokens_of(V.read_table(spark, sf_dir, "documents", ["text"])).select("token")
    return tokens.agg(F.expr("approx_top_k(token, 20)").alias("top")).select(F.explode("top").alias("t")).select(F.col("t.item").alias("token"), F.col("t.count").alias("count"))


@query()
def size_comparison(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sketch sizes of the approaches up to logarithms, by rounds and heavy keys, and as shares of the keys of the part vector."""
    rows = [(m, k, name, size) for m in (10, 100, 1_000, 10_000) for k in (1, 10, 100) for name, size in size_baselines(m, k).items()]
    sizes = spark.createDataFrame(rows, "rounds int, heavy int, approach string, size double")
    whole = V.part_quantities(spark, sf_dir).agg(F.count("*").alias("keys"))
    return sizes.crossJoin(F.broadcast(whole)).withColumn("share", F.col("size") / F.when(F.col("keys") > 0, F.col("keys")))


@query()
def sizing_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The parameter rules for a thousand queries of the part vector, each as a row."""
    n, m, k, beta, limit = V.part_quantities(spark, sf_dir).count(), 1_000, 4, 0.01, 100
    rows, width = Z.size_median(k, 0.25, beta, n, m)
    robust = Z.size_robust(k, n, m, limit, beta)
    terms = Z.generalization_terms(robust.buckets, robust.width, n, m, beta, Z.slack())
    out = {
        "median rows": rows, "median width": width, "agreement rows": Z.size_agreement(n, m, beta, (Z.TAU_B - Z.TAU_A) / 2), "agreement width": Z.width_for(k), "suspects at most": Z.suspect_cap(k),
        "robust buckets": robust.buckets, "robust width": robust.width, "epsilon": robust.eps, "delta": robust.delta, "limit with weights": 2 * limit,
        "slack": Z.slack(), "slack, continuous": Z.slack(continuous=True), "budget share, Markov": Z.budget_share(Z.slack()), "budget share, second moment": Z.budget_share(Z.slack(), "chebyshev"),
        **{f"generalization {name}": value for name, value in terms.items()},
    }
    return spark.createDataFrame([(name, float(value)) for name, value in out.items()], "rule string, value double")


@query()
def fast_hash_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The threshold report with the engine's own hash beside that with polynomials."""
    vec = V.skewed_parts(spark, sf_dir)
    out = None
    for family in ("poly", "fast"):
        layout = RowHashed(PARTS.rows, PARTS.width, PARTS.seed, family=family)
        report = E.threshold_report(E.agreement(E.votes(estimated(vec, layout)), layout.per_key), MID).select(F.lit(family).alias("family"), "query_id", "key", "sign")
        out = report if out is None else out.unionAll(report)
    return out.groupBy("query_id", "key").agg(F.max(F.when(F.col("family") == "poly", F.col("sign"))).alias("poly"), F.max(F.when(F.col("family") == "fast", F.col("sign"))).alias("fast"))


@query()
def report_correctness(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Heavy keys missed and reported keys that are no suspects, both by true agreement, for tags by number of rows."""
    vec = V.html_tags(spark, sf_dir)
    truth = E.normal_agreement(vec, 16, 1)
    heavy, suspect = E.heavy_set(truth, Z.TAU_B), E.suspect_set(truth, Z.TAU_A)
    out = None
    for rows in (65, 257):
        layout = RowHashed(rows, 16, 300 + rows, 4)
        report = E.threshold_report(E.agreement(E.votes(estimated(vec, layout)), rows), MID)
        wrong = M.is_correct(report.select("query_id", "key"), heavy, suspect).agg(F.coalesce(F.sum("missed"), F.lit(0)).alias("missed"), F.coalesce(F.sum("excess"), F.lit(0)).alias("excess"))
        sizes = heavy.agg(F.count("*").alias("heavy")).crossJoin(suspect.agg(F.count("*").alias("suspects")))
        part = wrong.crossJoin(sizes).select(F.lit(rows).alias("rows"), "missed", "excess", "heavy", "suspects", F.lit(Z.suspect_cap(1)).alias("suspects_at_most"))
        out = part if out is None else out.unionAll(part)
    return out

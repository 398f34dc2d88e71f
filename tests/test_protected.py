import math
import warnings

import numpy as np
import pytest
from pyspark.sql import functions as F

from steadysketch.catalog import QUERIES
from steadysketch.operators import baselines as B
from steadysketch.operators import estimators as E
from steadysketch.operators import sketch as S
from steadysketch.operators.candidates import CandidateSketch
from steadysketch.operators.gate import AT_LEAST, AT_MOST, Accesses, Gate, survival
from steadysketch.operators import sizing as Z
from steadysketch.operators.layouts import IndependentBuckets, RowHashed, RowHashedCopies
from steadysketch.operators.robust import BudgetExhausted, ContinuousReporter, RobustReporter, UnprovenLayout, serial_report
from steadysketch.operators.weights import private_median, scan, scan_naive
from steadysketch.sources import vectors as V

LAYOUT = RowHashed(33, 16, seed=5)
OPEN = Gate(0.1, 1e-6, 1000, 7, "scaled", 1e-4)


def skewed(spark, queries=1):
    rows = [(q, k, 4000 // (k + 1 + q)) for q in range(queries) for k in range(60)]
    return spark.createDataFrame(rows, "query_id bigint, key bigint, value bigint")


def estimates(spark, queries=1):
    vec = skewed(spark, queries)
    return S.estimates(vec.select("query_id", "key"), S.build(vec, LAYOUT), LAYOUT, queries)


def grouped(est):
    out = {}
    for r in est.collect():
        out.setdefault(r.key, []).append((r.row, r.bucket, r.est))
    return out


def test_survival_is_the_law_of_the_noise():
    rng = np.random.default_rng(1)
    for wide, narrow, cap in ((5.0, 2.0, 1.0), (1.0, 4.0, 3.0), (2.0, 2.0, 0.5)):
        draws = rng.laplace(0, wide, 400_000) + np.minimum(cap, rng.laplace(0, narrow, 400_000))
        for x in (-7.0, -1.0, 0.0, 0.4, 2.0, 9.0):
            assert abs((draws >= x).mean() - survival(x, wide, narrow, cap)) < 0.004


def test_noise_is_the_same_in_columns_and_in_python(spark):
    rows = spark.range(50).select("id", OPEN.noise_column(1, AT_LEAST, F.lit(3), F.col("id")).alias("a"), OPEN.noise_column(1, AT_MOST, F.lit(3), F.col("id")).alias("b")).collect()
    for r in rows:
        assert abs(r.a - OPEN.noise_value(1, AT_LEAST, 3, r.id)) < 1e-9
        assert abs(r.b - OPEN.noise_value(1, AT_MOST, 3, r.id)) < 1e-9
        assert r.a <= r.b + 1e-9
    # The second part of the noise is capped above for one direction and below for the other.
    assert max(r.a - r.b for r in rows) <= 2 * OPEN.cap + 1e-9


def test_charges_retire_at_exactly_the_limit():
    held = Accesses(2)
    held.charge([(0, 1)])
    assert not held.retired
    held.charge([(0, 1), (1, 1)])
    assert held.retired == {(0, 1)} and held.histogram() == {1: 1, 2: 1}


def test_distributed_report_equals_the_serial_rule(spark):
    for limit in (1, 3, 1000):
        gate = Gate(0.1, 1e-6, limit, 7, "scaled", 1e-4)
        mine, reference = RobustReporter(LAYOUT, gate), RobustReporter(LAYOUT, gate)
        est = estimates(spark)
        for q in range(2):
            assert mine.step(q, est.withColumn("query_id", F.lit(q).cast("bigint"))) == serial_report(q, grouped(est), reference)
        assert mine.accesses.counts == reference.accesses.counts


def test_a_batch_equals_step_by_step(spark):
    est = estimates(spark, 3)
    gate = Gate(0.1, 1e-6, 2, 7, "scaled", 1e-4)
    one, other = RobustReporter(LAYOUT, gate), RobustReporter(LAYOUT, gate)
    batch = one.run(est)
    for q in range(3):
        assert batch.get(q, []) == other.step(q, est.where(F.col("query_id") == q))
    assert one.accesses.counts == other.accesses.counts


def test_all_buckets_retired_reports_nothing(spark):
    reporter = RobustReporter(LAYOUT, OPEN)
    reporter.accesses.retired = {(r, b) for r in range(33) for b in range(16)}
    assert reporter.step(0, estimates(spark)) == []
    assert reporter.retired_share(skewed(spark)).agg(F.min("share")).first()[0] == 1.0


def test_continuous_report_enters_leaves_and_tracks(spark):
    reporter = ContinuousReporter(LAYOUT, OPEN, weights_up_to=20_000)
    keys = spark.createDataFrame([(0, k) for k in range(20)], "query_id bigint, key bigint")

    def est(value):
        vec = spark.createDataFrame([(0, 1, value)] + [(0, k, 3 + k) for k in range(2, 20)], "query_id bigint, key bigint, value bigint").where("value <> 0")
        return S.estimates(keys, S.build(vec, LAYOUT), LAYOUT, 1)

    assert reporter.advance(0, est(0)).get(1) is None
    sign, weight = reporter.advance(1, est(5000), {1: 5000})[1]
    assert sign == 1 and abs(weight - 5000) < 60
    assert abs(reporter.advance(2, est(5100), {1: 100})[1][1] - 5100) < 60
    assert 1 not in reporter.advance(3, est(0), {1: -5100})
    # A heavy key whose sign turns leaves in one step and can come back in the next.
    reporter.advance(4, est(5000), {1: 5000})
    assert 1 not in reporter.advance(5, est(-5000), {1: -10000})
    assert reporter.advance(6, est(-5000))[1][0] == -1


def test_skipping_scan_has_the_law_of_the_naive_scan():
    rng = np.random.default_rng(3)
    gate = Gate(2.0, 0.3, None, 1, "scaled", 0.2)
    est = np.array([-6.0, -2, -2, 1, 3, 3, 4, 8, 9])
    wide, narrow = gate.scales

    def noise(_):
        return rng.laplace(0, wide) + min(gate.cap, rng.laplace(0, narrow))

    a = np.array([scan_naive(est, 10, 4.5, noise) for _ in range(4000)])
    b = np.array([scan(est, 10, 4.5, gate, lambda cell: rng.uniform(1e-12, 1)) for _ in range(4000)])
    for w in range(-10, 11):
        assert abs((a <= w).mean() - (b <= w).mean()) < 0.045


def test_private_median_is_near_the_median():
    est = np.arange(101.0)
    got = [private_median(est, 1.0, np.arange(0, 101.0), u) for u in np.linspace(0.01, 0.99, 50)]
    assert abs(np.mean(got) - 50) < 5


def test_candidates_hold_the_heavy_keys(spark):
    vec = spark.createDataFrame([(0, (k * 37) % 1024, v) for k, v in enumerate([900, -800, 700] + [5, -5] * 200)], "query_id bigint, key bigint, value bigint").groupBy("query_id", "key").agg(F.sum("value").alias("value"))
    sieve = CandidateSketch(bits=10, keep=16, rows=5, width=64, first=4, stride=3)
    found = {r.key for r in sieve.query(sieve.build(vec), vec).collect()}
    assert {r.key for r in E.exact_heavy(vec, 5).collect()} <= found and len(found) <= 16


def test_ensemble_of_one_equals_its_inner_report(spark):
    vec = skewed(spark)
    keys = vec.select("query_id", "key")
    layout = RowHashedCopies(25, 16, 5)
    voted = {r.key: r.copies_for for r in B.ensemble_votes(vec, keys, 1, layout, 0.9).collect()}
    copy = lambda df: df.withColumn("copy", F.lit(0).cast("bigint"))
    cells = layout.participation(copy(vec)).groupBy("row", "bucket").agg(F.sum(F.col("sign") * F.col("value")).alias("c"))
    est = layout.participation(copy(keys)).join(cells, ["row", "bucket"]).groupBy("key").agg(F.avg((F.col("sign") * F.col("c") > 0).cast("int")).alias("p"), F.avg((F.col("sign") * F.col("c") < 0).cast("int")).alias("q"))
    assert voted == {r.key: 1 for r in est.where("p >= 0.9 or q >= 0.9").collect()} and voted


def test_copies_of_an_ensemble_differ(spark):
    layout = RowHashedCopies(5, 16, 5)
    rows = layout.participation(spark.createDataFrame([(k, c) for k in range(40) for c in range(2)], "key bigint, copy bigint")).collect()
    spots = {c: [(r.key, r.row, r.bucket, r.sign) for r in rows if r["copy"] == c] for c in range(2)}
    assert sorted(spots[0]) != sorted(spots[1]) and len(spots[0]) == 200 and B.ensemble_size(16, 5) == 9


def test_gate_follows_from_its_limit():
    gate = Gate.for_reports(64, 1000, 500, 16)
    assert gate.eps == 1 / 8 and gate.delta == 1 / (1000 * 500 * 16 * 64) and gate.limit == 64
    assert Gate.for_reports(64, 1000, 500, 16, weights=True).limit == 128
    with pytest.raises(ValueError):
        Gate.for_reports(64, 1000, 63, 16)
    assert gate.pass_probability(1e7, 10.0) == 1 and gate.pass_probability(0, 1e7) == 0


def test_unproven_layouts_warn_and_worn_ones_stop(spark):
    with pytest.warns(UnprovenLayout):
        reporter = RobustReporter(LAYOUT, Gate(0.1, 1e-6, 1, 7, "scaled", 1e-4), most_retired=0.2)
    with warnings.catch_warnings():
        warnings.simplefilter("error")
        RobustReporter(IndependentBuckets(64, 4), OPEN)
    buckets = [(0, row, row % 4, 5) for row in range(33)]
    held = {(r, b) for _, r, b, _ in buckets}
    reporter.replay(0, [(1, [(r, b, e) for _, r, b, e in buckets])], 20.0)
    assert reporter.accesses.retired == held
    with pytest.raises(BudgetExhausted):
        reporter.replay(1, [(1, [(r, b, e) for _, r, b, e in buckets])], 20.0)


def test_report_on_independent_buckets_equals_the_serial_rule(spark):
    layout, gate = IndependentBuckets(640, 8, seed=3), Gate(0.1, 1e-6, 2, 7, "scaled", 1e-4)
    vec = skewed(spark)
    est = S.estimates(vec.select("query_id", "key"), S.build(vec, layout), layout, 1)
    mine, reference = RobustReporter(layout, gate, tau_a=0.6, tau_b=0.9), RobustReporter(layout, gate, tau_a=0.6, tau_b=0.9)
    assert mine.step(0, est) == serial_report(0, grouped(est), reference) and mine.accesses.passes
    assert mine.accesses.retired == reference.accesses.retired


def test_sizes_by_their_formulas():
    assert Z.slack() == (Z.TAU_B - Z.TAU_A) / 10 and Z.slack(continuous=True) == (Z.TAU_B - Z.TAU_A) / 25
    assert Z.budget_share(0.02) == 0.01 and abs(Z.budget_share(0.02, "second moment") - 0.1) < 1e-12
    assert Z.width_for(4) == 64 and Z.suspect_cap(4) == 192
    assert Z.size_agreement(1000, 100, 0.01, 0.1) == math.ceil(300 * math.log(4e5 / 0.01))
    rows, width = Z.size_median(4, 0.5, 0.01, 1000)
    assert rows % 2 == 1 and rows >= 4 * math.log(1e5) and width == 64
    terms = Z.generalization_terms(10**9, 64, 100, 100, 0.01, 0.011)
    least = Z.generalization_terms(math.ceil(terms["least_buckets"]), 64, 100, 100, 0.01, 0.011)
    assert least["bound"] <= least["allowed"] + 1e-12 and Z.generalization_terms(1000, 64, 100, 100, 0.01, 0.011)["bound"] > least["allowed"]


def test_true_agreement_by_all_ways(spark):
    vec = spark.createDataFrame([(0, k, 1 + k % 3) for k in range(60)] + [(0, 99, 40)], "query_id bigint, key bigint, value bigint")
    keys = vec.select("query_id", "key")
    exact = {r.key: r.p_plus for r in E.true_agreement(vec, keys, 8, 200).collect()}
    normal = {r.key: r.p_plus for r in E.normal_agreement(vec, 8, 1).collect()}
    layout = IndependentBuckets(40_000, 8, seed=5)
    counted = E.votes(S.estimates(keys, S.build(vec, layout), layout, 1))
    sampled = {r.key: r.p_plus for r in E.sampled_agreement(counted, layout.per_key).collect()}
    sure = 0.5 * (1 + math.erf(40 / math.sqrt(sum((1 + k % 3) ** 2 for k in range(60)) / 8) / math.sqrt(2)))
    assert abs(normal[99] - sure) < 1e-6 and exact[99] > 0.99
    assert all(abs(exact[k] - sampled[k]) < 0.03 for k in exact)
    truth = E.true_agreement(vec, keys, 8, 200)
    assert [r.key for r in E.heavy_set(truth, 0.96).collect()] == [99] and {r.key for r in E.suspect_set(truth, 0.5).collect()} >= {99}


def test_fast_hash_has_fair_buckets_and_signs(spark):
    layout = RowHashed(9, 16, 3, family="fast")
    rows = layout.participation(spark.range(2000).withColumnRenamed("id", "key")).collect()
    assert abs(sum(r.sign for r in rows)) < 600 and {r.bucket for r in rows} == set(range(16)) and {r.sign for r in rows} == {-1, 1}
    assert layout.fingerprint != RowHashed(9, 16, 3).fingerprint


def test_frequent_counters_bound_the_counts(spark):
    items = spark.createDataFrame([(i % 7 if i % 3 else 1,) for i in range(3000)] + [(None,)], "x int").repartition(5)
    true = {r.x: r["count"] for r in items.where("x is not null").groupBy("x").count().collect()}
    low = {r["item"]: r.low for r in B.l1_frequent(items, "x", 3).collect()}
    assert all(true[i] - 3000 / 3 * 2 <= n <= true[i] for i, n in low.items())
    assert 1 in low


def test_sequences_go_through_all_hours(spark):
    data = "/root/testdata/sf0.001"
    vec = V.hourly_users(spark, data)
    assert QUERIES["bucket_health"](spark, data).count() == vec.select("key").distinct().count()
    hours = {r.query_id for r in QUERIES["robust_threshold_sequence"](spark, data).collect()}
    assert max(hours) >= 10


def test_weights_are_not_clipped_on_larger_tables(spark):
    rows = QUERIES["weight_scan_parts"](spark, "/root/testdata/sf0.1").collect()
    heaviest = max(rows, key=lambda r: r.value)
    assert heaviest.value > 2_000_000 and heaviest.weight != 2_000_000 and heaviest.within


def test_continuous_report_is_of_users(spark):
    data = "/root/testdata/sf0.001"
    users = {r.key for r in V.user_values(spark, data).select("key").distinct().collect()}
    found = {r.key for r in QUERIES["robust_hysteresis_events"](spark, data).collect()}
    assert found and found <= users and found - {(u % 32) ** 2 for u in users}


def test_counters_of_tasks_without_items(spark):
    """a task that had no item failed the query."""
    items = spark.createDataFrame([("a",), ("a",), (None,)], "x string").repartition(8)
    assert [tuple(r) for r in B.l1_frequent(items, "x", 3).collect()] == [("a", 2)]
    assert B.l1_frequent(items.where("x = 'none'"), "x", 3).count() == 0

from math import sqrt

import pytest
from pyspark.sql import functions as F

from steadysketch.operators import arena as R
from steadysketch.operators import attacks as A
from steadysketch.operators import sketch as S
from steadysketch.operators.gate import Gate
from steadysketch.operators.layouts import IndependentBuckets, RowHashed
from steadysketch.queries.adversarial import special_keys
from steadysketch.sources import vectors as V

DATA = "/root/testdata/sf0.001"
LAYOUT = RowHashed(9, 5, seed=21, degree=4)


def probe():
    noise = 1000 * sqrt(30 / 5)
    return A.Probe.make(LAYOUT, 3, 1_500_000_000, int(2 * noise), int(40 * noise))


def test_probe_estimates_equal_those_of_whole_queries(spark):
    tails = V.tails(spark, DATA, 30, 6)
    p = probe()
    mine = {(r.tail_id, r.key, r.row): r.special + r.noise for r in A.probe_estimates(tails, p, special_keys(p)).collect()}
    head = spark.createDataFrame([(q, k, w) for q in range(6) for k, w in p.weights.items()], "query_id bigint, key bigint, value bigint")
    vec = head.unionAll(tails.select(F.col("tail_id").alias("query_id"), "key", "value"))
    asked = spark.createDataFrame([(q, k) for q in range(6) for k in special_keys(p)], "query_id bigint, key bigint")
    whole = {(r.query_id, r.key, r.row): r.est for r in S.estimates(asked, S.build(vec, LAYOUT), LAYOUT, 6).collect()}
    assert mine == whole


def test_the_designated_key_gains_bias_and_the_control_key_none(spark):
    tails = V.tails(spark, DATA, 30, 200)
    p = probe()
    est = A.probe_estimates(tails, p, special_keys(p))
    signs = A.collect(A.median_rounds(est, p), "signed")
    last = {r.key: r.bnr for r in A.bnr_curve(est, signs, tails, p).where("round = 150").collect()}
    spread = (last[p.designated] - last[p.twin]) / 2
    assert spread > 0.5 and abs(last[p.control]) < spread


def test_updates_swap_tails_and_end_empty(spark):
    tails = V.tails(spark, DATA, 30, 4)
    ups = A.as_updates(tails, probe())
    left = {r.key: r.v for r in ups.groupBy("key").agg(F.sum("value").alias("v")).where("v <> 0").collect()}
    assert left == {1_500_000_000: 4}


def test_weight_is_found_by_bisection():
    assert A.calibrate_weight(lambda w: w / 1000, 0, 1000) == 500


@pytest.mark.parametrize("layout", [RowHashed(9, 5, seed=21, degree=4), IndependentBuckets(45, 5, seed=22)])
def test_spots_give_the_estimates_of_whole_queries(spark, layout):
    tails = V.tails(spark, DATA, 30, 4)
    held = R.spots(spark, [R.Contender(7, layout, 3)], 1_500_000_000, 1000 * sqrt(30))
    mine = {(r.tail_id, r.role, r.spot): r.special + r.noise for r in R.spot_noise(tails, held, 200).collect()}
    noise = 1000 * sqrt(30) / sqrt(5)
    keys = {1_500_000_000: 1, 1_500_000_001: -1, 1_500_000_002: 0}
    weights = {1_500_000_000: int(2 * noise), 1_500_000_001: int(2 * noise), 1_500_000_003: int(40 * noise), 1_500_000_004: int(40 * noise)}
    head = spark.createDataFrame([(q, k, w) for q in range(4) for k, w in weights.items()], "query_id bigint, key bigint, value bigint")
    vec = head.unionAll(tails.select(F.col("tail_id").alias("query_id"), "key", "value"))
    asked = spark.createDataFrame([(q, k) for q in range(4) for k in keys], "query_id bigint, key bigint")
    place = "row" if isinstance(layout, RowHashed) else "bucket"
    whole = {(r.query_id, keys[r.key], r[place]): r.est for r in S.estimates(asked, S.build(vec, layout), layout, 4).collect()}
    assert mine == whole and mine


def test_plain_rule_breaks_before_its_gate_lets_go(spark):
    tails = V.tails(spark, DATA, 80, 200)
    held = R.spots(spark, [R.Contender(3, IndependentBuckets(33 * 16, 16, seed=4), 1, 1.31)], 1_500_000_000, 1000 * sqrt(80)).where("role = 1")
    gate = Gate(0.1, 1e-9, 10, 5, "none")
    played = {r.rule: r for r in R.play_rules(R.spot_noise(tails, held, 200), tails, [R.Rule("plain", None), R.Rule("gate", gate)], 0.905, 2.6, 1 / 3).collect()}
    assert played["plain"].wrong_at and played["plain"].bnr > 0.5 and played["plain"].exhausted is None
    assert played["gate"].exhausted and played["gate"].queries < played["plain"].queries * 5


def test_border_is_found_without_parameters():
    needed = [900, 1000, 1100, 1200, 800, 950, 1050, 1010, 990]
    steps = A.search_border(lambda w, j: w > needed[j])
    assert 0 < steps[-1][1] < 9 and 800 < steps[-1][0] <= 1200


def test_game_sees_reports_only():
    said = A.play(lambda past: len(past) if len(past) < 3 else None, lambda q, v: [v * 10], 9)
    assert said == [[0], [10], [20]]

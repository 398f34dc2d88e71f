"""Queries of parameters that go over a given table."""

from steadysketch.catalog import QUERIES
from steadysketch.functions.hashing import PRIME
from steadysketch.sources import vectors as V


SF = "/root/testdata/sf0.001"


def test_gate_noise_is_drawn_for_every_order(spark):
    """the keys were made up."""
    orders = spark.read.parquet(f"{SF}/orders.parquet")
    found = QUERIES["gate_noise_sample"](spark, SF)
    assert found.count() == orders.count() and found.join(orders, found["key"] == orders["o_orderkey"], "left_anti").count() == 0


def test_pass_table_has_the_tests_of_all_parts(spark):
    """F8: no table was read."""
    found = QUERIES["gate_pass_table"](spark, SF).toPandas()
    keys = V.skewed_parts(spark, SF).count()
    assert len(found) == found["count"].nunique() == 130 and found["tests"].sum() == 2 * keys > 0


def test_coefficients_have_their_terms_over_all_line_items(spark):
    """no table was read."""
    keys = [r.l_partkey for r in spark.read.parquet(f"{SF}/lineitem.parquet").select("l_partkey").collect()]
    for r in QUERIES["row_coefficients"](spark, SF).collect():
        assert r.keyed == len(keys) and r.terms == sum(r.coefficient * k**r.power % PRIME for k in keys)


def test_sizes_are_shares_of_the_part_vector(spark):
    """no table was read."""
    keys = V.part_quantities(spark, SF).count()
    found = QUERIES["size_comparison"](spark, SF).collect()
    assert len(found) == 48 and all(r["keys"] == keys and r["share"] == r["size"] / keys for r in found)

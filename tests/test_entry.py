import duckdb
import pytest

import __spark_entry__
from steadysketch.catalog import ORACLE_SQL, QUERIES

DATA = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
CHEAP = ["exact_heavy_skewed_parts", "row_hash_cells_parts", "threshold_report_independent", "robust_threshold_parts", "candidate_keys", "attack_median_rounds", "budget_flips", "report_asof_orders", "session_cells", "gate_noise_sample", "hinted_joins", "report_sets", "pivoted_cells", "arrow_medians", "fresh_copy_report", "private_ensemble_report", "churn_against_flips", "sql_heavy_classes"]


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{DATA}/{t}.parquet'")
    return con


def test_every_oracle_belongs_to_a_query():
    assert set(ORACLE_SQL) <= set(QUERIES) <= set(__spark_entry__.queries())


def test_entry_gives_rows(spark):
    found = __spark_entry__.entry(spark)
    assert found.columns == ["query_id", "key", "sign", "count", "noise_mode"] and found.count() > 0


@pytest.mark.parametrize("name", CHEAP)
def test_query_equals_sql(spark, duck, name):
    got = QUERIES[name](spark, DATA).toPandas()
    want = duck.execute(ORACLE_SQL[name]).df()
    columns = sorted(want.columns)
    assert columns == sorted(got.columns)
    rows = lambda df: sorted(map(tuple, df[columns].astype(object).where(df[columns].notna(), None).values.tolist()), key=str)
    assert rows(got) == rows(want)

import duckdb
import pytest

import __spark_entry__ as entry

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SOME = ["mask_popcount", "vec_sum_flag", "vec_avg_all", "vec_count_lanes8", "mask_cmp_le", "coin_fraction", "null_probability", "released_sum_fixed_key", "tpch_h08", "tpch_h13", "tpch_h17", "tpch_h22", "hits_q10", "hits_q28", "stream_daily_counts", "vec_rollup", "vec_count_128_worlds", "posterior_fold", "session_two_releases", "attack_bounds", "ledger_cells", "released_h01", "released_h13", "released_h17", "tpch_h20_released", "hits_q43", "hits_q30_shared", "vec_sum_buffered", "vec_sum_levels", "approx_sum_near", "float_sum_near", "utility_pricing", "tpch_h15", "query_rehash", "membership_prior_raw", "success_budgets", "half_sample_interval", "unit_paths", "bernoulli_units", "multi_run_resampled", "ratio_noise_each", "laplace_pricing", "predicted_errors", "utility_diff_crafted"]


@pytest.fixture(scope="module")
def con(sf):
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"create view {t} as select * from '{sf}/{t}.parquet'")
    return c


def test_every_oracle_has_its_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert len(entry.oracle_sql()) > 90


def test_entry_gives_released_rows(spark):
    df = entry.entry(spark)
    assert df.count() > 0 and "sum_qty" in df.columns


@pytest.mark.parametrize("name", SOME)
def test_queries_equal_their_oracles(spark, sf, con, name):
    a = entry.queries()[name](spark, sf).toPandas()
    b = con.sql(entry.oracle_sql()[name]).df()
    a, b = a[sorted(a.columns)], b[sorted(b.columns)]
    assert list(a.columns) == list(b.columns) and len(a) == len(b)
    cols = list(a.columns)
    a, b = a.sort_values(cols, ignore_index=True), b.sort_values(cols, ignore_index=True)
    for c in cols:
        assert ((a[c] == b[c]) | (a[c].isna() & b[c].isna())).all(), c

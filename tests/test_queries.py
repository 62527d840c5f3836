"""Every query with SQL is compared with DuckDB by the driver; here a few of each kind at the smallest size."""

import glob
import os

import duckdb
import pytest

from spectral_frames import workloads

SF = "/root/testdata/sf0.001"
SOME = ["thin_gram_1_power_sums", "thin_mixed_qr_2_two_column", "rank_onehot", "build_cust_part", "gram_relational", "multiply_t_layouts", "stream_gram_daily", "stream_session_moments", "stream_dedup", "svd_udtf", "gram_udaf", "asof_event_feature", "leverage_two_column", "least_squares_price", "geo_low_entries", "stair_sigma",
        "thin_stair_sigma", "thin_geo_sigma", "svd_as_qr", "rank_at_precision_zero", "serial_low_rank", "pca_power_sum", "pivot_user_type", "matrix_files", "mllib_round_trip", "stream_stream_join", "stream_late_rows", "resumed_stream", "asof_order_feature", "renumbered_rows"]


@pytest.mark.parametrize("name", SOME)
def test_query_equals_sql(spark, name):
    c = duckdb.connect()
    for f in glob.glob(f"{SF}/*.parquet"):
        c.sql(f"create view {os.path.basename(f)[:-8]} as select * from '{f}'")
    mine = workloads.QUERIES[name](spark, SF)
    columns = sorted(mine.columns)
    other = c.sql(workloads.ORACLES[name]).df()
    assert columns == sorted(other.columns)
    rows = sorted(tuple(map(str, r)) for r in mine.select(columns).toPandas().values.tolist())
    assert rows == sorted(tuple(map(str, r)) for r in other[columns].values.tolist())


def test_the_engine_stands_alone():
    for path in glob.glob(os.path.join(os.path.dirname(workloads.__file__), "**", "*.py"), recursive=True):
        if f"{os.sep}llm{os.sep}" not in path:
            assert "llm" not in open(path).read()

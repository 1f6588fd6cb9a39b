"""Driver queries against DuckDB on the smallest tables."""

import os

import duckdb
import pytest

from slidemedian import catalog
from slidemedian.sources.tables import TABLES

DATA = "/root/testdata/sf0.001"
CHECKED = (
    "median_events_global",
    "median_lineitem_price_k1001",
    "median_wide_route",
    "median_lineitem_per_part",
    "median_orders_per_cust",
    "median_even_mean",
    "median_edges_partial",
    "median_edges_reflect",
    "median_edges_partial_blocks",
    "median_edges_keep_blocks",
    "median_edges_pad_blocks",
    "median_edges_reflect_blocks",
    "moving_average_global",
    "outer_full",
    "set_operations",
    "stream_tumbling_median",
    "sort_by_filter_isolated",
    "global_positions",
    "median_stride",
    "median_interval",
    "median_k_eq_n",
    "median_k_gt_n",
    "multi_quantile",
    "hampel_two_pass",
    "piecewise_sort_radix",
    "medians_from_sorted",
    "sort_by_filter_concat",
    "baseline_two_trees",
    "baseline_self_join",
    "recovery_quality",
    "median_gen_steps",
    "disorder_per_block",
    "agreement_matrix",
    "agreement_ties",
    "agreement_long",
    "median_out_range",
    "median_array_cells",
    "udtf_median",
    "asof_median_orders",
    "range_join_windows",
    "fn_array",
    "fn_json",
    "cube_flag_status",
)


@pytest.fixture(scope="module")
def duck():
    connection = duckdb.connect()
    for table in TABLES:
        connection.execute(f"CREATE VIEW {table} AS SELECT * FROM '{DATA}/{table}.parquet'")
    return connection


@pytest.mark.skipif(not os.path.isdir(DATA), reason="needs the given tables")
@pytest.mark.parametrize("key", CHECKED)
def test_query_equals_its_sql(spark, duck, key, tmp_path):
    catalog.QUERIES[key](spark, DATA).write.parquet(str(tmp_path / "out"))
    duck.execute(f"CREATE OR REPLACE TABLE wanted AS {catalog.ORACLE_SQL[key]}")
    duck.execute(f"CREATE OR REPLACE TABLE given AS SELECT * FROM '{tmp_path}/out/*.parquet'")
    kinds = [{r[0]: r[1] for r in duck.execute(f"DESCRIBE {t}").fetchall()} for t in ("wanted", "given")]
    assert kinds[0] == kinds[1]
    columns = ", ".join(f'"{c}"' for c in sorted(kinds[0]))
    for one, other in (("wanted", "given"), ("given", "wanted")):
        assert duck.execute(f"SELECT count(*) FROM (SELECT {columns} FROM {one} EXCEPT ALL SELECT {columns} FROM {other})").fetchone()[0] == 0


def test_every_sql_has_a_query():
    assert set(catalog.ORACLE_SQL) <= set(catalog.QUERIES)
    assert set(catalog.QUERIES) - set(catalog.ORACLE_SQL) == {"baseline_approx", "rank_error_approx"}


@pytest.mark.skipif(not os.path.isdir(DATA), reason="needs the given tables")
def test_flagship(spark):
    assert catalog.flagship(spark, DATA).count() > 1000

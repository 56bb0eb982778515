"""A part of the registered queries against DuckDB at the smallest size; tests/oracle.py does all of them."""

import pytest

import __spark_entry__ as entry
from tests.oracle import differences, duck
from twoview.plans.registry import oracle_sql

D = "/root/testdata/sf0.001"
SQL = {D: oracle_sql(D)}
NAMES = [
    "two_stage_knn", "adc_knn", "sdc_knn", "mismatch_knn", "pack_words_gray", "lloyd_two_rounds", "loss_rank_all_gray", "kendall_affine", "recall_table", "tau_histogram", "graph_stats",
    "learned_two_stage", "learned_numbering", "swap_delta_rank", "ivf_search_dealt", "knn_graph", "graph_descent", "residual_search", "probe_cells_udtf", "stream_late", "walk_step", "range_join", "asof_join", "skew_salted_join", "stream_sessions", "stream_interval_join", "stream_drift",
]


@pytest.fixture(scope="module")
def con():
    return duck(D)


@pytest.mark.parametrize("name", NAMES)
def test_query(spark, con, name):
    fn, sql = entry.queries()[name], SQL[D].get(name)
    if sql is None:
        assert fn(spark, D).count() > 0
    else:
        assert differences(spark, con, fn, sql, D) is None


def test_recursive_walk_reads_its_table(spark, tmp_path):
    spark.createDataFrame([(2, 5), (2, 7), (5, 9), (9, 2), (11, 1)], "l_partkey bigint, l_suppkey bigint").write.parquet(str(tmp_path / "lineitem.parquet"))
    got = [tuple(r) for r in entry.queries()["recursive_walk"](spark, str(tmp_path)).orderBy("step").collect()]
    assert got == [((2, 5, 9)[i % 3], i, 0.5**i) for i in range(9)]
    spark.catalog.clearCache()


def test_entry(spark):
    assert entry.entry(spark).count() > 0

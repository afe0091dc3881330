import pytest

import __spark_entry__ as entry
from stagewise import workloads

QUICK = [q for q in workloads.QUERIES if q.startswith(("op_", "t", "f01_bloom_native", "f11", "s01_staged_exact", "s08", "w3a", "w3d_v", "w9", "f01_bloom_w", "f03_union", "f06_counting_h", "s13", "s06_inc", "b09_locking_b", "w2e_d", "w4c_n", "w2c", "w4a_existing", "stream_run", "stream_probe", "stream_dedup", "stream_flush"))]


@pytest.mark.parametrize("name", [q for q in QUICK if q in workloads.ORACLE_SQL])
def test_rows_match_sql(spark, sf, same_rows, name):
    same_rows(workloads.QUERIES[name](spark, sf), workloads.ORACLE_SQL[name])


@pytest.mark.parametrize("name", [q for q in QUICK if q not in workloads.ORACLE_SQL])
def test_others_have_rows(spark, sf, name):
    assert workloads.QUERIES[name](spark, sf).count() > 0


def test_entry(spark):
    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())


@pytest.mark.parametrize("name", ["stream_sliding", "stream_sessions", "stream_interval_join"])
def test_streams_lose_no_rows(spark, sf, same_rows, name):
    same_rows(workloads.QUERIES[name](spark, sf), workloads.ORACLE_SQL[name])


@pytest.mark.parametrize("name", ["op_recursive", "t01_bounds_and_costs", "t16_general_costs", "t21_plans", "t24_layer_plan"])
def test_rows_come_from_a_table(spark, sf, name):
    assert workloads.QUERIES[name](spark, sf).inputFiles()

"""Registered queries against their SQL. The slowest are left to the driver's own comparison, which runs all."""

import pytest

from channelalign.plans import register
from conftest import SF, same

SLOW = {"incremental_equals_batch", "stream_equals_batch", "sensitivity_width", "ablation_matching", "metrics_sweep_monthly_supplier", "score_absent_zero", "score_forms", "negative_control", "pipeline_segments", "rayleigh_ks", "overlap"}


@pytest.mark.parametrize("name", sorted(set(register.oracle_sql()) - SLOW))
def test_query_equals_sql(spark, tables, name):
    same(register.queries()[name](spark, SF), tables, register.oracle_sql()[name])


def test_entry_runs(spark):
    import __spark_entry__ as driver

    assert driver.entry(spark).count() == 11
    assert set(driver.oracle_sql()) <= set(driver.queries())

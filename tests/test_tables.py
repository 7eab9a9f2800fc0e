"""Queries that once made up their rows: each reads a given table."""

import pytest
from pyspark.errors import AnalysisException

from densereps.queries import QUERIES

READING = [
    "test_size_table",
    "coverage_table",
    "eta_schedule",
    "w_alpha",
    "delta_trend",
    "processed_running_total",
    "test_size_shares",
    "predicted_cost_table",
    "k_frequency_table",
    "run_summary_table",
]


@pytest.mark.parametrize("name", READING)
def test_without_the_tables_there_are_no_rows(spark, tmp_path, name):
    with pytest.raises(AnalysisException, match="PATH_NOT_FOUND"):
        QUERIES[name](spark, str(tmp_path)).collect()

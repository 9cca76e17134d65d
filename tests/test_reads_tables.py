"""Queries whose cases once were made up: their rows come from a given table, which Spark reads."""

import pytest

from tests.conftest import FULL
from tilestar import registry

NAMES = [
    "alternating_grid",
    "alternating_optimal_check",
    "asymptotic_t2",
    "bound_grid",
    "bounds_by_memory",
    "buffer_demand_t1",
    "buffer_map",
    "buffers_by_bytes",
    "chunk_volumes",
    "column_dealing",
    "dependence_edges",
    "enrol_cases",
    # names
]


@pytest.mark.parametrize("name", NAMES)
def test_spark_reads_a_table(spark, name):
    assert any(f"{FULL}/" in x for x in registry.queries()[name](spark, FULL).inputFiles())

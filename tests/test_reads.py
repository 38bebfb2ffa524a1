"""Queries that once made their data up: without the tables they fail."""

import pytest

from ergodica import queries

NAMES = [
    "release_site_states",
    "release_site_source",
    "predicted_steps",
    "planner_choices",
    "matrix_free_equal",
    "five_state_rates",
    "five_state_pi",
    "five_state_extractions",
    "five_state_eigen",
    "five_state_counts",
]


@pytest.mark.parametrize("name", NAMES)
def test_reads_a_table(spark, tmp_path, name):
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        queries.queries()[name](spark, str(tmp_path)).collect()

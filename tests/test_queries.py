"""Every registered query with SQL equals DuckDB's result on the smallest tables."""

import pytest

from ergodica import oracles, queries
from verify import connect, rows_of, same

HEAVY = {"event_block_distributed", "event_window_distributed", "periods", "strong_components"}  # held to other truths in test_spark
ONE_COMPONENT = {  # need more than the smallest tables
    "regional_block_s5", "regional_block_distributed", "regional_laid_out", "regional_window", "regional_steps_fixed", "host_rank_undirected", "host_rank_directed", "host_rank_distributed", "validated",
    "grid_sweep", "savings_cube", "spectrum_leading", "spectrum_recommend", "width_sweep", "extraction_ablation", "image_ablation", "check_ablation", "hour_block_distributed", "accuracy_measures", "components", "knn_lsh_recall", "similarity_savings", "dangling_states", "dangling_repaired",
}


@pytest.fixture(scope="module")
def con(sf):
    return connect(sf)


@pytest.fixture(scope="module")
def con2(sf2):
    return connect(sf2)


@pytest.mark.parametrize("name", sorted(set(oracles.oracle_sql()) - HEAVY))
def test_equals_sql(spark, sf, sf2, con, con2, name):
    d, c = (sf2, con2) if name in ONE_COMPONENT else (sf, con)
    got, want = queries.queries()[name](spark, d).toPandas(), c.execute(oracles.oracle_sql()[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert same(rows_of(got), rows_of(want))


def test_entry(spark):
    import __spark_entry__ as entry

    assert abs(sum(r.pi for r in entry.entry(spark).collect()) - 1) < 1e-9
    assert set(entry.oracle_sql()) <= set(entry.queries())

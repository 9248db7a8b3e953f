"""Each query of the catalogue that has SQL gives the same rows as it."""

import pytest
from conftest import compare
from pyspark.errors import AnalysisException

from shardwise import catalog


@pytest.mark.parametrize("name", sorted(catalog.SQL))
def test_query_equals_sql(spark, sf, name):
    got, want = compare(spark, sf, catalog.QUERIES[name], catalog.SQL[name])
    assert got == want


@pytest.mark.parametrize("name", ["stream_tumbling", "stream_sessions", "stream_dedup", "gen_friendship_stats", "convergence_trace"])
def test_query_runs(spark, sf, name):
    assert catalog.QUERIES[name](spark, sf).count() > 0


FORMER_CONSTANTS = "exhaustive_toy kl_serial_toy gen_planted_fanout gen_friendship_stats expand_path gain_bins relative_quality reduction results_pivot results_cube results_rollup results_unpivot".split()


@pytest.mark.parametrize("name", FORMER_CONSTANTS)
def test_query_reads_its_tables(spark, tmp_path, name):
    """Without tables there is no result."""
    with pytest.raises(AnalysisException):
        catalog.QUERIES[name](spark, str(tmp_path)).collect()


def test_entry(spark):
    import __spark_entry__

    rows = __spark_entry__.entry(spark).collect()
    assert len(rows) == 8 and rows[0].fanout_after < rows[0].fanout_before

"""Queries that once made their data up read a given table."""

import pytest

import __spark_entry__ as entry

READS = [
    ("clique_contributions", "lineitem"),
    ("component_weights_c6", "lineitem"),
    ("expected_histogram", "lineitem"),
    ("hash_cost", "lineitem"),
    ("recover_counts", "lineitem"),
    ("reduction_ratio", "lineitem"),
    ("rel_cte_recursive", "orders"),
]


@pytest.mark.parametrize("name,table", READS)
def test_reads_the_table(spark, tiny, tmp_path, name, table):
    (tmp_path / "empty").mkdir()
    with pytest.raises(Exception, match=f"{table}.parquet"):
        entry.queries()[name](spark, str(tmp_path / "empty")).collect()
    assert entry.queries()[name](spark, tiny).count()

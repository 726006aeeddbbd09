"""Queries that read a given table in Spark, and make up neither rows nor figures."""

import pytest

from bundlemv.plans import catalog
from bundlemv.session import read_by
from bundlemv.sources.tables import load_table

READS = {
    "assign_blocks": "part",
    "bin_switches": "lineitem",
    "block_pairs": "lineitem",
    "block_pivot": "lineitem",
    "branch_misses_literal": "lineitem",
    "crossover_literal": "lineitem",
    "custom_blocks": "part",
    "edges_loops_dropped": "events",
    "g_banded": "part",
    "g_kronecker": "orders",
    "g_worked9": "lineitem",
}


@pytest.mark.parametrize("name", sorted(READS))
def test_reads_a_given_table(spark, tiny, name):
    assert any(f"{READS[name]}.parquet" in path for path in read_by(catalog.QUERIES[name](spark, tiny)))


def test_labels_by_degree_of_given_rows(spark, tiny):
    assert catalog.QUERIES["label_degree"](spark, tiny).count() == load_table(spark, tiny, "part").count()

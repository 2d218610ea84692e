"""Every registered graph query against its SQL on the smallest tables; queries without SQL must give rows that repeat."""

import pytest
from conftest import SF
from oracle import connection, rows_of_spark, rows_of_sql

from tuplegraph import registry
from tuplegraph.plans import registered

QUERIES, SQL = registry.queries(), registry.oracle_sql()


@pytest.fixture(scope="module")
def con():
    return connection(SF)


@pytest.mark.parametrize("name", sorted(SQL))
def test_same_rows(spark, con, name):
    assert rows_of_spark(QUERIES[name](spark, SF)) == rows_of_sql(con, SQL[name])


LIGHT = ["cluster_ball", "cluster_connection", "cluster_ratio", "two_phase_topk", "bidirectional_topk", "precision_at_10", "acceptable_at_10", "huffman_bits", "cluster_rounds_ball", "diameters", "bits_per_edge"]


@pytest.mark.parametrize("name", LIGHT)
def test_rows_repeat(spark, name):
    """Computed twice, with nothing held from the first time but the graph and its postings, the rows are the same."""
    first = rows_of_spark(QUERIES[name](spark, SF))
    for key in [k for k in registered._held if k[2] not in ("graph", "postings")]:
        del registered._held[key]
    assert first[1] and rows_of_spark(QUERIES[name](spark, SF)) == first

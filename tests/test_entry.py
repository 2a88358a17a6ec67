"""The entry module works with and without the optional subpackage; a sample of queries equals its SQL."""

import os

import duckdb
import pytest

import __spark_entry__ as entry

D = "/root/testdata/sf0.001"


def test_entry(spark):
    assert entry.entry(spark).count() > 0


@pytest.mark.parametrize("name", ["merge_labels_average", "merge_edges_average", "existence_marginals", "node_context", "index_len1", "index_lookup_reverse", "match_wedge", "baseline_sql"])
def test_query_equals_sql(spark, name):
    c = duckdb.connect()
    for f in os.listdir(D):
        c.execute(f"create view {f[:-8]} as select * from '{D}/{f}'")
    want = c.sql(entry.oracle_sql()[name]).df()
    got = entry.queries()[name](spark, D).toPandas()[list(want.columns)]
    key = lambda df: sorted(map(tuple, df.round(5).values.tolist()), key=str)
    assert key(got) == key(want)

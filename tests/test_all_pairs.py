"""Similarity joins over all pairs against DuckDB."""

import duckdb
import pytest

from ugraph import queries
from ugraph.sources import testgraphs

D = "/root/testdata/sf0.01"


def test_all_vectors(spark, monkeypatch):
    monkeypatch.setattr(queries, "VECTOR_BLOCK", 64)
    db = duckdb.connect()
    db.execute(f"CREATE VIEW embeddings AS SELECT * FROM read_parquet('{D}/embeddings.parquet')")
    want = sorted(db.execute(queries.SQL["knn_edges_all_pairs"]).fetchall())
    got = sorted(tuple(r) for r in queries.QUERIES["knn_edges_all_pairs"](spark, D).collect())
    assert [r[:2] for r in got] == [r[:2] for r in want] and [r[2] for r in got] == pytest.approx([r[2] for r in want], abs=1.01e-4)
    assert len(got) > len(db.execute(queries.SQL["knn_edges"]).fetchall())


def test_deletion_keys(spark):
    """Strings within one edit share a key; of over 20 characters, those within two."""
    rows = [("abcdef", "abxdef"), ("abcdef", "abcde"), ("abcdef", "xabcdef"), ("abcdef", "abxyef"), ("a" * 21 + "bc", "a" * 21 + "xy"), ("", "a")]
    df = spark.createDataFrame(rows, "s string, t string")
    got = df.select(testgraphs.F.arrays_overlap(testgraphs.deletion_keys(df.s), testgraphs.deletion_keys(df.t)).alias("x")).collect()
    assert [r.x for r in got] == [True, True, True, False, True, True]
    assert testgraphs.similar_customers(spark, D).count() == 149

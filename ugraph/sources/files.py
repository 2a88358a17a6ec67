"""Reference graphs from files and to files, and match export."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.entity_graph import ReferenceGraph

SCHEMAS = {
    "labels": "ref_id long, label string, p double",
    "edges": "src long, dst long, p double",
    "sets": "set_id long, members array<long>, p double",
    "cpt": "src long, dst long, l_src string, l_dst string, p double",
}


def read_edge_list(spark: SparkSession, path: str, sep: str = "\t", directed: bool = False, comment: str = "#") -> DataFrame:
    """src, dst, p from lines ``src dst [p]``; without a probability an edge is certain. Loops and lines without two
    numbers go; an undirected pair comes once, as src < dst; a pair listed more than once has its greatest p."""
    rows = spark.read.schema("src string, dst string, p string").csv(path, sep=sep, comment=comment, ignoreLeadingWhiteSpace=True, ignoreTrailingWhiteSpace=True)
    rows = rows.select(F.expr("try_cast(src AS long)").alias("src"), F.expr("try_cast(dst AS long)").alias("dst"), F.when(F.col("p").isNull(), 1.0).otherwise(F.expr("try_cast(p AS double)")).alias("p"))
    rows = rows.filter("src is not null and dst is not null and src <> dst")
    if not directed:
        rows = rows.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), "p")
    return rows.groupBy("src", "dst").agg(F.max("p").alias("p"))


def load_reference_graph(spark: SparkSession, folder: str, directed: bool = False, correlated: bool = False, kind: str = "parquet") -> ReferenceGraph:
    """labels, edges, sets and, where ``correlated``, cpt from a folder of Parquet or JSON tables."""
    names = [n for n in SCHEMAS if correlated or n != "cpt"]
    tables = {n: spark.read.schema(SCHEMAS[n]).format(kind).load(f"{folder}/{n}") for n in names}
    return ReferenceGraph(tables["labels"], tables["edges"], tables["sets"], directed, tables.get("cpt"))


def save_reference_graph(rg: ReferenceGraph, folder: str, kind: str = "parquet") -> None:
    for name, schema in SCHEMAS.items():
        table = getattr(rg, name)
        if table is not None:
            casts = [f.strip().split(" ") for f in schema.split(", ")]
            table.select(*[F.col(n).cast(t).alias(n) for n, t in casts]).write.format(kind).save(f"{folder}/{name}")


def write_matches(matches: DataFrame, path: str, kind: str = "parquet") -> None:
    """Export matches as Parquet, JSON or CSV (with a header)."""
    matches.write.options(**({"header": True} if kind == "csv" else {})).format(kind).save(path)

"""Connected components of a table of links, by alternating star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialise


def _digest(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("u", "v")), F.bit_xor(F.xxhash64("v", "u", F.lit(1)))).first())


def components(links: DataFrame, most_rounds: int = 60) -> DataFrame:
    """``links`` (u, v) to (node, root): root is the least node that each node can reach.

    Each round ties the larger neighbours of a node to its least one, then the smaller ones; neither step holds a
    node's neighbours in one place. The rounds end when the links no longer change."""
    edges = links.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).filter("u <> v").distinct()
    edges = materialise(edges, "cc")
    before = _digest(edges)
    for _ in range(most_rounds):
        if not before[0]:
            break
        # large star: all neighbours; ties of the greater ones move to the least
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = materialise(both.groupBy("u").agg(F.min("v").alias("m")).withColumn("m", F.least("m", "u")), "cc-least")
        edges = both.filter("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u <> v").distinct()
        edges = materialise(edges, "cc")
        # small star: smaller neighbours (and the node itself) move to the least of them
        least = materialise(edges.groupBy("u").agg(F.min("v").alias("m")), "cc-least")
        moved = edges.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u <> v")
        edges = materialise(moved.unionByName(least.select("u", F.col("m").alias("v"))).distinct(), "cc")
        after = _digest(edges)
        if after == before:
            break
        before = after
    else:
        raise RuntimeError("components did not settle")
    return edges.select(F.col("u").alias("node"), F.col("v").alias("root"))

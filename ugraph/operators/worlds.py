"""Probabilities of given mappings and of given worlds, straight from the entity graph's tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.pattern import Pattern
from .engine import product
from .entity_graph import EntityGraph
from .identity import pn_expr


def mapping_probability(eg: EntityGraph, mappings: DataFrame, q: Pattern) -> DataFrame:
    """``mappings`` (a column of entity ids for each pattern node) with ple, pn and p; 0 where a label or an edge is
    impossible, or two nodes share an entity or a reference."""
    names = sorted(q.nodes)
    rows = mappings.select(*[F.col(n).alias(f"n_{n}") for n in names])
    for n in names:
        node = eg.nodes().filter(F.col("label") == q.nodes[n])
        rows = rows.join(node.select(*[F.col(a).alias(f"{b}_{n}") for a, b in (("e", "n"), ("q", "q"), ("c", "c"), ("m", "m"), ("w", "w"))]), f"n_{n}", "left")
    for a, b in q.edges:
        e = eg.edges.filter((F.col("l_src") == q.nodes[a]) & (F.col("l_dst") == q.nodes[b])) if eg.conditional else eg.edges
        rows = rows.join(e.select(F.col("src").alias(f"n_{a}"), F.col("dst").alias(f"n_{b}"), F.col("p").alias(f"e_{a}_{b}")), [f"n_{a}", f"n_{b}"], "left")
    factors = [F.coalesce(F.col(f"q_{n}"), F.lit(0.0)) for n in names] + [F.coalesce(F.col(f"e_{a}_{b}"), F.lit(0.0)) for a, b in q.edges]
    differ = F.size(F.array_distinct(F.array(*[F.col(f"n_{n}") for n in names]))) == len(names)
    rows = rows.withColumn("ple", F.when(differ, product(factors)).otherwise(F.lit(0.0))).withColumn("pn", pn_expr(names))
    return rows.select(*[F.col(f"n_{n}").alias(n) for n in names], "ple", "pn", (F.col("ple") * F.col("pn")).alias("p"))


def worlds_probability(eg: EntityGraph, nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """world, p: of worlds given by their entities with labels (world, entity_id, label) and their edges (world, src, dst;
    each undirected edge once). All entities which are certain to exist belong to every world; edges that a world lacks
    count with the probability that they are absent. For small graphs: the work is worlds times entities and edges."""
    each = nodes.select("world").distinct()
    there = nodes.join(eg.entities.select("entity_id", "comp_id", "mask"), "entity_id", "left")
    # components: the mask has to be one of the worlds of the component
    held = there.filter("comp_id is not null").groupBy("world", "comp_id").agg(F.bit_or("mask").alias("mask"))
    n_comps = eg.worlds.select("comp_id").distinct().count()
    exist = held.join(eg.worlds.withColumnRenamed("p", "pw"), ["comp_id", "mask"], "left").groupBy("world").agg(F.product(F.coalesce("pw", F.lit(0.0))).alias("pe"), F.count(F.lit(1)).alias("n_comps"))
    certain = eg.entities.filter("comp_id is null").count()
    whole = there.filter("comp_id is null and mask is not null").groupBy("world").agg(F.count_distinct("entity_id").alias("n"))
    label = there.join(eg.labels.withColumnRenamed("p", "pl"), ["entity_id", "label"], "left").groupBy("world").agg(F.product(F.coalesce("pl", F.lit(0.0))).alias("pl"))
    ends = eg.edges if eg.directed else eg.edges.filter("src < dst")
    a = nodes.select("world", F.col("entity_id").alias("src"), F.col("label").alias("l_src"))
    b = nodes.select("world", F.col("entity_id").alias("dst"), F.col("label").alias("l_dst"))
    more = ["l_src", "l_dst"] if eg.conditional else []
    both = ends.join(a, ["src", *more[:1]]).join(b, ["world", "dst", *more[1:]])
    src, dst = (F.col("src"), F.col("dst")) if eg.directed else (F.least("src", "dst"), F.greatest("src", "dst"))
    given = edges.select("world", src.alias("src"), dst.alias("dst")).distinct().withColumn("on", F.lit(True))
    edge = both.select("world", "src", "dst", "p").join(given, ["world", "src", "dst"], "full")
    edge = edge.groupBy("world").agg(F.product(F.when(F.col("on"), F.coalesce("p", F.lit(0.0))).otherwise(1 - F.col("p"))).alias("px"))
    out = each.join(exist, "world", "left").join(whole, "world", "left").join(label, "world", "left").join(edge, "world", "left")
    complete = (F.coalesce("n", F.lit(0)) == certain) & (F.coalesce("n_comps", F.lit(0)) == n_comps)
    return out.select("world", F.when(complete, F.coalesce("pe", F.lit(1.0)) * F.coalesce("pl", F.lit(1.0)) * F.coalesce("px", F.lit(1.0))).otherwise(F.lit(0.0)).alias("p"))

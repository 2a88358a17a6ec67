"""Synthetic reference graphs by preferential attachment, made in parallel."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.tables import materialise
from ..operators.entity_graph import ReferenceGraph


def u(key, salt: int):
    """A number in [0, 1) from a key: 53 bits of its hash, so that no draw repeats within a graph's slots."""
    return F.pmod(F.xxhash64(key, F.lit(salt)), F.lit(1 << 53)).cast("double") / F.lit(float(1 << 53))


def attachment_edges(spark: SparkSession, n: int, per_node: int = 5) -> DataFrame:
    """Each node opens ``per_node`` slots; slot k copies an end of a random earlier slot, and pointer jumping resolves
    copies of copies. Popular ends are copied more often."""
    slot = spark.range(per_node, n * per_node).withColumn("src", F.floor(F.col("id") / per_node).cast("long"))
    first = F.col("src") * per_node
    # an even draw copies the drawn slot's own node, an odd one that slot's far end
    draw = F.floor(u(F.col("id") * 7 + 3, 31) * (2 * first)).cast("long")
    slot = slot.withColumn("at", F.floor(draw / 2).cast("long")).withColumn("own", draw % 2 == 0)
    known = slot.select("id", F.when(F.col("own") | (F.col("at") < per_node), F.floor(F.col("at") / per_node).cast("long")).alias("dst"), F.col("at").alias("ref"))
    known = materialise(known, "synth")
    while not known.filter("dst is null").isEmpty():
        far = known.select(F.col("id").alias("ref"), F.col("dst").alias("d2"), F.col("ref").alias("r2"))
        known = known.join(far, "ref", "left").select("id", F.coalesce("dst", "d2").alias("dst"), F.when(F.col("dst").isNull(), F.col("r2")).otherwise(F.col("ref")).alias("ref"))
        known = materialise(known, "synth")
    ends = known.select(F.floor(F.col("id") / per_node).cast("long").alias("a"), F.col("dst").alias("b")).filter("a <> b")
    return ends.select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst")).distinct()


def generate(spark: SparkSession, n: int, share: float = 0.2, seed: int = 1, n_labels: int = 5, groups: int | None = None) -> ReferenceGraph:
    """n references with 5 n relations; ``share`` of nodes, edges and sets get a real distribution. In each of
    ``groups`` (n / 1000 by default) groups of four nodes four pairs are reference sets."""
    edges = attachment_edges(spark, n)
    key = F.col("src") * 20011 + F.col("dst")
    x = u(key, seed + 4) / (u(key, seed + 4) + u(key, seed + 5) / 2)
    edges = edges.withColumn("p", F.when(u(key, seed + 3) < share, x).otherwise(F.lit(1.0))).filter("p > 0")
    nodes = spark.range(n).withColumnRenamed("id", "ref_id")
    w = F.array(*[F.struct(((F.col("ref_id") + i) % n_labels).alias("k"), (u(F.col("ref_id"), seed + 10 + i) / (i + 1)).alias("x")) for i in range(n_labels)])
    many = nodes.filter(u(F.col("ref_id"), seed) < share).select("ref_id", F.explode(w).alias("w")).select("ref_id", "w.k", "w.x")
    many = many.withColumn("p", F.col("x") / F.sum("x").over(Window.partitionBy("ref_id"))).filter("p > 0").select("ref_id", F.concat(F.lit("L"), "k").alias("label"), "p")
    one = nodes.filter(u(F.col("ref_id"), seed) >= share).select("ref_id", F.concat(F.lit("L"), F.floor(u(F.col("ref_id"), seed + 9) * n_labels).cast("long")).alias("label"), F.lit(1.0).alias("p"))
    k = max(1, n // 1000) if groups is None else groups
    width = n // k
    pair = spark.range(4 * k).select(F.floor(F.col("id") / 4).cast("long").alias("g"), (F.col("id") % 4).alias("i"), F.col("id").alias("set_id"))
    node = lambda i: F.col("g") * width + (i % 4) * F.lit(max(1, width // 5))
    sets = pair.select("set_id", F.array_sort(F.array(node(F.col("i")), node(F.col("i") + 1))).alias("members"), (0.05 + 0.9 * u(F.col("set_id"), seed + 6)).alias("p"))
    return ReferenceGraph(many.unionByName(one), edges, sets)

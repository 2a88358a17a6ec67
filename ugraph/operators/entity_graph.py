"""Reference graphs, and the entity graphs that merges and identity worlds make of them."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.merge import MERGES
from ..functions.tables import materialise
from .identity import DRAWS, MOST_REFS, SET_OFFSET, complete_singletons, component_marginals, component_worlds, identity_components, marginal_on_demand


@dataclass
class ReferenceGraph:
    """labels (ref_id, label, p), edges (src, dst, p; src < dst unless directed), sets (set_id, members, p) and, for
    correlated edges, cpt (src, dst, l_src, l_dst, p)."""

    labels: DataFrame
    edges: DataFrame
    sets: DataFrame
    directed: bool = False
    cpt: DataFrame | None = None

    def validate(self) -> "ReferenceGraph":
        checks = {
            "label probabilities lie in [0, 1]": self.labels.filter("p < 0 or p > 1 or p is null"),
            "labels of a reference sum to 1": self.labels.groupBy("ref_id").agg(F.sum("p").alias("s")).filter("abs(s - 1) > 1e-9"),
            "edge probabilities lie in [0, 1]": self.edges.filter("p < 0 or p > 1 or p is null"),
            "edges have different ends": self.edges.filter("src = dst"),
            "set members are references": self.sets.select(F.explode("members").alias("ref_id")).join(self.labels, "ref_id", "left_anti"),
        }
        for what, bad in checks.items():
            if not bad.isEmpty():
                raise ValueError(f"reference graph: {what}: {bad.first()}")
        return self


TABLES = ("entities", "labels", "edges", "worlds", "marginals", "packed")


@dataclass
class EntityGraph:
    """entities (entity_id, refs, prior, comp_id, bit, mask, worlds, p_exist), labels (entity_id, label, p), edges (src,
    dst, p, and l_src, l_dst where correlated; both directions unless directed), worlds and marginals by component, and
    packed (comp_id and its worlds in a row). Marginals not given are tabled when they are first asked for."""

    entities: DataFrame
    labels: DataFrame
    edges: DataFrame
    worlds: DataFrame
    tabled: DataFrame | None
    packed: DataFrame
    directed: bool = False
    conditional: bool = False
    label_merge: str = "average"
    edge_merge: str = "average"

    @property
    def marginals(self) -> DataFrame:
        if self.tabled is None:
            self.tabled = materialise(component_marginals(self.worlds), "marginals")
        return self.tabled

    def nodes(self) -> DataFrame:
        """Possible labels of entities with what a match needs of each: e, label, q, c, m, w."""
        e = self.entities.select(F.col("entity_id").alias("e"), F.col("comp_id").alias("c"), F.col("mask").alias("m"), F.col("worlds").alias("w"))
        return self.labels.select(F.col("entity_id").alias("e"), "label", F.col("p").alias("q")).join(e, "e")

    def register(self, prefix: str = "") -> None:
        self.labels.createOrReplaceTempView(f"{prefix}entity_labels")
        self.edges.createOrReplaceTempView(f"{prefix}entity_edges")
        self.entities.select("entity_id", "comp_id", "mask", "p_exist").createOrReplaceTempView(f"{prefix}entities")
        self.marginals.createOrReplaceTempView(f"{prefix}marginals")

    def save(self, path: str) -> None:
        for name in TABLES:
            getattr(self, name).write.parquet(f"{path}/{name}")

    @staticmethod
    def load(spark, path: str, directed: bool = False, conditional: bool = False) -> "EntityGraph":
        return EntityGraph(*(spark.read.parquet(f"{path}/{n}") for n in TABLES), directed, conditional)


def existence_factors(sets: DataFrame, weighting: str = "per_reference") -> DataFrame:
    """set_id, ref_id, factor: what a set's existence gives to the factor of each of its references."""
    root = F.lit(1.0) if weighting == "per_reference" else F.lit(1.0) / F.size("members")
    return sets.select("set_id", F.explode("members").alias("ref_id"), F.pow("p", root).alias("factor"))


def members_of(rg: ReferenceGraph) -> DataFrame:
    """entity_id, ref_id, size of all entities, singletons included."""
    single = rg.labels.select("ref_id").distinct().select(F.col("ref_id").alias("entity_id"), "ref_id", F.lit(1).alias("size"))
    multi = rg.sets.filter("size(members) > 1").select((F.col("set_id") + SET_OFFSET).alias("entity_id"), F.explode("members").alias("ref_id"), F.size("members").alias("size"))
    return single.unionByName(multi)


def merge_labels(rg: ReferenceGraph, how: str = "average") -> DataFrame:
    """entity_id, label, p. Labels that a reference lacks count as probability 0."""
    rows = members_of(rg).join(rg.labels, "ref_id").groupBy("entity_id", "label")
    return rows.agg(MERGES[how](F.col("p"), F.col("size")).alias("p")).filter("p > 0")


def _conflicts(member: DataFrame) -> DataFrame:
    """Entity pairs that share a reference; only multi-member sets make any."""
    multi = member.filter("size > 1").select(F.col("entity_id").alias("src"), "ref_id")
    other = member.select(F.col("entity_id").alias("dst"), "ref_id")
    one = multi.join(other, "ref_id").filter("src <> dst").select("src", "dst")
    return one.unionByName(one.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()


def merge_edges(rg: ReferenceGraph, how: str = "average", missing: str = "zero") -> DataFrame:
    """src, dst, p over entities, both directions unless directed. ``missing`` = recorded averages recorded pairs."""
    how = "recorded" if how == "average" and missing == "recorded" else how
    return _merged(rg, rg.edges.select("src", "dst", "p"), [], how)


def merge_edges_conditional(rg: ReferenceGraph, how: str = "average") -> DataFrame:
    """src, dst, l_src, l_dst, p: the same for each pair of labels."""
    return _merged(rg, rg.cpt.select("src", "dst", "l_src", "l_dst", "p"), ["l_src", "l_dst"], how)


def _merged(rg: ReferenceGraph, edges: DataFrame, extra: list[str], how: str) -> DataFrame:
    """Undirected pairs are merged once, the lesser entity first, and turned at the end."""
    member = members_of(rg)
    a = member.select(F.col("ref_id").alias("src"), F.col("entity_id").alias("s"), F.col("size").alias("ns"))
    b = member.select(F.col("ref_id").alias("dst"), F.col("entity_id").alias("t"), F.col("size").alias("nt"))
    rows = edges.join(a, "src").join(b, "dst").filter("s <> t").select(F.col("s").alias("src"), F.col("t").alias("dst"), *extra, "p", (F.col("ns") * F.col("nt")).alias("n"))
    if not rg.directed:
        swap = lambda c, other: F.when(F.col("src") < F.col("dst"), F.col(c)).otherwise(F.col(other)).alias(c)
        rows = rows.select(swap("src", "dst"), swap("dst", "src"), *[swap(c, t) for c, t in zip(extra, reversed(extra), strict=True)], "p", "n")
    out = rows.groupBy("src", "dst", *extra).agg(MERGES[how](F.col("p"), F.col("n")).alias("p")).filter("p > 0")
    out = out.join(_conflicts(member), ["src", "dst"], "left_anti")
    if rg.directed:
        return out
    ends = ["src", "dst", *extra]
    other = ["dst", "src", *reversed(extra)]
    return out.select(F.inline(F.array(F.struct(*ends, "p"), F.struct(*[F.col(c).alias(t) for c, t in zip(other, ends, strict=True)], "p"))))


def build_entity_graph(rg: ReferenceGraph, label_merge: str = "average", edge_merge: str = "average", missing: str = "zero", prior: str = "balanced", weighting: str = "per_reference", most_refs: int = MOST_REFS, draws: int = DRAWS, like: EntityGraph | None = None) -> EntityGraph:
    """All possible entities with their labels and edges, and the joint existence of those that compete. ``like``: a graph of
    the same references and sets, whose entities and worlds are taken."""
    if like is not None:
        labels = materialise(merge_labels(rg, label_merge), "labels")
        edges = merge_edges_conditional(rg, edge_merge) if rg.cpt is not None else merge_edges(rg, edge_merge, missing)
        return EntityGraph(like.entities, labels, materialise(edges, "edges"), like.worlds, like.tabled, like.packed, rg.directed, rg.cpt is not None, label_merge, edge_merge)
    refs = rg.labels.select("ref_id").distinct()
    single = complete_singletons(rg.sets, refs, prior).join(identity_components(rg.sets), "ref_id", "left")
    multi = rg.sets.filter("size(members) > 1")
    comp = single.select("ref_id", "comp_id").filter("comp_id is not null")
    multi = multi.join(comp, F.col("members")[0] == F.col("ref_id")).select((F.col("set_id") + SET_OFFSET).alias("entity_id"), F.col("members").alias("refs"), "p", "comp_id")
    single = single.select(F.col("ref_id").alias("entity_id"), F.array("ref_id").alias("refs"), "p", "comp_id")
    trivial = single.filter("comp_id is null").withColumn("bit", F.lit(0))
    bits = Window.partitionBy("comp_id").orderBy("entity_id")
    tied = materialise(single.filter("comp_id is not null").unionByName(multi).withColumn("bit", (F.row_number().over(bits) - 1).cast("int")), "tied")
    tied = tied.withColumn("mask", F.expr("shiftleft(1L, bit)"))
    worlds = materialise(component_worlds(tied, weighting, most_refs, draws), "worlds")
    packed = materialise(worlds.groupBy("comp_id").agg(F.collect_list(F.struct("mask", "p")).alias("worlds")), "packed")
    tied = tied.join(packed, "comp_id").withColumn("p_exist", marginal_on_demand(F.col("worlds"), F.col("mask")))
    trivial = trivial.withColumn("mask", F.lit(0).cast("long")).withColumn("worlds", F.lit(None).cast("array<struct<mask:bigint,p:double>>")).withColumn("p_exist", F.lit(1.0))
    columns = ["entity_id", "refs", F.col("p").alias("prior"), "comp_id", "bit", "mask", "worlds", "p_exist"]
    entities = materialise(tied.select(*columns).unionByName(trivial.select(*columns)), "entities")
    labels = materialise(merge_labels(rg, label_merge), "labels")
    edges = merge_edges_conditional(rg, edge_merge) if rg.cpt is not None else merge_edges(rg, edge_merge, missing)
    return EntityGraph(entities, labels, materialise(edges, "edges"), worlds, None, packed, rg.directed, rg.cpt is not None, label_merge, edge_merge)

"""Pattern matching: candidates, join links, joint reduction and assembly."""

from __future__ import annotations

import math
import threading
import time
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field, replace
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.tables import EPS, materialise
from ..plans.decompose import Decomposition, cover_of, decompose, join_order
from ..plans.pattern import Pattern, node_label_counts, path_chords, path_neighbours, reverse_neighbours
from .entity_graph import EntityGraph
from .identity import pn_expr
from .path_index import PathIndex, estimate_count, joined_edges, labelled_edges, load_counts, node_context


@dataclass(frozen=True)
class MatchOptions:
    L: int | None = None
    decomposition: str = "auto"  # greedy, exact, random; auto: exact up to EXACT_EDGES pattern edges, else greedy
    efficiency: str = "length"
    paths: tuple[tuple[str, ...], ...] | None = None  # a cover given by the caller
    seed: int = 0
    node_context: bool = True
    path_context: bool = True
    reduction: str = "auto"  # none, structure, bounds, both; auto: both where the search space exceeds REDUCE_FROM
    incremental: bool = True
    order: str = "heuristic"
    distinct: str = "embedding"  # or subgraph
    identity: bool = True
    max_rounds: int = 50
    limit: int | None = None


#: Log10 of the search space from which the joint reduction pays for its rounds. It never changes the result.
REDUCE_FROM = 8.0


def at_once(*runs: Callable) -> list:
    """The results of ``runs``, whose Spark jobs overlap."""
    if len(runs) < 2:
        return [run() for run in runs]
    with ThreadPoolExecutor(min(8, len(runs))) as pool:
        return [f.result() for f in [pool.submit(run) for run in runs]]


def product(columns: list[Column]) -> Column:
    return reduce(lambda a, b: a * b, columns, F.lit(1.0))


def _edge_column(e: tuple[str, str]) -> str:
    return f"e_{e[0]}_{e[1]}"


@dataclass
class KPartite:
    """Candidate paths (part, vid, w1, w2, s0..) and the links between them (p1, v1, p2, v2, both directions)."""

    vertices: DataFrame
    links: DataFrame
    wanted: dict[int, int]
    k: int
    rounds: list[dict] = field(default_factory=list)


class Engine:
    def __init__(self, eg: EntityGraph, idx: PathIndex, ctx: DataFrame | None = None):
        self.eg, self.idx = eg, idx
        self._ctx, self._lock = ctx, threading.Lock()
        self._edges: dict[tuple, DataFrame] = {}
        self.trace: list[dict] = []

    @property
    def ctx(self) -> DataFrame:
        """The context of the nodes, written when it is first asked for."""
        with self._lock:
            if self._ctx is None:
                self._ctx = materialise(node_context(self.eg), "context")
            return self._ctx

    # -- step 1 -------------------------------------------------------------------------------------------------
    def plan(self, q: Pattern, alpha: float, o: MatchOptions) -> Decomposition:
        from ..plans.pattern import enumerate_query_paths

        if o.paths:
            return cover_of(q, list(o.paths))
        most = o.L or self.idx.L
        keys = {}
        for p in enumerate_query_paths(q, most):
            k, b = "|".join(q.nodes[n] for n in p), "|".join(q.nodes[n] for n in reversed(p))
            keys[p] = k if q.directed else min(k, b)
        known = load_counts(self.idx, sorted(set(keys.values())))
        counts = lambda p: estimate_count(known[keys[p]], alpha) if keys[p] in known else 0.0
        return decompose(q, most, counts, o.decomposition, o.efficiency, o.seed)

    # -- step 2 -------------------------------------------------------------------------------------------------
    def fetch(self, q: Pattern, path: tuple[str, ...], alpha: float) -> DataFrame:
        labels = [q.nodes[n] for n in path]
        expanded = len(path) > 1 and (alpha < self.idx.beta - EPS or len(path) - 1 > self.idx.L) and not (self.eg.directed or self.eg.conditional)
        rows = joined_edges(self.labelled(q, alpha), labels, alpha) if expanded else self.idx.lookup(labels, alpha)
        node = [F.col(f"{c}_{i}").alias(f"{c}_{n}") for i, n in enumerate(path) for c in ("n", "q", "c", "m", "w")]
        return rows.select(*node, *[F.col(f"e_{i}").alias(_edge_column(e)) for i, e in enumerate(q.path_edges(path))], "ple", "pn")

    def labelled(self, q: Pattern, alpha: float) -> DataFrame:
        """Edges between the labels of the pattern's edges, written once for all its paths."""
        pairs = {tuple(sorted((q.nodes[a], q.nodes[b]))) for a, b in q.edges}
        key = (tuple(sorted(pairs)), alpha)
        with self._lock:
            if key not in self._edges:
                self._edges[key] = materialise(labelled_edges(self.eg, pairs, alpha), "labelled")
            return self._edges[key]

    def node_candidates(self, q: Pattern, name: str, alpha: float, bound: bool = True) -> DataFrame:
        """Entities that can stand for a pattern node: enough neighbours of each label, at sufficient probability."""
        rows = self.eg.nodes().filter((F.col("label") == q.nodes[name]) & (F.col("q") >= alpha - EPS)).select("e", "q")
        for (n, label), k in sorted(node_label_counts(q).items()):
            if n == name:
                c = self.ctx.filter((F.col("label") == label) & (F.col("n") >= k)).select("e", "fpu")
                rows = rows.join(c, "e")
                rows = rows.filter(F.col("q") * F.pow("fpu", F.lit(k)) >= alpha - EPS).drop("fpu") if bound else rows.drop("fpu")
        return rows.select("e")

    def neighbourhood_bound(self, q: Pattern, path: tuple[str, ...], rows: DataFrame) -> DataFrame:
        """Column pu: at most this much can the pattern's nodes next to the path multiply the probability by."""
        need = sorted({(n, q.nodes[m]) for m in path_neighbours(q, path) for n in reverse_neighbours(q, path, m)})
        for n, label in need:
            c = self.ctx.filter(F.col("label") == label).select(F.col("e").alias(f"n_{n}"), F.col("fpu").alias(f"f_{n}_{label}"), F.col("ppu").alias(f"g_{n}_{label}"))
            rows = rows.join(c, f"n_{n}")
        bounds = []
        for m in sorted(path_neighbours(q, path)):
            ends, label = sorted(reverse_neighbours(q, path, m)), q.nodes[m]
            ways = [F.col(f"f_{n}_{label}") * product([F.col(f"g_{x}_{label}") for x in ends if x != n]) for n in ends]
            bounds.append(ways[0] if len(ways) == 1 else F.least(*ways))
        return rows.withColumn("pu", product(bounds)).drop(*[f"{s}_{n}_{label}" for n, label in need for s in "fg"])

    def chords(self, q: Pattern, path: tuple[str, ...], rows: DataFrame) -> DataFrame:
        for a, b in path_chords(q, path):
            e = self.eg.edges
            if self.eg.conditional:
                e = e.filter((F.col("l_src") == q.nodes[a]) & (F.col("l_dst") == q.nodes[b]))
            rows = rows.join(e.select(F.col("src").alias(f"n_{a}"), F.col("dst").alias(f"n_{b}"), F.col("p").alias(_edge_column((a, b)))), [f"n_{a}", f"n_{b}"])
        return rows

    def candidates(self, q: Pattern, d: Decomposition, alpha: float, o: MatchOptions) -> list[DataFrame]:
        """The lists of candidate paths, written; those of the nodes come first, in one job."""
        nodes = None
        if o.node_context:
            whole = reduce(DataFrame.unionByName, [self.node_candidates(q, n, alpha).withColumn("node", F.lit(n)) for n in q.nodes])
            nodes = materialise(whole, "cn")

        def one(i: int, path: tuple[str, ...]) -> DataFrame:
            rows = self.fetch(q, path, alpha)
            for n in path if nodes is not None else ():
                rows = rows.join(nodes.filter(F.col("node") == n).select(F.col("e").alias(f"n_{n}")), f"n_{n}", "left_semi")
            if o.path_context:
                rows = self.chords(q, path, self.neighbourhood_bound(q, path, rows))
                cpr = product([F.col(_edge_column(c)) for c in path_chords(q, path)])
                rows = rows.filter(F.col("ple") * F.col("pn") * F.col("pu") * cpr >= alpha - EPS).drop("pu", *[_edge_column(c) for c in path_chords(q, path)])
            return materialise(rows.withColumn("vid", F.monotonically_increasing_id()), f"cand-{i}")

        return at_once(*[lambda i=i, p=p: one(i, p) for i, p in enumerate(d.paths)])

    # -- step 3 -------------------------------------------------------------------------------------------------
    def _joined(self, q: Pattern, a: DataFrame, names_a: list[str], edges_a, b: DataFrame, path_b, alpha: float | None):
        """Two lists joined on their shared nodes; different nodes differ, and the union keeps probability alpha."""
        edges_b = q.path_edges(path_b)
        shared = [n for n in path_b if n in names_a]
        fresh = [n for n in path_b if n not in names_a]
        new_edges = [e for e in edges_b if e not in edges_a]
        keep = [f"n_{n}" for n in shared] + [f"{c}_{n}" for n in fresh for c in ("n", "q", "c", "m", "w")] + [_edge_column(e) for e in new_edges]
        if not shared:
            raise ValueError(f"{path_b} shares no node with {names_a}: their join would be a product")
        both = a.join(b.select(*keep, *[c for c in b.columns if c.startswith("v")]), [f"n_{n}" for n in shared])
        for x in fresh:
            for y in names_a:
                both = both.filter(F.col(f"n_{x}") != F.col(f"n_{y}"))
        names, edges = names_a + fresh, edges_a + new_edges
        both = both.withColumn("ple", product([F.col(f"q_{n}") for n in names] + [F.col(_edge_column(e)) for e in edges])).withColumn("pn", pn_expr(names))
        if alpha is not None:
            both = both.filter(F.col("ple") * F.col("pn") >= alpha - EPS)
        return both, names, edges

    def joinable(self, q: Pattern, d: Decomposition, cands: list[DataFrame], i: int, j: int, alpha: float) -> DataFrame:
        """Pairs of two lists that agree on shared nodes, differ on others, and together keep probability alpha."""
        a, b = cands[i].withColumnRenamed("vid", "va"), cands[j].withColumnRenamed("vid", "vb")
        return self._joined(q, a, list(d.paths[i]), q.path_edges(d.paths[i]), b, d.paths[j], alpha)[0]

    def links(self, q: Pattern, d: Decomposition, cands: list[DataFrame], alpha: float) -> dict[tuple[int, int], DataFrame]:
        pairs = list(d.predicates)
        found = at_once(*[lambda i=i, j=j: materialise(self.joinable(q, d, cands, i, j, alpha).select("va", "vb"), f"links-{i}-{j}") for i, j in pairs])
        return dict(zip(pairs, found, strict=True))

    def kpartite(self, q: Pattern, d: Decomposition, cands: list[DataFrame], links: dict) -> KPartite:
        k = len(d.paths)
        vertices, pairs = None, None
        for i, df in enumerate(cands):
            w1 = product([F.col(f"q_{n}") for n in d.owned_nodes[i]] + [F.col(_edge_column(e)) for e in d.owned_edges[i]])
            rows = df.select(F.lit(i).alias("part"), "vid", w1.alias("w1"), F.col("pn").alias("w2"))
            rows = rows.select("*", *[(F.col("w1") if i == s else F.lit(1.0)).alias(f"s{s}") for s in range(k)])
            vertices = rows if vertices is None else vertices.unionByName(rows)
        for (i, j), df in links.items():
            there = df.select(F.lit(i).alias("p1"), F.col("va").alias("v1"), F.lit(j).alias("p2"), F.col("vb").alias("v2"))
            back = df.select(F.lit(j).alias("p1"), F.col("vb").alias("v1"), F.lit(i).alias("p2"), F.col("va").alias("v2"))
            pairs = there.unionByName(back) if pairs is None else pairs.unionByName(there).unionByName(back)
        kp_v, kp_l = at_once(lambda: materialise(vertices, "kp-v"), lambda: materialise(pairs, "kp-l"))
        return KPartite(kp_v, kp_l, {i: len(d.neighbours(i)) for i in range(k)}, k)

    # -- step 4 -------------------------------------------------------------------------------------------------
    def _round(self, kp: KPartite, alpha: float, structure: bool, bounds: bool, changed: DataFrame | None) -> tuple[KPartite, DataFrame, int]:
        """One round in one pass over the links. Each vertex hears from every list that it is linked to: how many lists
        those are (structure: it needs all its neighbours), and for each list the greatest values that its links there can
        bring, over the lists the least (bounds: the product of its slots has to reach alpha).

        ``changed`` (part, vid) limits the round to vertices that lost a neighbour, or have one whose slots fell, since they
        were last looked at; all others would hear what they know already."""
        slots = [f"s{i}" for i in range(kp.k)]
        links, asked = kp.links, kp.vertices
        if changed is not None:
            links = links.join(changed.select(F.col("part").alias("p1"), F.col("vid").alias("v1")), ["p1", "v1"], "left_semi")
            asked = asked.join(changed, ["part", "vid"], "left_semi")
        to = (F.col("p1").alias("part"), F.col("v1").alias("vid"))
        if bounds:
            sent = links.join(kp.vertices.select(F.col("part").alias("p2"), F.col("vid").alias("v2"), *slots), ["p2", "v2"])
            best = sent.repartition("p1", "v1").groupBy("p1", "v1", "p2").agg(*[F.max(s).alias(s) for s in slots])
            heard = best.groupBy(*to).agg(F.count(F.lit(1)).alias("lists"), *[F.min(s).alias(f"t{i}") for i, s in enumerate(slots)])
        else:  # links hold no vertex that went, and slots don't matter
            heard = links.groupBy(*to).agg(F.bit_count(F.bit_or(F.expr("shiftleft(1L, p2)"))).alias("lists"))
        rows = asked.join(heard, ["part", "vid"], "left")
        other = lambda i, s: F.when(F.col("part") == i, F.col(s)).otherwise(F.least(F.col(s), F.coalesce(F.col(f"t{i}"), F.col(s))))
        new = [(other(i, s) if bounds else F.col(s)).alias(s) for i, s in enumerate(slots)]
        fell = reduce(lambda a, b: a | b, [other(i, s) < F.col(s) - EPS for i, s in enumerate(slots)]) if bounds else F.lit(False)
        wanted = F.element_at(F.create_map(*[F.lit(x) for i in kp.wanted.items() for x in i]), F.col("part"))
        whole = F.coalesce(F.col("lists"), F.lit(0)) == wanted if structure else F.lit(True)
        rows = rows.select("part", "vid", "w1", "w2", *new, fell.alias("fell"), whole.alias("whole"))
        keep = F.col("whole") & (product([F.col(s) for s in slots]) * F.col("w2") >= alpha - EPS) if bounds else F.col("whole")
        moved = materialise(rows.withColumn("keep", keep).filter("fell or not keep" if changed is not None else "true"), "kp-round")
        told = moved.agg(F.count(F.when(~F.col("keep"), 1)), F.count(F.when(F.col("keep") & F.col("fell"), 1))).first()
        gone, news = moved.filter("not keep").select("part", "vid"), moved.filter("not keep or fell").select("part", "vid")
        if told[0] or told[1]:
            still = kp.vertices.join(moved.select("part", "vid"), ["part", "vid"], "left_anti") if changed is not None else None
            held = moved.filter("keep").select("part", "vid", "w1", "w2", *slots)
            beside = kp.links.join(news.select(F.col("part").alias("p2"), F.col("vid").alias("v2")), ["p2", "v2"], "left_semi").select(F.col("p1").alias("part"), F.col("v1").alias("vid")).distinct()
            left = kp.links
            for p, v in (("p1", "v1"), ("p2", "v2")) if told[0] else ():
                left = left.join(gone.select(F.col("part").alias(p), F.col("vid").alias(v)), [p, v], "left_anti")
            kp.vertices, kp.links, changed = at_once(
                lambda: materialise(held if still is None else still.unionByName(held), "kp-v"),
                lambda: materialise(left, "kp-l") if told[0] else kp.links,
                lambda: materialise(beside.join(gone, ["part", "vid"], "left_anti"), "kp-c"),
            )
        kp.rounds.append({"kind": "both" if structure and bounds else "structure" if structure else "bounds", "removed": told[0], "fell": told[1]})
        return kp, changed, told[0] + told[1]

    def _settle(self, kp: KPartite, alpha: float, structure: bool, bounds: bool, incremental: bool, max_rounds: int) -> KPartite:
        changed = None
        for _ in range(max_rounds):
            kp, changed, moves = self._round(kp, alpha, structure, bounds, changed if incremental else None)
            if not moves:
                break
        return kp

    def reduce_structure(self, kp: KPartite, max_rounds: int = 50, incremental: bool = True) -> KPartite:
        """Drop paths that lack a link to a path list they must join, until none does."""
        return self._settle(kp, 0.0, True, False, incremental, max_rounds)

    def reduce_bounds(self, kp: KPartite, alpha: float, max_rounds: int = 50, incremental: bool = True) -> KPartite:
        """Pass perception vectors along the links and drop paths whose bound stays below alpha, until nothing changes."""
        return self._settle(kp, alpha, False, True, incremental, max_rounds)

    def reduce_joint(self, kp: KPartite, alpha: float, mode: str = "both", incremental: bool = True, max_rounds: int = 50) -> KPartite:
        """Both reductions in the same rounds (or one of them). Vertices only go and slots only fall, whichever comes first,
        so that the rounds end where alternating fixpoints would."""
        return self._settle(kp, alpha, mode in ("structure", "both"), mode in ("bounds", "both"), incremental, max_rounds)

    # -- step 5 -------------------------------------------------------------------------------------------------
    def assemble(self, q: Pattern, d: Decomposition, cands: list[DataFrame], links: dict, order: list[int], alpha: float, early: bool = True) -> DataFrame:
        """The lists joined in order; ``links`` holds the pairs (va, vb) that the reduction left."""
        first = order[0]
        rows = cands[first].withColumnRenamed("vid", f"v_{first}")
        names, edges, done = list(d.paths[first]), q.path_edges(d.paths[first]), [first]
        for i in order[1:]:
            nxt = cands[i].withColumnRenamed("vid", f"v_{i}")
            rows, names, edges = self._joined(q, rows, names, edges, nxt, d.paths[i], alpha if early else None)
            for j in done if links else ():
                pair = (min(i, j), max(i, j))
                if pair in links:
                    rows = rows.join(links[pair].select(F.col("va").alias(f"v_{pair[0]}"), F.col("vb").alias(f"v_{pair[1]}")), [f"v_{pair[0]}", f"v_{pair[1]}"], "left_semi")
            done.append(i)
        return rows

    def finalise(self, q: Pattern, rows: DataFrame, alpha: float, o: MatchOptions) -> DataFrame:
        names = sorted(q.nodes)
        p = F.col("ple") * F.col("pn") if o.identity else F.when(F.col("pn") > 0, F.col("ple")).otherwise(F.lit(0.0))
        rows = rows.select(*[F.col(f"n_{n}").alias(n) for n in names], "ple", "pn", p.alias("p")).filter(F.col("p") >= alpha - EPS)
        if o.distinct == "subgraph":
            ends = [F.array_sort(F.array(F.concat_ws(":", F.col(a), F.lit(q.nodes[a])), F.concat_ws(":", F.col(b), F.lit(q.nodes[b])))) for a, b in q.edges]
            key = F.array_sort(F.array(*[F.concat_ws("~", e) for e in ends])) if ends else F.array(F.col(names[0]).cast("string"))
            rows = rows.withColumn("key", F.concat_ws(";", key)).dropDuplicates(["key"]).drop("key")
        return rows.orderBy(F.desc("p"), *names).limit(o.limit) if o.limit else rows

    def match(self, q: Pattern, alpha: float, options: MatchOptions | None = None) -> DataFrame:
        """One row a match: a column of entity ids for each pattern node, ple, pn and p >= alpha."""
        o = options or MatchOptions()
        if not 0 < alpha <= 1:
            raise ValueError("alpha must lie in (0, 1]")
        if o.L and o.L > self.idx.L:
            raise ValueError("the index holds no paths of this length")
        self.trace, began = [], time.time()
        d = self.plan(q, alpha, o)
        if o.identity is False:
            # without marginals the index's p underestimates: fetch everything the labels and edges alone allow
            engine = Engine(replace_certain(self.eg), PathIndex({}, replace_certain(self.eg), self.idx.L, 2.0, 1.0), self.ctx)
            cands = engine.candidates(q, d, alpha, replace(o, identity=True))
        else:
            cands = self.candidates(q, d, alpha, o)
        sizes = at_once(*[c.count for c in cands])
        self._note("candidates", sizes, d, began)
        links: dict = {}
        reduction = o.reduction
        if reduction == "auto":
            reduction = "both" if sum(math.log10(max(s, 1)) for s in sizes) > REDUCE_FROM else "none"
        if len(cands) > 1 and min(sizes) and reduction != "none" and o.identity:
            kp = self.kpartite(q, d, cands, self.links(q, d, cands, alpha))
            kp = self.reduce_joint(kp, alpha, reduction, o.incremental, o.max_rounds)
            links = {(i, j): kp.links.filter((F.col("p1") == i) & (F.col("p2") == j)).select(F.col("v1").alias("va"), F.col("v2").alias("vb")) for i, j in d.predicates}
            left = {r["part"]: r["count"] for r in kp.vertices.groupBy("part").count().collect()}
            cands = [c.join(kp.vertices.filter(F.col("part") == i).select("vid"), "vid", "left_semi") for i, c in enumerate(cands)]
            sizes = [left.get(i, 0) for i in range(len(cands))]
            self._note("reduced", sizes, d, began, kp.rounds)
        rows = self.assemble(q, d, cands, links, join_order(d, sizes, o.order), alpha, early=o.identity)
        if o.identity is False:
            real = self.eg.entities
            rows = rows.drop("pn")
            for n in sorted(q.nodes):
                e = real.select(F.col("entity_id").alias(f"n_{n}"), F.col("comp_id").alias(f"c_{n}"), F.col("mask").alias(f"m_{n}"), F.col("worlds").alias(f"w_{n}"))
                rows = rows.drop(f"c_{n}", f"m_{n}", f"w_{n}").join(e, f"n_{n}")
            rows = rows.withColumn("pn", pn_expr(sorted(q.nodes)))
        return self.finalise(q, rows, alpha, o)

    def _note(self, step, sizes, d, began, rounds=()):
        self.trace.append({"step": step, "sizes": sizes, "log10": sum(math.log10(max(s, 1e-3)) for s in sizes), "paths": d.paths, "s": time.time() - began, "rounds": list(rounds)})

    def explain(self, q: Pattern, alpha: float, options: MatchOptions | None = None) -> str:
        """The decomposition and the physical plan of the assembly."""
        rows = self.match(q, alpha, options)
        plan = rows._jdf.queryExecution().toString()
        return "\n".join([*(f"{t['step']}: {t['paths']} sizes {t['sizes']}" for t in self.trace), plan])


def replace_certain(eg: EntityGraph) -> EntityGraph:
    """The same graph with every entity certain to exist."""
    e = eg.entities.withColumn("comp_id", F.lit(None).cast("long")).withColumn("worlds", F.lit(None).cast("array<struct<mask:bigint,p:double>>"))
    return replace(eg, entities=e)

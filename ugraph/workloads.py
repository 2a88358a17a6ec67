"""The experiment sweeps on the given tables and on synthetic graphs."""

from __future__ import annotations

import random

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from . import metrics
from .operators import baselines
from .operators.engine import Engine, MatchOptions
from .operators.entity_graph import EntityGraph, build_entity_graph
from .operators.path_index import build_path_index
from .plans.pattern import Pattern, edge, random_pattern, shape
from .sources import synth, testgraphs

PART_LABELS = ["SMALL", "PROMO", "LARGE", "ECONOMY", "MEDIUM", "STANDARD"]
QUERY_SIZES = [(n, min(4 * n, n * (n - 1) // 2)) for n in (3, 5, 7, 9, 11, 13, 15)]
DENSITIES = [(15, m) for m in (20, 40, 60, 80, 100)]
SWEEP_SIZES = [(5, 5), (5, 9), (10, 20), (10, 40)]


def planted_pattern(eg: EntityGraph, n: int, m: int, seed: int = 0, pool: int = 60) -> Pattern:
    """A pattern that has a match of probability 0.8 or more: n linked entities among the ``pool`` best connected ones (of
    those with sure labels and edges), grown by the most edges to those chosen, and m of their edges (all, where no start gives as many). What is read to the
    driver is bounded by ``pool``."""
    sure = eg.labels.filter("p > 0.99").join(eg.entities.filter("comp_id is null"), "entity_id", "left_semi")
    links = eg.edges.filter("p > 0.99").join(sure.select(F.col("entity_id").alias("src")), "src", "left_semi").join(sure.select(F.col("entity_id").alias("dst")), "dst", "left_semi")
    top = [r[0] for r in links.groupBy("src").count().orderBy(F.desc("count"), "src").limit(pool).collect()]
    rows = links.filter(F.col("src").isin(top) & F.col("dst").isin(top)).orderBy("src", "dst").select("src", "dst").distinct().collect()
    near: dict[int, set[int]] = {x: set() for x in top}
    for a, b in rows:
        near[a].add(b)
        near[b].add(a)
    rng = random.Random(f"{n},{m},{seed}")
    linked = sorted(x for x in top if near[x])
    if len(linked) < n:
        raise ValueError("too few linked entities in the pool")
    rng.shuffle(linked)
    densest = (-1, [])
    for start in linked:
        grown = [start]
        while len(grown) < n:
            rest = sorted({y for x in grown for y in near[x]} - set(grown))
            if not rest:
                break
            best = max(len(near[y] & set(grown)) for y in rest)
            grown.append(rng.choice([y for y in rest if len(near[y] & set(grown)) == best]))
        if len(grown) == n:
            densest = max(densest, (sum(len(near[x] & set(grown)) for x in grown) // 2, grown))
            if densest[0] >= m:
                break
    chosen = densest[1]
    if not chosen:
        raise ValueError(f"no {n} linked entities in the pool")
    name = {x: f"x{i}" for i, x in enumerate(chosen)}
    tree = [edge(name[x], name[next(y for y in chosen[:i] if y in near[x])]) for i, x in enumerate(chosen) if i]
    more = sorted({edge(name[x], name[y]) for x in chosen for y in near[x] & set(chosen)} - set(tree))
    rng.shuffle(more)
    labels = {r["entity_id"]: r["label"] for r in eg.labels.filter(F.col("entity_id").isin(chosen)).groupBy("entity_id").agg(F.max_by("label", F.struct("p", "label")).alias("label")).collect()}
    return Pattern({name[x]: labels[x] for x in chosen}, sorted(tree + more[: max(0, m - len(tree))]))


def length_comparison(engine: Engine, q: Pattern, alpha: float = 0.7, budget: float = 900.0) -> list[dict]:
    """Matches, log10 of the final search space and seconds by the path method at each length, by its baselines and as
    one statement."""
    spark = engine.eg.labels.sparkSession
    runs = {f"paths of {L}": lambda L=L: engine.match(q, alpha, MatchOptions(L=L, reduction="both")) for L in range(1, engine.idx.L + 1)}
    runs |= {"planned": lambda: engine.match(q, alpha), "random paths": lambda: baselines.random_decomposition(engine, q, alpha), "no reduction": lambda: baselines.no_reduction(engine, q, alpha)}
    runs |= {"node at a time": lambda: baselines.node_at_a_time(engine.eg, engine, q, alpha), "one statement": lambda: baselines.direct_sql(engine.eg, q, alpha)}
    out = []
    for name, run in runs.items():
        engine.trace = []
        got = metrics.run_with_budget(spark, lambda run=run: run().count(), budget)
        last = engine.trace[-1]["log10"] if engine.trace else None
        out.append({"method": name, "status": got["status"], "n_matches": got["result"] if got["status"] == "ok" else None, "log10": last, "s": got["s"]})
    return out


def engine_for(rg, L: int = 2, beta: float = 0.3) -> Engine:
    eg = build_entity_graph(rg)
    return Engine(eg, build_path_index(eg, L, beta))


def offline_grid(spark: SparkSession, sf_dir: str, lengths=(1, 2), betas=(0.5, 0.7, 0.9)) -> list[dict]:
    rg = testgraphs.costar(spark, sf_dir)
    return [metrics.offline_time(rg, L, b) for L in lengths for b in betas]


def size_sweep(engine: Engine, sizes=QUERY_SIZES, alpha: float = 0.7, seeds: int = 5, options: MatchOptions | None = None, labels=None, budget: float = 900.0) -> list[dict]:
    """Seconds of ``seeds`` random patterns of each size; a run over its budget is told as such."""
    out = []
    spark = engine.eg.labels.sparkSession
    for n, m in sizes:
        runs = [metrics.run_with_budget(spark, lambda s=s: engine.match(random_pattern(n, m, labels or PART_LABELS, s), alpha, options).count(), budget) for s in range(seeds)]
        out.append({"n": n, "m": m, "s": sum(r["s"] for r in runs) / seeds, "status": sorted({r["status"] for r in runs})})
    return out


def density_sweep(engine: Engine, **kw) -> list[dict]:
    return size_sweep(engine, DENSITIES, **kw)


def uncertainty_sweep(spark: SparkSession, sf_dir: str, shares=(0.2, 0.4, 0.6, 0.8, 1.0), **kw) -> list[dict]:
    return [{"share": s, **r} for s in shares for r in size_sweep(engine_for(testgraphs.costar(spark, sf_dir, s)), SWEEP_SIZES, **kw)]


def graph_size_sweep(spark: SparkSession, dirs: list[str], **kw) -> list[dict]:
    return [{"dir": d, **r} for d in dirs for r in size_sweep(engine_for(testgraphs.costar(spark, d)), SWEEP_SIZES, **kw)]


def synthetic_sweep(spark: SparkSession, sizes=(500, 5000, 50000), **kw) -> list[dict]:
    return [{"n_refs": n, **r} for n in sizes for r in size_sweep(engine_for(synth.generate(spark, n)), SWEEP_SIZES[:2], labels=[f"L{i}" for i in range(5)], **kw)]


def threshold_sweep(engine: Engine, alphas=(0.3, 0.5, 0.7, 0.9), **kw) -> list[dict]:
    return [{"alpha": a, **r} for a in alphas for r in size_sweep(engine, SWEEP_SIZES[:2], alpha=a, **kw)]


def search_space_progression(engine: Engine, q: Pattern, alpha: float = 0.7, covers: dict | None = None) -> list[dict]:
    """Steps of the search space for each path length; ``covers`` gives the paths of each, else the planner chooses."""
    covers = covers or dict.fromkeys(range(1, engine.idx.L + 1))
    return [{"L": L, **r} for L, paths in covers.items() for r in metrics.progression(engine, q, alpha, None if paths else L, paths)]


def reduction_contribution(engine: Engine, alpha: float = 0.1, q: Pattern | None = None, covers: dict | None = None) -> list[dict]:
    """What structure and bounds leave of the search space, on the 5-cycle by default."""
    covers = covers or dict.fromkeys(range(1, engine.idx.L + 1))
    return [{"L": L, **metrics.reduction_ratio(engine, q or shape("cycle5", PART_LABELS), alpha, None if paths else L, paths)} for L, paths in covers.items()]


def sql_comparison(engine: Engine, alpha: float = 0.7, budget: float = 900.0, seed: int = 0) -> dict:
    q = random_pattern(5, 7, PART_LABELS, seed)
    spark = engine.eg.labels.sparkSession
    return {"method": metrics.run_with_budget(spark, lambda: engine.match(q, alpha).count(), budget), "sql": metrics.run_with_budget(spark, lambda: baselines.direct_sql(engine.eg, q, alpha).count(), budget)}


def real_shapes(engine: Engine, label: str | None = None, alpha: float = 0.1, names=("path3", "triangle", "star3", "square", "tree7", "clique4")) -> list[dict]:
    """Same-label shapes, as on the two real networks."""
    return [{"shape": n, "s": metrics.timed(lambda n=n: engine.match(shape(n, [label or PART_LABELS[0]]), alpha).count())[0]} for n in names]

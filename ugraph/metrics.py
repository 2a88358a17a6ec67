"""Cost and accuracy measures."""

from __future__ import annotations

import math
import threading
import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .operators.engine import Engine, MatchOptions
from .operators.entity_graph import EntityGraph, build_entity_graph
from .operators.identity import sampled_marginals
from .operators.path_index import PathIndex, build_path_index, estimate_count, exact_count, load_counts, node_context
from .plans.pattern import Pattern


def timed(run) -> tuple[float, object]:
    began = time.time()
    out = run()
    return time.time() - began, out


def offline_time(rg, L: int, beta: float, gamma: float = 0.1) -> dict:
    """Seconds for the entity graph with its marginals, the index and the context."""
    graph_s, (eg, _) = timed(lambda: (g := build_entity_graph(rg), g.marginals))
    index_s, idx = timed(lambda: build_path_index(eg, L, beta, gamma))
    context_s, _ = timed(lambda: node_context(eg).count())
    return {"L": L, "beta": beta, "graph_s": graph_s, "index_s": index_s, "context_s": context_s, "paths": {n: d.count() for n, d in idx.paths.items()}, "bytes": index_bytes(idx.hist.sparkSession, idx.paths)}


def run_with_budget(spark, run, seconds: float = 900.0) -> dict:
    """``run`` under a tag whose jobs are cancelled after its budget: ok, time, memory or error."""
    tag = f"budget-{time.time_ns()}"
    late = threading.Event()
    timer = threading.Timer(seconds, lambda: (late.set(), spark.interruptTag(tag)))
    spark.addTag(tag)
    timer.start()
    try:
        s, out = timed(run)
        return {"status": "time" if late.is_set() else "ok", "s": s, "result": out}
    except Exception as e:  # noqa: BLE001  what ended it is the result
        memory = any(x in str(e) for x in ("OutOfMemory", "out of memory", "UNABLE_TO_ACQUIRE_MEMORY", "No space left"))
        return {"status": "time" if late.is_set() else "memory" if memory else "error", "s": seconds, "result": str(e)[:200]}
    finally:
        timer.cancel()
        spark.removeTag(tag)


def online_time(engine: Engine, patterns: list[Pattern], alpha: float, options: MatchOptions | None = None) -> float:
    """Mean seconds of a match over the patterns."""
    return sum(timed(lambda q=q: engine.match(q, alpha, options).count())[0] for q in patterns) / len(patterns)


def search_space(sizes: list[int]) -> float:
    """Log10 of the product of the list sizes; an empty list gives -inf."""
    return sum(math.log10(s) for s in sizes) if all(sizes) else -math.inf


def progression(engine: Engine, q: Pattern, alpha: float, L: int | None = None, paths=None) -> list[dict]:
    """Search space after the index read, after node and path context, and after the joint reduction."""
    o = MatchOptions(L=L, reduction="both", paths=paths)
    d = engine.plan(q, alpha, o)
    raw = [engine.fetch(q, p, alpha).count() for p in d.paths]
    engine.match(q, alpha, o)
    steps = {t["step"]: t["sizes"] for t in engine.trace}
    rows = [("path", raw), ("context", steps["candidates"]), ("final", steps.get("reduced", steps["candidates"]))]
    return [{"step": s, "log10": search_space(x), "lists": len(x), "paths": sum(x)} for s, x in rows]


def reduction_ratio(engine: Engine, q: Pattern, alpha: float, L: int | None = None, paths=None) -> dict:
    """Search space after structure, and after bounds, over that just before."""
    out = {}
    o = MatchOptions(L=L, paths=paths)
    d = engine.plan(q, alpha, o)
    cands = engine.candidates(q, d, alpha, o)
    sizes = [c.count() for c in cands]
    if len(cands) < 2 or not all(sizes):
        return {"structure": 0.0, "bounds": 0.0}
    kp = engine.kpartite(q, d, cands, engine.links(q, d, cands, alpha))
    for step, run in (("structure", lambda: engine.reduce_structure(kp)), ("bounds", lambda: engine.reduce_joint(kp, alpha, "both"))):
        run()
        now = {r["part"]: r["count"] for r in kp.vertices.groupBy("part").count().collect()}
        after = [now.get(i, 0) for i in range(kp.k)]
        out[step] = 10 ** (search_space(after) - search_space(sizes)) if all(sizes) and all(after) else 0.0
        sizes = after
    return out


def reduction_trace(engine: Engine) -> list[dict]:
    return [r for t in engine.trace for r in t["rounds"]]


def graph_stats(eg: EntityGraph) -> DataFrame:
    """Entities, edges, mean number of edges at an entity, and the shares of uncertain entities and edges."""
    e = eg.entities.agg(F.count(F.lit(1)).alias("n_entities"), F.count("comp_id").alias("n_identity"))
    x = eg.edges.agg(F.count(F.lit(1)).alias("n_edges"), F.round(F.sum("p"), 4).alias("edge_mass"), F.count(F.when(F.col("p") < 1, 1)).alias("uncertain"))
    both = e.crossJoin(x)  # one row each
    share = lambda a, b: F.round(F.when(F.col(b) > 0, F.col(a) / F.col(b)).otherwise(0.0), 6)
    return both.select("n_entities", "n_identity", "n_edges", "edge_mass", share("n_edges", "n_entities").alias("mean_degree"), share("uncertain", "n_edges").alias("uncertain_edges"), share("n_identity", "n_entities").alias("uncertain_entities"))


def index_bytes(spark, paths: dict[int, DataFrame]) -> dict[int, int]:
    """Bytes of the files of each path length, from the file system's own list."""
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    out = {}
    for n, df in paths.items():
        files = [jvm.org.apache.hadoop.fs.Path(f) for f in df.inputFiles()]
        out[n] = sum(f.getFileSystem(conf).getFileStatus(f).getLen() for f in files)
    return out


def estimate_qerror(idx: PathIndex, keys: list[list[str]], alpha: float) -> list[float]:
    """max(estimate / count, count / estimate) of label sequences at a threshold between the histogram's points."""
    out = []
    for labels in keys:
        key = min("|".join(labels), "|".join(reversed(labels)))
        known = load_counts(idx, [key])
        est, real = max(estimate_count(known[key], alpha) if known else 0.0, 1.0), max(exact_count(idx, labels, alpha), 1)
        out.append(max(est / real, real / est))
    return out


def compare(found: DataFrame, true: DataFrame, keys: list[str]) -> dict:
    """Precision, recall and greatest probability error of a match frame."""
    a, b = found.select(*keys, F.col("p").alias("pa")), true.select(*keys, F.col("p").alias("pb"))
    r = a.join(b, keys, "full").agg(F.count("pa").alias("a"), F.count("pb").alias("b"), F.count(F.when(F.col("pa").isNotNull() & F.col("pb").isNotNull(), 1)).alias("both"), F.max(F.abs(F.col("pa") - F.col("pb"))).alias("err")).first()
    return {"precision": r["both"] / r["a"] if r["a"] else 1.0, "recall": r["both"] / r["b"] if r["b"] else 1.0, "error": r["err"] or 0.0}


def marginal_error(eg: EntityGraph, draws: int = 2000) -> dict:
    """Entities' probabilities from drawn worlds against the exact ones: greatest difference, and greatest standard error."""
    drawn = sampled_marginals(eg.entities.withColumn("p", F.col("prior")), draws).join(eg.entities.select("entity_id", "p_exist"), "entity_id")
    r = drawn.agg(F.max(F.abs(F.col("p") - F.col("p_exist"))), F.max("se")).first()
    return {"error": r[0] or 0.0, "se": r[1] or 0.0}

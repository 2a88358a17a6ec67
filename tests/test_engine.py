"""Engine, index and identity at work: variants agree, files are pruned, guards hold, streams equal tables."""

import itertools
import os
import shutil
import subprocess
import sys

import pytest
from pyspark.sql import functions as F

from ugraph import metrics, queries, workloads
from ugraph.functions.merge import MERGES
from ugraph.operators import baselines
from ugraph.operators.engine import Engine, MatchOptions
from ugraph.operators.entity_graph import EntityGraph, ReferenceGraph, build_entity_graph, existence_factors, merge_edges
from ugraph.operators.identity import component_worlds, sampled_marginals
from ugraph.operators.path_index import PathIndex, build_path_index
from ugraph.plans.decompose import best_cover, decompose, decomposition_cost, join_order, path_cost
from ugraph.plans.pattern import Pattern, enumerate_query_paths, random_pattern, shape
from ugraph.sources import synth, testgraphs
from ugraph.streaming.edges import pair_counts, run_stream, windowed_users

D = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def engine(spark):
    eg = build_entity_graph(testgraphs.costar(spark, D))
    return Engine(eg, build_path_index(eg, 3, 0.3))


def held(df):
    return sorted(tuple(round(v, 6) if isinstance(v, float) else v for v in r) for r in df.collect())


@pytest.mark.parametrize("name", ["triangle", "square", "star3"])
def test_reductions_and_covers_agree(engine, name):
    q = shape(name, workloads.PART_LABELS[:3])
    want = held(baselines.direct_sql(engine.eg, q, 0.2).select(*sorted(q.nodes), "p"))
    assert want
    variants = (
        MatchOptions(reduction="both"), MatchOptions(), MatchOptions(reduction="structure", L=1), MatchOptions(reduction="bounds", L=1, incremental=False), MatchOptions(reduction="both", incremental=False, L=2),
        MatchOptions(decomposition="greedy", reduction="both"), MatchOptions(decomposition="random", seed=3, reduction="both"), MatchOptions(order="exact"), MatchOptions(node_context=False, path_context=False, reduction="both"),
    )
    for o in variants if name == "triangle" else variants[:2]:
        got = engine.match(q, 0.2, o)
        assert held(got.select(*sorted(q.nodes), F.round("p", 6).alias("p"))) == want, o


def test_incremental_rounds_end_alike(engine):
    q, o = shape("cycle5", workloads.PART_LABELS[:2]), MatchOptions(L=1)
    d = engine.plan(q, 0.2, o)
    left = []
    for mode, incremental in itertools.product(("structure", "bounds", "both"), (True, False)):
        cands = engine.candidates(q, d, 0.2, o)
        kp = engine.reduce_joint(engine.kpartite(q, d, cands, engine.links(q, d, cands, 0.2)), 0.2, mode, incremental)
        left.append(sorted((r.part, r["count"]) for r in kp.vertices.groupBy("part").count().collect()))
    assert left[0] == left[1] and left[2] == left[3] and left[4] == left[5]
    assert sum(n for _, n in left[4]) <= min(sum(n for _, n in left[0]), sum(n for _, n in left[2]))


def test_symmetric_matches_as_subgraphs(engine):
    q = shape("wedge", ["SMALL"])
    both, once = engine.match(q, 0.5), engine.match(q, 0.5, MatchOptions(distinct="subgraph"))
    assert both.count() == 2 * once.count() > 0


def test_single_node(engine):
    q = Pattern({"x": "SMALL"}, [])
    want = engine.eg.labels.filter("label = 'SMALL'").join(engine.eg.entities, "entity_id").filter("p * p_exist >= 0.5 - 1e-12").count()
    assert engine.match(q, 0.5).count() == want > 0


def test_index_files_are_pruned_and_reloaded(spark, engine, tmp_path, monkeypatch):
    from ugraph.operators import path_index

    monkeypatch.setattr(path_index, "FILE_ROWS", 1000)
    store = str(tmp_path / "index")
    engine.idx.save(store)
    engine.eg.save(str(tmp_path / "graph"))
    again = PathIndex.load(spark, store, EntityGraph.load(spark, str(tmp_path / "graph")))
    files = again.paths[2].inputFiles()
    import pyarrow.parquet as pq

    ranges = []
    for f in files:
        meta = pq.ParquetFile(f.removeprefix("file://")).metadata
        stats = [meta.row_group(g).column(next(i for i in range(meta.num_columns) if meta.schema.column(i).path == "label_key")).statistics for g in range(meta.num_row_groups)]
        ranges += [(s.min, s.max) for s in stats]
    key = "LARGE|PROMO|SMALL"
    holding = [r for r in ranges if r[0] <= key <= r[1]]
    assert len(ranges) > 10 and len(holding) <= 2
    labels = key.split("|")
    rows = again.lookup(labels, 0.5)
    spark.conf.set("spark.sql.maxMetadataStringLength", "2000")
    plan = again.stored(labels, 0.5)._jdf.queryExecution().executedPlan().toString()
    spark.conf.unset("spark.sql.maxMetadataStringLength")
    assert "PushedFilters" in plan and "EqualTo(label_key" in plan and "w_0" not in " ".join(again.paths[2].columns)
    assert held(rows.select("n_0", "n_1", "n_2", "p")) == held(engine.idx.lookup(labels, 0.5).select("n_0", "n_1", "n_2", "p"))
    assert again.L == 3 and again.beta == 0.3 and metrics.index_bytes(spark, again.paths)[2] > 0


def test_exact_cover_is_least():
    for n, m, seed in itertools.product((3, 4), (3, 5), range(4)):
        q = random_pattern(n, m, ["a", "b"], seed)
        options = enumerate_query_paths(q, 2)
        counts = lambda p: 1.0 + (hash(p) % 50 if False else sum(map(ord, "".join(p))) * (len(p) + 1) % 50)
        best = decomposition_cost(q, best_cover(q, options, {p: path_cost(q, p, counts(p)) for p in options}), counts)
        for k in range(1, 4):
            for some in itertools.combinations(options, k):
                if {e for p in some for e in q.path_edges(p)} == set(q.edges) and all(counts(p) >= 1 for p in some):
                    useful = [p for i, p in enumerate(some) if set(q.path_edges(p)) - {e for o in some[:i] for e in q.path_edges(o)}]
                    if len(useful) == len(some):
                        assert best <= decomposition_cost(q, some, counts) + 1e-9
        assert decomposition_cost(q, decompose(q, 2, counts, "greedy").paths, counts) >= best - 1e-9
    with pytest.raises(ValueError):
        decompose(random_pattern(10, 20, ["a"], 0), 1, lambda p: 1.0, "exact")


def test_join_orders_are_connected():
    q = random_pattern(6, 8, ["a", "b"], 2)
    d = decompose(q, 2, lambda p: 5.0, "greedy")
    for mode in ("heuristic", "matches", "exact"):
        order = join_order(d, [10.0 * (i + 1) for i in range(len(d.paths))], mode)
        assert sorted(order) == list(range(len(d.paths)))
        assert all(set(d.paths[i]) & {n for j in order[:k] for n in d.paths[j]} for k, i in enumerate(order) if k)


def test_no_product_joins(engine):
    q = Pattern.parse("(a:SMALL)-(b:PROMO)-(c:LARGE)-(d:SMALL)")
    lists = [engine.fetch(q, p, 0.5) for p in (("a", "b"), ("c", "d"))]
    with pytest.raises(ValueError, match="product"):
        engine._joined(q, lists[0], ["a", "b"], [("a", "b")], lists[1], ("c", "d"), 0.5)


def chain(spark, n, p=0.5):
    rows = [(1, i, [i], 0.6, i) for i in range(n)] + [(1, n + i, [i, i + 1], p, n + i) for i in range(n - 1)]
    return spark.createDataFrame(rows, "comp_id long, entity_id long, refs array<long>, p double, bit int")


def test_large_components(spark):
    """Beyond the limit worlds are drawn, with marginals within a few standard errors of the exact ones; too many entities
    for a mask are an error."""
    exact = {r.mask: r.p for r in component_worlds(chain(spark, 8)).collect()}
    drawn = {r.mask: r.p for r in component_worlds(chain(spark, 8), most_refs=4, draws=6000).collect()}
    assert set(drawn) <= set(exact) and abs(sum(drawn.values()) - 1) < 1e-9
    for r in sampled_marginals(chain(spark, 8), 6000).collect():
        want = sum(p for m, p in exact.items() if m >> r.entity_id & 1)
        assert abs(r.p - want) < 5 * r.se + 1e-3 and r.se < 0.05
    with pytest.raises(Exception, match="63 at most"):
        component_worlds(chain(spark, 40)).count()


def test_existence_factors(spark):
    sets = spark.createDataFrame([(1, [1, 2], 0.25), (2, [1], 0.4)], "set_id long, members array<long>, p double")
    assert held(existence_factors(sets)) == [(1, 1, 0.25), (1, 2, 0.25), (2, 1, 0.4)]
    assert held(existence_factors(sets, "per_set")) == [(1, 1, 0.5), (1, 2, 0.5), (2, 1, 0.4)]


def test_missing_pairs_and_max(spark):
    labels = spark.createDataFrame([(i, "a", 1.0) for i in range(1, 4)], "ref_id long, label string, p double")
    edges = spark.createDataFrame([(1, 3, 0.8)], "src long, dst long, p double")
    rg = ReferenceGraph(labels, edges, spark.createDataFrame([(1, [1, 2], 0.5)], "set_id long, members array<long>, p double"))
    one = lambda **kw: {(r.src, r.dst): r.p for r in merge_edges(rg, **kw).collect()}[1_000_000_001, 3]
    assert one() == 0.4 and one(missing="recorded") == 0.8 and one(how="max") == 0.8 and set(MERGES) >= {"average", "disjunct", "max"}


def test_measures(spark, engine):
    steps = metrics.progression(engine, shape("cycle5", workloads.PART_LABELS), 0.3)
    assert steps[0]["log10"] >= steps[1]["log10"] >= steps[2]["log10"]
    error = metrics.marginal_error(engine.eg, 4000)
    assert error["error"] < 0.06 and error["se"] < 0.05
    assert max(metrics.estimate_qerror(engine.idx, [["SMALL", "PROMO"], ["LARGE", "LARGE"]], 0.55)) < 3
    q = shape("wedge", workloads.PART_LABELS)
    a = engine.match(q, 0.5)
    assert metrics.compare(a, a, sorted(q.nodes)) == {"precision": 1.0, "recall": 1.0, "error": 0.0}
    assert metrics.run_with_budget(spark, lambda: spark.range(10).count(), 60)["status"] == "ok"
    slow = metrics.run_with_budget(spark, lambda: spark.range(0, 200_000_000, 1, 2000).selectExpr("max(sha2(cast(id as string), 256))").collect(), 2)
    assert slow["status"] == "time"


def test_directed_and_conditional(spark):
    for kind, q, sql in (("directed", queries.DIRECTED, {}), ("collab", queries.CONDITIONAL, {"conditional": True})):
        e = queries.engine(spark, D, kind, 2, 0.1)
        want = held(baselines.direct_sql(e.eg, q, 0.1).select(*sorted(q.nodes), "p"))
        for o in (MatchOptions(), MatchOptions(L=1, reduction="both")):
            assert held(e.match(q, 0.1, o).select(*sorted(q.nodes), F.round("p", 6).alias("p"))) == want


def test_synthetic_graph(spark):
    rg = synth.generate(spark, 600).validate()
    edges = rg.edges.collect()
    assert 2600 < len(edges) <= 3000 and all(r.src < r.dst < 600 for r in edges) and len({(r.src, r.dst) for r in edges}) == len(edges)
    degree = rg.edges.selectExpr("explode(array(src, dst)) AS v").groupBy("v").count()
    assert degree.agg(F.max("count")).first()[0] > 8 * degree.agg(F.avg("count")).first()[0]
    draws = spark.range(200_000).select(synth.u(F.col("id"), 1).alias("x"))
    assert draws.distinct().count() == 200_000 and abs(draws.agg(F.avg("x")).first()[0] - 0.5) < 0.01


def test_planted_pattern(spark):
    eg = build_entity_graph(synth.generate(spark, 400))
    e = Engine(eg, build_path_index(eg, 3, 0.7))
    q = workloads.planted_pattern(eg, 5, 7, 0)
    got = {r["method"]: r for r in workloads.length_comparison(e, q, 0.7, 300)}
    assert len({r["n_matches"] for r in got.values()}) == 1 and got["one statement"]["n_matches"] > 0
    assert got["paths of 3"]["log10"] <= got["paths of 2"]["log10"] + 1e-9 <= got["paths of 1"]["log10"] + 2e-9


def test_stream_equals_table(spark, tmp_path):
    events = spark.read.parquet(f"{D}/events.parquet")
    folder = str(tmp_path / "events")
    # a last event far ahead closes all windows before it
    last = events.limit(1).withColumn("ts", F.expr("cast(ts as timestamp) + INTERVAL 90 DAYS")).select(events.columns)
    events.withColumn("ts", F.col("ts").cast("timestamp")).unionByName(last).repartition(3).write.parquet(folder)
    stream = spark.readStream.schema(spark.read.parquet(folder).schema).parquet(folder)
    run_stream(stream, str(tmp_path / "out"), str(tmp_path / "ck")).awaitTermination()
    got = spark.read.parquet(str(tmp_path / "out"))
    assert held(pair_counts(got)) == held(pair_counts(windowed_users(events))) != []


def test_without_the_optional_folders(tmp_path):
    """A copy without the subpackage, its tests and the pipeline still offers all other queries."""
    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    copy = tmp_path / "copy"
    shutil.copytree(root, copy, ignore=shutil.ignore_patterns("llm", "corpus_pipeline.py", ".git", "__pycache__"))
    code = "import __spark_entry__ as e; q = e.queries(); assert len(q) > 90 and not [n for n in q if n.startswith('op') or n == 'pipeline'] and set(e.oracle_sql()) <= set(q)"
    subprocess.run([sys.executable, "-c", code], cwd=copy, check=True, env={**os.environ, "PYTHONPATH": str(copy)})

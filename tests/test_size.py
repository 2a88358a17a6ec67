"""What operators shuffle on tables where the plain plan would multiply rows."""

import pytest
from pyspark.sql import functions as F

from ugraph import queries
from ugraph.operators import baselines, engine, entity_graph, path_index
from ugraph.operators.engine import Engine
from ugraph.operators.entity_graph import ReferenceGraph, build_entity_graph
from ugraph.plans.pattern import Pattern, shape
from ugraph.sources import testgraphs
from ugraph.streaming import edges


@pytest.fixture
def moved(spark):
    """Run something without broadcasts; the records that its stages wrote to shuffles."""
    plain = {"spark.sql.autoBroadcastJoinThreshold": "-1", "spark.sql.adaptive.enabled": "false"}
    before = {k: spark.conf.get(k) for k in plain}

    def records() -> int:
        sc = spark.sparkContext
        stages = sc._jsc.sc().statusStore().stageList(None, False, False, sc._gateway.new_array(sc._jvm.double, 0), None)
        return sum(stages.apply(i).shuffleWriteRecords() for i in range(stages.size()))

    def run(f):
        start = records()
        out = f()
        return out, records() - start

    for k, v in plain.items():
        spark.conf.set(k, v)
    yield run
    for k, v in before.items():
        spark.conf.set(k, v)


@pytest.fixture(scope="module")
def hubs(spark):
    """One square a-b-c-d whose corners have 60 neighbours each of a label that the pattern lacks."""
    labels = [(i, s, 1.0) for i, s in enumerate("abcd")] + [(100 + i, "z", 1.0) for i in range(60)]
    edges = [(0, 1, 0.9), (1, 2, 0.9), (2, 3, 0.9), (0, 3, 0.9)] + [(i, 100 + j, 1.0) for i in range(4) for j in range(60)]
    sets = spark.createDataFrame([], "set_id long, members array<long>, p double")
    return build_entity_graph(ReferenceGraph(spark.createDataFrame(labels, "ref_id long, label string, p double"), spark.createDataFrame(edges, "src long, dst long, p double"), sets))


@pytest.mark.parametrize("run", [lambda eg, q: baselines.node_at_a_time(eg, Engine(eg, None, eg.labels), q, 0.5, early=False), lambda eg, q: baselines.direct_sql(eg, q, 0.5)])
def test_edges_to_other_labels_multiply_nothing(spark, moved, hubs, run):
    q = shape("square", list("abcd"))
    rows, records = moved(lambda: run(hubs, q).collect())
    assert [(r.x0, r.x1, r.x2, r.x3, round(r.p, 6)) for r in rows] == [(0, 1, 2, 3, 0.6561)]
    assert records <= 2 * hubs.edges.count()


@pytest.mark.parametrize("block", [40, 10_000])
def test_pairs_of_full_windows_are_not_shuffled(spark, moved, monkeypatch, block):
    """120 of 150 users in each of 20 windows: 142,800 pairs, with ids that lie far apart."""
    monkeypatch.setattr(edges, "BLOCKS_FROM", 1, raising=False)
    monkeypatch.setattr(edges, "USER_BLOCK", block, raising=False)
    monkeypatch.setattr(edges, "PAIRS_A_ROW", 1, raising=False)
    held = {w: sorted({(7 * w + 3 * i) % 150 * 10**12 for i in range(120)} & {i * 10**12 for i in range(150)}) for w in range(20)}
    rows = [(f"t{w % 3}" if w else None, f"2024-01-01 {w:02d}:00:00", u) for w, u in held.items()]
    windows = spark.createDataFrame(rows, "event_type string, hour string, users array<long>").withColumn("hour", F.col("hour").cast("timestamp"))
    want = {}
    for w, users in held.items():
        for i, a in enumerate(users) if w else ():  # no type, no window
            for b in users[i + 1 :]:
                want[a, b] = want.get((a, b), 0) + 1
    got, records = moved(lambda: edges.pair_counts(windows).collect())
    assert len(got) == len(want) and {(r.src, r.dst): r.n for r in got} == want
    assert records < len(want)


def test_path_counts_store_no_longest_paths(spark, monkeypatch):
    """The counts are those of the indexes, also where two nodes of a path share an identity component, and the longest
    paths are never written."""
    rg = testgraphs.tiny(spark)
    more = spark.createDataFrame([(3, 4, 0.9), (1, 4, 0.8)], "src long, dst long, p double")
    eg = build_entity_graph(ReferenceGraph(rg.labels, rg.edges.unionByName(more), rg.sets))
    want = [(b, n, df.count()) for b in (0.05, 0.2) for n, df in path_index.build_path_index(eg, 3, b).paths.items()]
    written, write = [], path_index.materialise
    monkeypatch.setattr(path_index, "materialise", lambda df, tag: (written.append(tag), write(df, tag))[1])
    assert path_index.path_counts(eg, 3, (0.05, 0.2)) == want and want[2][2] > want[6][2] > 0
    assert written == ["paths-0", "paths-1", "paths-2"]
    for n in ((1, "i"), (3, "r")):
        q = Pattern({"x0": n[1], "x1": "a", "x2": "i"}, [("x0", "x1"), ("x1", "x2")])
        got = sorted((r.n_0, r.n_1, r.n_2, round(r.p, 6)) for r in path_index.on_demand(eg, [n[1], "a", "i"], 0.01).collect())
        assert got == sorted((r.x0, r.x1, r.x2, r.p) for r in baselines.direct_sql(eg, q, 0.01).collect()) != []


@pytest.fixture
def written(monkeypatch):
    """The tags of the tables that operators write, in a session without graphs."""
    tags, write = [], path_index.materialise
    monkeypatch.setattr(queries, "_ENGINES", {})
    for module in (engine, entity_graph, path_index):
        monkeypatch.setattr(module, "materialise", lambda df, tag: (tags.append(tag), write(df, tag))[1])
    return tags


def test_late_threshold_builds_the_graph_alone(spark, written):
    """No index, no context and no table of marginals, none of which it reads."""
    queries.QUERIES["baseline_late_threshold_square"](spark, "/root/testdata/sf0.001").collect()
    assert sorted(written) == ["edges", "entities", "labels", "packed", "tied", "worlds"]


def test_reduction_below_beta_builds_no_index(spark, written):
    """The lists of all its covers come from one table of labelled edges."""
    e = queries.engine(spark, "/root/testdata/sf0.001")
    for path in queries.CYCLE_PATHS[3]:
        names, labels = [f"n_{n}" for n in path], [queries.CYCLE5.nodes[n] for n in path]
        found = e.fetch(queries.CYCLE5, path, 0.1).select(*names, F.round(F.col("ple") * F.col("pn"), 6))
        want = path_index.on_demand(e.eg, labels, 0.1).select(*[f"n_{i}" for i in range(len(path))], F.round("p", 6))
        assert sorted(map(tuple, found.collect())) == sorted(map(tuple, want.collect())) != []
    assert written.count("labelled") == 1 and not [t for t in written if t.startswith(("paths", "index", "hist", "marginals"))]


def test_sweep_indexes_its_own_sequences(spark, written):
    """The graphs of a sweep share their entities, and hold the index rows of their patterns alone."""
    d, q = "/root/testdata/sf0.001", queries.TRIANGLE
    a, b = (queries.engine(spark, d, share=x, patterns=(q,)) for x in (0.2, 1.0))
    assert written.count("entities") == 1 and written.count("edges") == 2 and a.eg.entities is b.eg.entities
    whole = path_index.build_path_index(b.eg, 2, 0.3)
    held = lambda df: sorted(tuple(round(v, 9) if isinstance(v, float) else v for v in r) for r in df.collect())
    for labels in (["PROMO", "LARGE"], ["LARGE", "SMALL", "PROMO"]):
        assert held(b.idx.stored(labels, 0.3)) == held(whole.stored(labels, 0.3)) != []
    with pytest.raises(ValueError, match="holds no paths"):
        b.idx.lookup(["SMALL", "SMALL"], 0.5)

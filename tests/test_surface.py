"""What surrounds the methods: files, SQL over a graph, merges of the user's own, kinds of stream windows."""

import pytest
from pyspark.sql import functions as F

from ugraph.functions.merge import MERGES, noisy_or, register_merge
from ugraph.operators.engine import Engine
from ugraph.operators.entity_graph import build_entity_graph, merge_edges
from ugraph.operators.path_index import build_path_index
from ugraph.plans.pattern import Pattern
from ugraph.sources import files, testgraphs
from ugraph.sqlapi import SqlSession
from ugraph.streaming.edges import once, pair_probabilities, run_stream, session_users, windowed_users


def held(df):
    return sorted(tuple(round(v, 9) if isinstance(v, float) else v for v in r) for r in df.collect())


def test_edge_list(spark, tmp_path):
    (tmp_path / "e.txt").write_text("# from to p\n1\t2\t0.5\n2\t1\t0.7\n3\t3\t1\n4\t2\n\nx\t2\t0.1\n")
    assert held(files.read_edge_list(spark, f"{tmp_path}/e.txt")) == [(1, 2, 0.7), (2, 4, 1.0)]
    assert held(files.read_edge_list(spark, f"{tmp_path}/e.txt", directed=True)) == [(1, 2, 0.5), (2, 1, 0.7), (4, 2, 1.0)]


@pytest.mark.parametrize("kind", ["parquet", "json"])
def test_graph_round_trip(spark, tmp_path, kind):
    rg = testgraphs.tiny(spark)
    files.save_reference_graph(rg, f"{tmp_path}/g", kind)
    back = files.load_reference_graph(spark, f"{tmp_path}/g", kind=kind).validate()
    for name in ("labels", "edges"):
        assert held(getattr(back, name)) == held(getattr(rg, name).select(getattr(back, name).columns))
    assert sorted(map(str, back.sets.select("members", "p").collect())) == sorted(map(str, rg.sets.select(F.col("members").cast("array<long>"), "p").collect()))


def test_sql_and_export(spark, tmp_path):
    engine = Engine(*(lambda eg: (eg, build_path_index(eg, 2, 0.05)))(build_entity_graph(testgraphs.tiny(spark))))
    label = {r.label for r in engine.eg.labels.select("label").distinct().collect()}
    a, b = sorted(label)[:2]
    text = f"(x:{a})-(y:{b})"
    want = engine.match(Pattern.parse(text), 0.05)
    session = SqlSession(engine, "t_")
    got = session.sql(f"SELECT m.x, m.y, m.p FROM match_pattern('{text}', 0.05, 1) m JOIN t_entities e ON e.entity_id = m.x")
    assert held(got) == held(want.select("x", "y", "p"))
    both = session.sql(f"SELECT count(*) FROM match_pattern('{text}', 0.05) m JOIN match_pattern('{text}', 5e-2) n USING (x, y)")
    assert both.first()[0] == want.count()
    assert session.sql("SELECT count(*) FROM t_paths_1").first()[0] == engine.idx.paths[1].count()
    with pytest.raises(ValueError):
        session.sql("SELECT * FROM match_pattern(1)")
    files.write_matches(want, f"{tmp_path}/m", "csv")
    assert spark.read.csv(f"{tmp_path}/m", header=True).count() == want.count()


def test_own_merges(spark):
    rg = testgraphs.tiny(spark)
    register_merge("sure", noisy_or(1.0))
    register_merge("middle", lambda p, n: F.median(p))
    try:
        assert held(merge_edges(rg, "sure")) == held(merge_edges(rg, "disjunct"))
        weaker = {r[:2]: r[2] for r in held(merge_edges(rg, "noisy_or"))}
        full = {r[:2]: r[2] for r in held(merge_edges(rg, "disjunct"))}
        assert weaker.keys() == full.keys() and all(weaker[k] < full[k] for k in full)
        assert len(held(merge_edges(rg, "middle"))) == len(full)
    finally:
        del MERGES["sure"], MERGES["middle"]


def test_windows_of_streams(spark, tmp_path):
    rows = [("a", m, u) for m, u in ((0, 1), (10, 2), (25, 3), (70, 1), (75, 4), (300, 9))]
    events = spark.createDataFrame(rows, "event_type string, m int, user_id long").selectExpr("event_type", "timestamp '2024-01-01 00:00:00' + make_dt_interval(0, 0, m) AS ts", "user_id")
    minutes = F.round((F.unix_timestamp("hour") - F.unix_timestamp(F.lit("2024-01-01 00:00:00"))) / 60).cast("int")
    sessions = session_users(events).select(minutes.alias("m"), "users")
    assert sorted((r.m, r.users) for r in sessions.collect()) == [(0, [1, 2, 3]), (70, [1, 4]), (300, [9])]
    sliding = {r.m: r.users for r in windowed_users(events, "1 hour", slide="30 minutes").select(minutes.alias("m"), "users").collect()}
    assert sliding[-30] == sliding[0] == [1, 2, 3] and sliding[30] == sliding[60] == [1, 4]
    events.unionByName(events).write.parquet(f"{tmp_path}/in")
    stream = once(spark.readStream.schema(events.schema).parquet(f"{tmp_path}/in"), ["event_type", "ts", "user_id"], "1 hour")
    run_stream(stream, f"{tmp_path}/out", f"{tmp_path}/ck", late=None, users=session_users).awaitTermination()
    got = spark.read.parquet(f"{tmp_path}/out").select(minutes.alias("m"), "users")
    assert sorted((r.m, r.users) for r in got.collect()) == [(0, [1, 2, 3]), (70, [1, 4])]
    assert once(events.unionByName(events), ["event_type", "ts", "user_id"], "1 hour").count() == len(rows)
    counts = spark.createDataFrame([(1, 2, 1), (1, 3, 2)], "src long, dst long, n long")
    assert held(pair_probabilities(counts)) == [(1, 2, 0.5), (1, 3, 0.75)]

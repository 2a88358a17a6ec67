"""Worked examples, the possible-worlds oracle and the planner's formulas."""

import itertools

import pytest
from pyspark.sql import functions as F

from ugraph.functions.merge import MERGES
from ugraph.operators import baselines
from ugraph.operators.engine import Engine, MatchOptions
from ugraph.operators.entity_graph import ReferenceGraph, build_entity_graph
from ugraph.operators.identity import component_marginals, component_worlds, exact_covers
from ugraph.operators.path_index import build_path_index, estimate_count
from ugraph.plans.decompose import assign_ownership, decompose, join_predicates
from ugraph.plans.pattern import Pattern, path_chords, path_degree, path_density, path_neighbours, random_pattern, reverse_neighbours
from ugraph.sources import testgraphs

EXPERT = Pattern.parse("(x0:r)-(x1:a)-(x2:i)")


@pytest.fixture(scope="module")
def tiny(spark):
    eg = build_entity_graph(testgraphs.tiny(spark))
    return Engine(eg, build_path_index(eg, 2, 0.05))


def rows(df):
    return {(r.x0, r.x1, r.x2): (round(r.ple, 6), round(r.pn, 6), round(r.p, 6)) for r in df.collect()}


def test_expert_example(tiny):
    got = rows(tiny.match(EXPERT, 0.02))
    big = 1_000_000_003
    assert got == {(1, 2, 4): (0.1125, 0.2, 0.0225), (1, 2, big): (0.084375, 0.8, 0.0675), (3, 2, 1): (0.675, 0.2, 0.135), (3, 2, 4): (0.5, 0.2, 0.1), (big, 2, 1): (0.253125, 0.8, 0.2025)}
    assert len(rows(tiny.match(EXPERT, 0.2))) == 1
    assert len(rows(tiny.match(EXPERT, 0.1))) == 3
    assert rows(tiny.match(EXPERT, 0.25)) == {}


@pytest.mark.parametrize("o", [MatchOptions(L=1), MatchOptions(reduction="none"), MatchOptions(decomposition="random", L=1), MatchOptions(node_context=False, path_context=False, L=1, incremental=False), MatchOptions(decomposition="exact")])
def test_variants_agree(tiny, o):
    assert rows(tiny.match(EXPERT, 0.05, o)) == rows(tiny.match(EXPERT, 0.05))


def test_against_possible_worlds(tiny):
    labels = {1: {"i": 0.75, "r": 0.25}, 2: {"a": 1.0}, 3: {"r": 1.0}, 4: {"i": 1.0}}
    sets = [(frozenset({1}), 1.0), (frozenset({2}), 1.0), (frozenset({3}), 0.4), (frozenset({4}), 0.4), (frozenset({3, 4}), 0.8)]
    worlds = baselines.possible_worlds(labels, {(1, 2): 0.9, (2, 3): 1.0, (2, 4): 0.5}, sets, EXPERT, 0.02)
    assert {m: round(p, 6) for m, p in worlds.items()} == {m: p for m, (_, _, p) in rows(tiny.match(EXPERT, 0.02)).items()}


def test_overlapping_sets(spark):
    members = [[1], [2], [3], [4], [1, 2], [2, 3], [3, 4]]
    p = [0.5] * 4 + [0.6, 0.7, 0.8]
    df = spark.createDataFrame([(1, i, m, q, i) for i, (m, q) in enumerate(zip(members, p))], "comp_id long, entity_id long, refs array<long>, p double, bit int")
    worlds = component_worlds(df)
    got = {r["mask"]: round(r["p"], 6) for r in worlds.collect()}
    assert got == {0b1111: 0.093928, 0b1000011: 0.240457, 0b101001: 0.1841, 0b11100: 0.135257, 0b1010000: 0.346258}
    marg = {r["mask"]: round(r["p"], 6) for r in component_marginals(worlds).collect()}
    assert marg[1 << 6] == 0.586715 and marg[0b1010000] == 0.346258 and 0b110000 not in marg
    assert len(exact_covers([1, 2, 3, 4], [(i, frozenset(m)) for i, m in enumerate(members)])) == 5


def test_merges(spark):
    df = spark.createDataFrame([(1.0, 2), (0.5, 2)], "p double, n int")
    assert df.agg(MERGES["average"](F.col("p"), F.col("n"))).first()[0] == 0.75
    assert df.agg(MERGES["disjunct"](F.col("p"), F.col("n"))).first()[0] == 1.0
    assert df.limit(1).agg(MERGES["average"](F.col("p"), F.col("n"))).first()[0] == 0.5


def test_validation(spark):
    bad = ReferenceGraph(spark.createDataFrame([(1, "a", 0.4)], "ref_id long, label string, p double"), spark.createDataFrame([], "src long, dst long, p double"), spark.createDataFrame([], "set_id long, members array<long>, p double"))
    with pytest.raises(ValueError, match="sum to 1"):
        bad.validate()


def test_path_statistics():
    q = Pattern({str(i): "a" for i in range(1, 7)}, [("1", "2"), ("2", "3"), ("3", "4"), ("1", "3"), ("3", "5"), ("4", "5"), ("2", "6")])
    p = ("1", "2", "3", "4")
    assert path_degree(q, p) == 5 and path_density(q, p) == pytest.approx(4 / 6)
    assert path_neighbours(q, p) == {"5", "6"} and reverse_neighbours(q, p, "5") == {"3", "4"} and path_chords(q, p) == [("1", "3")]
    nodes, edges = assign_ownership(q, [p, ("3", "5", "4")])
    assert nodes == [list(p), ["5"]] and len(edges[1]) == 2
    assert join_predicates([p, ("3", "5", "4")]) == {(0, 1): ["3", "4"]}


@pytest.mark.parametrize("strategy", ["greedy", "random", "exact"])
def test_cover(strategy):
    for n, m, seed in itertools.product((3, 5), (4, 7), range(3)):
        q = random_pattern(n, m, ["a", "b"], seed)
        d = decompose(q, 2, lambda p: 10.0 ** len(p), strategy)
        assert {e for p in d.paths for e in q.path_edges(p)} == set(q.edges)


def test_estimate():
    assert estimate_count([(0.1, 100.0), (0.2, 25.0)], 0.15) == pytest.approx(50)
    assert estimate_count([(0.1, 10.0), (0.2, 0.0)], 0.15) == pytest.approx(5)


def test_disconnected_pattern():
    with pytest.raises(ValueError):
        Pattern({"a": "x", "b": "y"}, [])

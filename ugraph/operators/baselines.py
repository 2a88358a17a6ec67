"""What the path method is compared with: one relational statement, node-at-a-time joins, ablations and worlds."""

from __future__ import annotations

import itertools
import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.tables import EPS
from ..plans.pattern import Pattern
from .engine import Engine, MatchOptions, product
from .entity_graph import EntityGraph
from .identity import exact_covers, pn_expr


def direct_sql_text(q: Pattern, alpha: float, prefix: str = "", identity: bool = True, conditional: bool = False, limit: int | None = None, parts: bool = False) -> str:
    """One statement over entity_labels, entity_edges, entities and marginals; runs in Spark and elsewhere. ``parts``: with
    the factors of every match (q_node, e_edge, ple, pn), nothing rounded."""
    names = sorted(q.nodes)
    source = [f"{prefix}entity_labels l_{n} JOIN {prefix}entities t_{n} ON t_{n}.entity_id = l_{n}.entity_id AND l_{n}.label = '{q.nodes[n]}'" for n in names]
    edges = []
    for i, (a, b) in enumerate(q.edges):
        more = f" AND e{i}.l_src = '{q.nodes[a]}' AND e{i}.l_dst = '{q.nodes[b]}'" if conditional else ""
        edges.append((f"{prefix}entity_edges e{i}", f"e{i}.src = l_{a}.entity_id AND e{i}.dst = l_{b}.entity_id{more}"))
    joins, placed, text = list(edges), {names[0]}, source[0]
    todo = list(enumerate(q.edges))
    while todo:
        k, (i, (a, b)) = next((k, x) for k, x in enumerate(todo) if placed & set(x[1]))
        todo.pop(k)
        more = f" AND e{i}.l_src = '{q.nodes[a]}' AND e{i}.l_dst = '{q.nodes[b]}'" if conditional else ""
        if {a, b} <= placed:
            text += f" JOIN {joins[i][0]} ON {joins[i][1]}"
        else:
            have, new = (a, b) if a in placed else (b, a)
            ends = ("src", "dst") if have == a else ("dst", "src")
            text += f" JOIN {joins[i][0]} ON e{i}.{ends[0]} = l_{have}.entity_id{more} JOIN {prefix}entity_labels l_{new} ON l_{new}.entity_id = e{i}.{ends[1]} AND l_{new}.label = '{q.nodes[new]}' JOIN {prefix}entities t_{new} ON t_{new}.entity_id = l_{new}.entity_id"
            placed.add(new)
    factors = []
    for i, n in enumerate(names):
        mask = " | ".join([f"t_{n}.mask"] + [f"(CASE WHEN t_{m}.comp_id = t_{n}.comp_id THEN t_{m}.mask ELSE CAST(0 AS BIGINT) END)" for m in names if m != n])
        text += f" LEFT JOIN {prefix}marginals k_{n} ON k_{n}.comp_id = t_{n}.comp_id AND k_{n}.mask = ({mask})"
        before = " OR ".join(f"coalesce(t_{m}.comp_id = t_{n}.comp_id, false)" for m in names[:i]) or "false"
        factors.append(f"(CASE WHEN t_{n}.comp_id IS NULL OR {before} THEN CAST(1 AS DOUBLE) ELSE coalesce(k_{n}.p, CAST(0 AS DOUBLE)) END)")
    ple = " * ".join([f"l_{n}.p" for n in names] + [f"e{i}.p" for i in range(len(q.edges))])
    differ = " AND ".join(f"l_{a}.entity_id <> l_{b}.entity_id" for a, b in itertools.combinations(names, 2)) or "true"
    picked = ", ".join(f"l_{n}.entity_id AS {n}" for n in names)
    if parts:
        picked += "".join(f", l_{n}.p AS q_{n}" for n in names) + "".join(f", e{i}.p AS e_{a}_{b}" for i, (a, b) in enumerate(q.edges))
        return f"SELECT * FROM (SELECT {picked}, {ple} AS ple, {' * '.join(factors)} AS pn FROM {text} WHERE {differ}) a WHERE ple * pn >= CAST({alpha} AS DOUBLE) - CAST({EPS} AS DOUBLE)"
    inner = f"SELECT {picked}, {ple} AS ple, {' * '.join(factors)} AS pn FROM {text} WHERE {differ}"
    p = "ple * pn" if identity else "CASE WHEN pn > 0 THEN ple ELSE 0 END"
    tail = f" ORDER BY p DESC, {', '.join(names)} LIMIT {limit}" if limit else ""
    return f"SELECT {', '.join(names)}, round(p, 6) AS p FROM (SELECT *, {p} AS p FROM ({inner}) a) b WHERE p >= CAST({alpha} AS DOUBLE) - CAST({EPS} AS DOUBLE){tail}"


def _entering(q: Pattern) -> list[tuple[str, list[str]]]:
    """The pattern's nodes in the order of the joins, each with its neighbours placed before it."""
    names = sorted(q.nodes, key=lambda n: (-q.degree(n), n))
    order = [names[0]]
    while len(order) < len(names):
        order.append(next(n for n in names if n not in order and q.near[n] & set(order)))
    return [(n, sorted(q.near[n] & set(order[:i]))) for i, n in enumerate(order)]


def nested_sql_text(q: Pattern, alpha: float, prefix: str = "", identity: bool = True, conditional: bool = False) -> str:
    """The statement of ``direct_sql_text`` as nested steps. Each node comes with all its edges to the nodes before it and
    their labels, as one table of its own, and what the end asks of the product holds of every part of it, since no factor
    exceeds 1. Existence enters last."""
    names, least = sorted(q.nodes), f"CAST({alpha} AS DOUBLE) - CAST({EPS} AS DOUBLE)"
    text, have = "", []
    for n, ends in _entering(q):
        f, tests, source = f"l_{n}.p", [f"l_{n}.label = '{q.nodes[n]}'"], f"{prefix}entity_labels l_{n}"
        for m in ends:
            a, b = q.key(m, n)
            own, far = ("dst", "src") if b == n else ("src", "dst")
            more = f" AND e_{m}.l_src = '{q.nodes[a]}' AND e_{m}.l_dst = '{q.nodes[b]}'" if conditional else ""
            source += f" JOIN {prefix}entity_edges e_{m} ON e_{m}.{own} = l_{n}.entity_id{more} LEFT SEMI JOIN {prefix}entity_labels s_{m} ON s_{m}.entity_id = e_{m}.{far} AND s_{m}.label = '{q.nodes[m]}'"
            tests.append(f"e_{m}.p >= {least}")
            f += f" * e_{m}.p"
        far = {m: f"e_{m}.{'src' if q.key(m, n)[1] == n else 'dst'}" for m in ends}
        step = f"SELECT l_{n}.entity_id AS {n}, {', '.join([f'{far[m]} AS {m}' for m in ends] + [f'{f} AS f'])} FROM {source} WHERE {' AND '.join([*tests, f'{f} >= {least}'])}"
        if not have:
            text = f"SELECT {n}, f AS ple FROM ({step}) a"
        else:
            on = " AND ".join(f"r.{m} = s.{m}" for m in ends)
            differ = "".join(f" AND r.{m} <> s.{n}" for m in have)
            text = f"SELECT {', '.join(f'r.{m}' for m in have)}, s.{n}, r.ple * s.f AS ple FROM ({text}) r JOIN ({step}) s ON {on} WHERE r.ple * s.f >= {least}{differ}"
        have.append(n)
    source, factors = f"({text}) x", []
    for n in names:
        source += f" JOIN {prefix}entities t_{n} ON t_{n}.entity_id = x.{n}"
    for i, n in enumerate(names):
        mask = " | ".join([f"t_{n}.mask"] + [f"(CASE WHEN t_{m}.comp_id = t_{n}.comp_id THEN t_{m}.mask ELSE CAST(0 AS BIGINT) END)" for m in names if m != n])
        source += f" LEFT JOIN {prefix}marginals k_{n} ON k_{n}.comp_id = t_{n}.comp_id AND k_{n}.mask = ({mask})"
        before = " OR ".join(f"coalesce(t_{m}.comp_id = t_{n}.comp_id, false)" for m in names[:i]) or "false"
        factors.append(f"(CASE WHEN t_{n}.comp_id IS NULL OR {before} THEN CAST(1 AS DOUBLE) ELSE coalesce(k_{n}.p, CAST(0 AS DOUBLE)) END)")
    p = "ple * pn" if identity else "CASE WHEN pn > 0 THEN ple ELSE 0 END"
    inner = f"SELECT {', '.join(f'x.{n}' for n in names)}, x.ple, {' * '.join(factors)} AS pn FROM {source}"
    return f"SELECT {', '.join(names)}, round(p, 6) AS p FROM (SELECT *, {p} AS p FROM ({inner}) a) b WHERE p >= {least}"


def direct_sql(eg: EntityGraph, q: Pattern, alpha: float, identity: bool = True) -> DataFrame:
    prefix = f"g{uuid.uuid4().hex[:8]}_"
    eg.register(prefix)
    return eg.labels.sparkSession.sql(nested_sql_text(q, alpha, prefix, identity, eg.conditional))


def late_threshold(eg: EntityGraph, engine: Engine, q: Pattern, alpha: float) -> DataFrame:
    """Node-at-a-time joins on the structure alone; the threshold holds at the end. A node comes with all its edges to the
    nodes before it, between the labels that the pattern asks for; rows hold entity ids and one product, and the worlds
    are joined to what passes."""
    rows, have = None, []
    labelled = lambda n: eg.labels.filter(F.col("label") == q.nodes[n]).select(F.col("entity_id").alias(f"n_{n}"), F.col("p").alias("f"))
    for n, ends in _entering(q):
        step = labelled(n)
        for m in ends:
            a, b = q.key(m, n)
            e = eg.edges.filter((F.col("l_src") == q.nodes[a]) & (F.col("l_dst") == q.nodes[b])) if eg.conditional else eg.edges
            e = e.select(F.col("src").alias(f"n_{a}"), F.col("dst").alias(f"n_{b}"), F.col("p").alias("pe"))
            e = e.join(labelled(m).select(f"n_{m}"), f"n_{m}", "left_semi")
            step = step.join(e, f"n_{n}").withColumn("f", F.col("f") * F.col("pe")).drop("pe")
        if rows is None:
            rows = step.withColumnRenamed("f", "ple")
        else:
            rows = rows.join(step, [f"n_{m}" for m in ends]).withColumn("ple", F.col("ple") * F.col("f")).drop("f")
            for x in have:
                rows = rows.filter(F.col(f"n_{x}") != F.col(f"n_{n}"))
        have.append(n)
    rows = rows.filter(F.col("ple") >= alpha - EPS)
    for n in have:
        rows = rows.join(eg.entities.select(F.col("entity_id").alias(f"n_{n}"), F.col("comp_id").alias(f"c_{n}"), F.col("mask").alias(f"m_{n}"), F.col("worlds").alias(f"w_{n}")), f"n_{n}")
    return engine.finalise(q, rows.withColumn("pn", pn_expr(sorted(q.nodes))), alpha, MatchOptions())


def node_at_a_time(eg: EntityGraph, engine: Engine, q: Pattern, alpha: float, early: bool = True) -> DataFrame:
    """Candidates of single nodes, joined edge by edge; the threshold holds at every step, or (early off) at the end."""
    if not early:
        return late_threshold(eg, engine, q, alpha)
    order = [n for n, _ in _entering(q)]
    nodes = eg.nodes()

    def node(n):
        rows = nodes.filter(F.col("label") == q.nodes[n]).join(engine.node_candidates(q, n, alpha), "e", "left_semi")
        return rows.select(*[F.col(a).alias(f"{b}_{n}") for a, b in (("e", "n"), ("q", "q"), ("c", "c"), ("m", "m"), ("w", "w"))])

    rows, have, es = node(order[0]), [order[0]], []
    for n in order[1:]:
        joined = False
        for m in sorted(q.near[n] & set(have)):
            a, b = q.key(n, m)
            e = eg.edges.filter((F.col("l_src") == q.nodes[a]) & (F.col("l_dst") == q.nodes[b])) if eg.conditional else eg.edges
            e = e.select(F.col("src").alias(f"n_{a}"), F.col("dst").alias(f"n_{b}"), F.col("p").alias(f"e_{a}_{b}"))
            rows = rows.join(e, [f"n_{a}", f"n_{b}"] if joined else [f"n_{m}"])
            joined = True
            es.append(f"e_{a}_{b}")
        rows = rows.join(node(n), f"n_{n}")
        for x in have:
            rows = rows.filter(F.col(f"n_{x}") != F.col(f"n_{n}"))
        have.append(n)
        rows = rows.filter(product([F.col(f"q_{x}") for x in have] + [F.col(e) for e in es]) * pn_expr(have) >= alpha - EPS)
    rows = rows.withColumn("ple", product([F.col(f"q_{x}") for x in have] + [F.col(e) for e in es])).withColumn("pn", pn_expr(have))
    return engine.finalise(q, rows, alpha, MatchOptions())


def random_decomposition(engine: Engine, q: Pattern, alpha: float, seed: int = 1) -> DataFrame:
    return engine.match(q, alpha, MatchOptions(decomposition="random", order="matches", seed=seed, reduction="both"))


def no_reduction(engine: Engine, q: Pattern, alpha: float) -> DataFrame:
    return engine.match(q, alpha, MatchOptions(reduction="none"))


def no_identity(engine: Engine, q: Pattern, alpha: float) -> DataFrame:
    return engine.match(q, alpha, MatchOptions(identity=False))


def possible_worlds(labels: dict[int, dict[str, float]], edges: dict[tuple[int, int], float], sets: list[tuple[frozenset, float]], q: Pattern, alpha: float, offset: int = 1_000_000_000):
    """Matches by summing over all worlds of a tiny graph: references covered once, every label, every edge.

    labels: reference -> distribution; edges: unordered pair -> probability; sets: (members, p), singletons included;
    a set's entity id is its reference, or offset plus its least member."""
    ents = {(min(m) if len(m) == 1 else offset + min(m)): (m, p) for m, p in sets}
    lab = {e: {s: sum(labels[r].get(s, 0) for r in m) / len(m) for r0 in m for s in labels[r0]} for e, (m, _) in ents.items()}
    prob = lambda a, b: sum(edges.get((min(r, s), max(r, s)), 0) for r in ents[a][0] for s in ents[b][0]) / len(ents[a][0]) / len(ents[b][0])
    covers = exact_covers(sorted(labels), [(e, m) for e, (m, _) in ents.items()])
    weight = {c: 1.0 for c in covers}
    for c in covers:
        for e in c:
            weight[c] *= ents[e][1] ** len(ents[e][0])
    z = sum(weight.values())
    names, found = sorted(q.nodes), {}
    for c in covers:
        pairs = [(a, b) for a, b in itertools.combinations(c, 2) if prob(a, b) > 0]
        for present in itertools.product((0, 1), repeat=len(pairs)):
            pe = 1.0
            for (a, b), on in zip(pairs, present, strict=True):
                pe *= prob(a, b) if on else 1 - prob(a, b)
            if not pe:
                continue
            on = {frozenset(x) for x, o in zip(pairs, present, strict=True) if o}
            for choice in itertools.product(*(lab[e].items() for e in c)):
                pl = 1.0
                for _, v in choice:
                    pl *= v
                label = {e: s for e, (s, _) in zip(c, choice, strict=True)}
                for m in itertools.permutations(c, len(names)):
                    of = dict(zip(names, m, strict=True))
                    if all(label[of[n]] == q.nodes[n] for n in names) and all(frozenset((of[a], of[b])) in on for a, b in q.edges):
                        found[m] = found.get(m, 0.0) + weight[c] / z * pe * pl
    return {m: p for m, p in found.items() if p >= alpha - EPS}

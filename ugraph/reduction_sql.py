"""The candidate lists and their joint reduction as one SQL statement with unrolled rounds: an answer of its own to check
the engine's. It knows no index: lists are joins over the entity tables."""

from __future__ import annotations

import itertools

from .functions.tables import EPS
from .operators.baselines import direct_sql_text
from .plans.decompose import Decomposition
from .plans.pattern import Pattern, node_label_counts, path_chords, path_neighbours, reverse_neighbours

ROUNDS = 12


def path_pattern(q: Pattern, path: tuple[str, ...]) -> Pattern:
    return Pattern({n: q.nodes[n] for n in path}, q.path_edges(path), q.directed)


def edge_name(e: tuple[str, str]) -> str:
    return f"e_{e[0]}_{e[1]}"


def node_cte(q: Pattern, n: str, alpha: float) -> str:
    """cn_n: entities that have enough neighbours of each label at sufficient probability."""
    need = [(label, k) for (m, label), k in sorted(node_label_counts(q).items()) if m == n]
    joins = "".join(f" JOIN context c{i} ON c{i}.e = l.entity_id AND c{i}.label = '{s}' AND c{i}.n >= {k}" for i, (s, k) in enumerate(need))
    tests = "".join(f" AND l.p * pow(c{i}.fpu, {k}) >= {alpha} - {EPS}" for i, (_, k) in enumerate(need))
    return f"cn_{n} AS MATERIALIZED (SELECT l.entity_id AS e FROM entity_labels l{joins} WHERE l.label = '{q.nodes[n]}' AND l.p >= {alpha} - {EPS}{tests})"


def list_ctes(q: Pattern, path: tuple[str, ...], i: int, alpha: float) -> list[str]:
    """raw_i: the paths of probability alpha; cand_i: those whose nodes and surroundings allow a match."""
    need = sorted({(n, q.nodes[m]) for m in path_neighbours(q, path) for n in reverse_neighbours(q, path, m)})
    joins = "".join(f" JOIN context k_{n}_{s} ON k_{n}_{s}.e = r.{n} AND k_{n}_{s}.label = '{s}'" for n, s in need)
    joins += "".join(f" JOIN entity_edges h_{a}_{b} ON h_{a}_{b}.src = r.{a} AND h_{a}_{b}.dst = r.{b}" for a, b in path_chords(q, path))
    bounds = []
    for m in sorted(path_neighbours(q, path)):
        ends, s = sorted(reverse_neighbours(q, path, m)), q.nodes[m]
        bounds.append("least(" + ", ".join(" * ".join([f"k_{n}_{s}.fpu", *[f"k_{x}_{s}.ppu" for x in ends if x != n]]) for n in ends) + ")")
    bound = " * ".join(["r.ple * r.pn", *bounds, *[f"h_{a}_{b}.p" for a, b in path_chords(q, path)]])
    inside = " AND ".join(f"r.{n} IN (SELECT e FROM cn_{n})" for n in path)
    return [
        f"raw_{i} AS MATERIALIZED ({direct_sql_text(path_pattern(q, path), alpha, parts=True)})",
        f"cand_{i} AS MATERIALIZED (SELECT row_number() OVER () AS vid, r.* FROM raw_{i} r{joins} WHERE {inside} AND {bound} >= {alpha} - {EPS})",
    ]


def link_cte(q: Pattern, d: Decomposition, i: int, j: int, alpha: float) -> str:
    a, b = d.paths[i], d.paths[j]
    shared, names = [n for n in b if n in a], [*a, *[n for n in b if n not in a]]
    at = {n: f"a.{n}" if n in a else f"b.{n}" for n in names}
    on = " AND ".join([f"a.{n} = b.{n}" for n in shared] + [f"{at[x]} <> {at[y]}" for x, y in itertools.combinations(names, 2)])
    edges_a = q.path_edges(a)
    ple = " * ".join([f"{'a' if n in a else 'b'}.q_{n}" for n in names] + [f"a.{edge_name(e)}" for e in edges_a] + [f"b.{edge_name(e)}" for e in q.path_edges(b) if e not in edges_a])
    text, factors = f"cand_{i} a JOIN cand_{j} b ON {on}", []
    text += "".join(f" JOIN entities t_{n} ON t_{n}.entity_id = {at[n]}" for n in names)
    for k, n in enumerate(names):
        mask = " | ".join([f"t_{n}.mask"] + [f"(CASE WHEN t_{m}.comp_id = t_{n}.comp_id THEN t_{m}.mask ELSE CAST(0 AS BIGINT) END)" for m in names if m != n])
        text += f" LEFT JOIN marginals k_{n} ON k_{n}.comp_id = t_{n}.comp_id AND k_{n}.mask = ({mask})"
        before = " OR ".join(f"coalesce(t_{m}.comp_id = t_{n}.comp_id, false)" for m in names[:k]) or "false"
        factors.append(f"(CASE WHEN t_{n}.comp_id IS NULL OR {before} THEN CAST(1 AS DOUBLE) ELSE coalesce(k_{n}.p, CAST(0 AS DOUBLE)) END)")
    return f"link_{i}_{j} AS MATERIALIZED (SELECT a.vid AS v{i}, b.vid AS v{j} FROM {text} WHERE {ple} * {' * '.join(factors)} >= {alpha} - {EPS})"


def round_ctes(q: Pattern, d: Decomposition, alpha: float, tag: str, structure: bool, bounds: bool, rounds: int = ROUNDS) -> list[str]:
    """<tag>_i: the vertices of list i that are left after the rounds, from those of the lists."""
    k = len(d.paths)
    slots = [f"s{x}" for x in range(k)]
    out = []
    for i in range(k):
        w1 = " * ".join([f"q_{n}" for n in d.owned_nodes[i]] + [edge_name(e) for e in d.owned_edges[i]]) or "1.0"
        out.append(f"{tag}_0_{i} AS MATERIALIZED (SELECT vid, pn AS w2, " + ", ".join(f"CAST({w1 if x == i else '1.0'} AS DOUBLE) AS s{x}" for x in range(k)) + f" FROM cand_{i})")
    for r in range(rounds):
        for i in range(k):
            heard = []
            for j in d.neighbours(i):
                best = ", ".join(f"max({s}) AS {s}" for s in slots)
                heard.append(f"{'JOIN' if structure else 'LEFT JOIN'} (SELECT l.v{i} AS vid, {best} FROM link_{min(i, j)}_{max(i, j)} l JOIN {tag}_{r}_{j} o ON o.vid = l.v{j} GROUP BY l.v{i}) h{j} ON h{j}.vid = v.vid")
            new = [f"v.{s}" if x == i or not bounds else f"least({', '.join([f'v.{s}', *[f'coalesce(h{j}.{s}, v.{s})' for j in d.neighbours(i)]])})" for x, s in enumerate(slots)]
            inner = f"SELECT v.vid, v.w2, {', '.join(f'{e} AS {s}' for e, s in zip(new, slots, strict=True))} FROM {tag}_{r}_{i} v {' '.join(heard)}"
            test = f" WHERE {' * '.join(slots)} * w2 >= {alpha} - {EPS}" if bounds else ""
            out.append(f"{tag}_{r + 1}_{i} AS MATERIALIZED (SELECT * FROM ({inner}) z{test})")
    return out + [f"{tag}_{i} AS (SELECT * FROM {tag}_{rounds}_{i})" for i in range(k)]


def reduction_ctes(q: Pattern, d: Decomposition, alpha: float, context: str, modes: dict[str, tuple[bool, bool]]) -> str:
    """``context``, the lists, their links, and for each tag of ``modes`` (structure, bounds) the reduced lists."""
    parts = [context, *[node_cte(q, n, alpha) for n in q.nodes]]
    parts += [x for i, p in enumerate(d.paths) for x in list_ctes(q, p, i, alpha)]
    parts += [link_cte(q, d, i, j, alpha) for i, j in d.predicates]
    return ", ".join(parts + [x for tag, (s, b) in modes.items() for x in round_ctes(q, d, alpha, tag, s, b)])

"""Query patterns and what the planner reads off them; all of it is driver-side and independent of the data."""

from __future__ import annotations

import random
import re
from dataclasses import dataclass, field


def edge(a: str, b: str) -> tuple[str, str]:
    return (a, b) if a <= b else (b, a)


@dataclass(frozen=True)
class Pattern:
    """nodes: name -> label; edges: pairs of names."""

    nodes: dict[str, str]
    edges: list[tuple[str, str]]
    directed: bool = False
    near: dict[str, set[str]] = field(init=False, compare=False, default_factory=dict)

    def __post_init__(self):
        for n in self.nodes:
            self.near[n] = set()
        for a, b in self.edges:
            if a == b or a not in self.nodes or b not in self.nodes:
                raise ValueError(f"bad pattern edge {a}-{b}")
            self.near[a].add(b)
            self.near[b].add(a)
        seen, open_ = set(), [next(iter(self.nodes))]
        while open_:
            n = open_.pop()
            if n not in seen:
                seen.add(n)
                open_ += self.near[n]
        if seen != set(self.nodes):
            raise ValueError("the pattern is not connected")

    @staticmethod
    def parse(text: str) -> "Pattern":
        """``(x:a)-(y:b)-(z:c), (x)-(z)``; ``->`` makes a directed pattern."""
        nodes, edges, directed = {}, [], "->" in text
        for chain in text.split(","):
            last = None
            for name, label, arrow in re.findall(r"\(\s*(\w+)\s*(?::\s*([^)]+?)\s*)?\)\s*(->|-)?", chain):
                if label:
                    nodes[name] = label
                if last:
                    edges.append((last, name) if directed else edge(last, name))
                last = name if arrow else None
        return Pattern(nodes, edges, directed)

    def key(self, a: str, b: str) -> tuple[str, str]:
        """The pattern's edge between two neighbours, as stored."""
        return (a, b) if (a, b) in self.edges else (b, a)

    def degree(self, n: str) -> int:
        return len(self.near[n])

    def path_edges(self, path: tuple[str, ...]) -> list[tuple[str, str]]:
        return [self.key(a, b) for a, b in zip(path, path[1:])]


def enumerate_query_paths(q: Pattern, most: int) -> list[tuple[str, ...]]:
    """Simple paths of 1 to ``most`` edges, each once; a single node for a pattern of one. Directed: along the edges."""
    if len(q.nodes) == 1:
        return [tuple(q.nodes)]
    found, level = [], [(n,) for n in q.nodes]
    for _ in range(most):
        level = [(*p, n) for p in level for n in sorted(q.near[p[-1]]) if n not in p and (not q.directed or (p[-1], n) in q.edges)]
        found += [p for p in level if q.directed or p[0] < p[-1]]
    return found


def path_chords(q: Pattern, path: tuple[str, ...]) -> list[tuple[str, str]]:
    """Pattern edges between nodes of the path that the path itself lacks."""
    own = set(q.path_edges(path))
    return [e for e in q.edges if e not in own and e[0] in path and e[1] in path]


def path_degree(q: Pattern, path: tuple[str, ...]) -> int:
    return sum(q.degree(n) for n in path) - 2 * (len(path) - 1)


def path_density(q: Pattern, path: tuple[str, ...]) -> float:
    m = len(path)
    return 1.0 if m < 2 else 2 * (m - 1 + len(path_chords(q, path))) / (m * (m - 1))


def path_neighbours(q: Pattern, path: tuple[str, ...]) -> set[str]:
    return {n for p in path for n in q.near[p]} - set(path)


def reverse_neighbours(q: Pattern, path: tuple[str, ...], m: str) -> set[str]:
    return q.near[m] & set(path)


def node_label_counts(q: Pattern) -> dict[tuple[str, str], int]:
    """How many neighbours of each label a pattern node needs."""
    out: dict[tuple[str, str], int] = {}
    for n in q.nodes:
        for m in q.near[n]:
            out[n, q.nodes[m]] = out.get((n, q.nodes[m]), 0) + 1
    return out


SHAPES = {
    "wedge": [(0, 1), (1, 2)], "path3": [(0, 1), (1, 2), (2, 3)], "triangle": [(0, 1), (1, 2), (0, 2)], "square": [(0, 1), (1, 2), (2, 3), (0, 3)],
    "star3": [(0, 1), (0, 2), (0, 3)], "tree7": [(0, 1), (0, 2), (1, 3), (1, 4), (2, 5), (2, 6)], "cycle5": [(0, 1), (1, 2), (2, 3), (3, 4), (0, 4)],
    "clique4": [(0, 1), (0, 2), (0, 3), (1, 2), (1, 3), (2, 3)], "edge": [(0, 1)],
}


def shape(name: str, labels: list[str]) -> Pattern:
    n = max(max(e) for e in SHAPES[name]) + 1
    return Pattern({f"x{i}": labels[i % len(labels)] for i in range(n)}, [edge(f"x{a}", f"x{b}") for a, b in SHAPES[name]])


def random_pattern(n: int, m: int, labels: list[str], seed: int) -> Pattern:
    """A connected pattern of n nodes and min(m, n(n-1)/2) edges: a random tree, then random further edges."""
    rng = random.Random(f"{n},{m},{seed}")
    names = [f"x{i:02d}" for i in range(n)]
    edges = {edge(names[i], names[rng.randrange(i)]) for i in range(1, n)}
    rest = [edge(a, b) for i, a in enumerate(names) for b in names[:i] if edge(a, b) not in edges]
    rng.shuffle(rest)
    edges |= set(rest[: max(0, min(m, n * (n - 1) // 2) - len(edges))])
    return Pattern({x: rng.choice(labels) for x in names}, sorted(edges))

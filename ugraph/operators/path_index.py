"""The path index: all paths up to a length whose probability reaches beta, by label sequence and probability."""

from __future__ import annotations

import json
import threading
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.tables import EPS, materialise
from .entity_graph import EntityGraph
from .identity import marginal_on_demand, pn_expr

#: What the index keeps of each node: entity, label, label probability, component, mask. The worlds of components, which
#: scoring needs, are joined from their own small table.
PER_NODE = ("n", "l", "q", "c", "m")
#: Paths of one index file, about.
FILE_ROWS = 250_000


def with_worlds(df: DataFrame, eg: EntityGraph, names: list[str]) -> DataFrame:
    """``df`` with w_x, the worlds of node x's component, for each name. Nodes without one get keys of their own, so that
    they don't meet in one place."""
    for x in names:
        key = F.coalesce(F.col(f"c_{x}"), -1 - F.pmod(F.col(f"n_{x}"), F.lit(4096)))
        df = df.withColumn("comp_key", key).join(eg.packed.select(F.col("comp_id").alias("comp_key"), F.col("worlds").alias(f"w_{x}")), "comp_key", "left").drop("comp_key")
    return df


def _node(eg: EntityGraph, i, label: str | None = None) -> DataFrame:
    rows = eg.nodes() if label is None else eg.nodes().filter(F.col("label") == label)
    return rows.select(*[F.col(a).alias(f"{b}_{i}") for a, b in (("e", "n"), ("label", "l"), ("q", "q"), ("c", "c"), ("m", "m"), ("w", "w"))])


def _scored(df: DataFrame, length: int, beta: float) -> DataFrame:
    names = [str(i) for i in range(length + 1)]
    df = df.withColumn("pn", pn_expr(names)).withColumn("p", F.col("ple") * F.col("pn"))
    return df.filter(F.col("p") >= beta - EPS)


def seed_paths(eg: EntityGraph, beta: float, label: str | None = None) -> DataFrame:
    return _scored(_node(eg, 0, label).withColumn("ple", F.col("q_0")), 0, beta)


def extend_paths(paths: DataFrame, eg: EntityGraph, length: int, beta: float, label: str | None = None) -> DataFrame:
    """Paths of ``length`` edges to those of one more. A probability below beta can't rise again. Edges take their far
    nodes along, so that the paths move once; the far node's worlds are all that its part in existence needs."""
    i, j = length, length + 1
    edges = eg.edges.filter(F.col("p") >= beta - EPS).select(F.col("src").alias(f"n_{i}"), F.col("dst").alias(f"n_{j}"), F.col("p").alias(f"e_{i}"), *([F.col("l_src").alias(f"l_{i}"), F.col("l_dst").alias(f"l_{j}")] if eg.conditional else []))
    step = edges.join(_node(eg, j, label), [f"n_{j}", f"l_{j}"] if eg.conditional else [f"n_{j}"]).filter(F.col(f"e_{i}") * F.col(f"q_{j}") >= beta - EPS)
    out = paths.drop("p", *[f"w_{k}" for k in range(i + 1)]).join(step, [f"n_{i}", f"l_{i}"] if eg.conditional else [f"n_{i}"])
    for k in range(j):
        out = out.filter(F.col(f"n_{k}") != F.col(f"n_{j}"))
    out = out.withColumn("ple", F.col("ple") * F.col(f"e_{i}") * F.col(f"q_{j}")).filter(F.col("ple") * F.col("pn") >= beta - EPS)
    beside = F.lit(0).cast("long")  # the mask of the path's other nodes in the far node's component
    for k in range(j):
        beside = beside.bitwiseOR(F.when(F.col(f"c_{k}") == F.col(f"c_{j}"), F.col(f"m_{k}")).otherwise(F.lit(0)))
    worlds = F.col(f"w_{j}")
    joint = marginal_on_demand(worlds, beside.bitwiseOR(F.col(f"m_{j}"))) / F.when(beside == 0, F.lit(1.0)).otherwise(marginal_on_demand(worlds, beside))
    out = out.withColumn("pn", F.when(F.col(f"c_{j}").isNull(), F.col("pn")).otherwise(F.col("pn") * joint))
    return out.withColumn("p", F.col("ple") * F.col("pn")).filter(F.col("p") >= beta - EPS).drop(f"w_{j}")


def columns(length: int) -> list[str]:
    return [f"{c}_{i}" for i in range(length + 1) for c in PER_NODE] + [f"e_{i}" for i in range(length)] + ["ple", "pn", "p"]


def label_key(length: int):
    return F.concat_ws("|", *[f"l_{i}" for i in range(length + 1)])


def canonical(paths: DataFrame, length: int, directed: bool) -> DataFrame:
    """One orientation of each path: the lesser label sequence, of equal ones the lesser first node."""
    paths = paths.withColumn("label_key", label_key(length))
    if directed or length == 0:
        return paths
    back = F.concat_ws("|", *[f"l_{i}" for i in range(length, -1, -1)])
    return paths.filter((F.col("label_key") < back) | ((F.col("label_key") == back) & (F.col("n_0") < F.col(f"n_{length}"))))


def bucket_of(p, beta: float, gamma: float):
    return F.floor(F.round((p - beta) / gamma, 9)).cast("int")


@dataclass
class PathIndex:
    paths: dict[int, DataFrame]
    eg: EntityGraph
    L: int
    beta: float
    gamma: float
    points: tuple[float, ...] = tuple(round(0.1 * i, 1) for i in range(1, 11))
    hist: DataFrame | None = None

    def lookup(self, labels: list[str], alpha: float) -> DataFrame:
        """Paths with these labels in this order and p >= alpha; below beta they are found by expansion."""
        length = len(labels) - 1
        if alpha < self.beta - EPS or length > self.L:
            return on_demand(self.eg, labels, alpha)
        return with_worlds(self.stored(labels, alpha), self.eg, [str(i) for i in range(length + 1)])

    def stored(self, labels: list[str], alpha: float) -> DataFrame:
        """The indexed paths, without worlds. Files and row groups go by label sequence and probability, so that the filter
        on both leaves the others unread."""
        length = len(labels) - 1
        key, back = "|".join(labels), "|".join(reversed(labels))
        stored = self.paths[length].filter((F.col("p") >= alpha - EPS) & (F.col("bucket") >= _bucket(alpha, self.beta, self.gamma)))
        found = stored.filter(F.col("label_key") == (key if self.eg.directed else min(key, back))).select(columns(length))
        if self.eg.directed or length == 0 or key < back:
            return found
        turned = found.select(*[F.col(f"{c}_{length - i}").alias(f"{c}_{i}") for i in range(length + 1) for c in PER_NODE], *[F.col(f"e_{length - 1 - i}").alias(f"e_{i}") for i in range(length)], "ple", "pn", "p")
        return turned if key > back else found.unionByName(turned)

    def size(self) -> DataFrame:
        """Rows by length, label sequence and bucket, with totals."""
        parts = [df.select(F.lit(n).alias("len"), "label_key", "bucket") for n, df in self.paths.items()]
        whole = parts[0]
        for x in parts[1:]:
            whole = whole.unionByName(x)
        return whole.cube("len", "label_key", "bucket").agg(F.count(F.lit(1)).alias("n_paths"))

    def save(self, path: str) -> None:
        for n, df in self.paths.items():
            _laid_out(df, df.count()).write.parquet(f"{path}/len={n}")
        self.hist.write.parquet(f"{path}/hist")
        note = {"label_merge": self.eg.label_merge, "edge_merge": self.eg.edge_merge, "L": self.L, "beta": self.beta, "gamma": self.gamma, "points": list(self.points), "directed": self.eg.directed}
        spark = self.hist.sparkSession
        spark.createDataFrame([(json.dumps(note),)], "note string").coalesce(1).write.text(f"{path}/manifest")

    @staticmethod
    def load(spark: SparkSession, path: str, eg: EntityGraph) -> "PathIndex":
        note = json.loads(spark.read.text(f"{path}/manifest").first()[0])
        paths = {n: spark.read.parquet(f"{path}/len={n}") for n in range(note["L"] + 1)}
        return PathIndex(paths, eg, note["L"], note["beta"], note["gamma"], tuple(note["points"]), spark.read.parquet(f"{path}/hist"))


class DeferredIndex(PathIndex):
    """An index that is built when its paths or counts are first asked for. Lookups below beta or over L, which expand
    along their labels, leave it unbuilt. With ``sequences`` it holds these label sequences alone, and refuses others."""

    def __init__(self, eg: EntityGraph, L: int, beta: float, gamma: float = 0.1, sequences: set[tuple[str, ...]] | None = None):
        self.eg, self.L, self.beta, self.gamma = eg, L, beta, gamma
        self.sequences = None if sequences is None else {min(s, s[::-1]) for s in sequences}
        self._lock, self._built = threading.Lock(), None

    def built(self) -> PathIndex:
        with self._lock:
            if self._built is None:
                self._built = build_path_index(self.eg, self.L, self.beta, self.gamma) if self.sequences is None else index_sequences(self.eg, self.L, self.beta, self.gamma, self.sequences)
            return self._built

    def stored(self, labels: list[str], alpha: float) -> DataFrame:
        if self.sequences is not None and min(tuple(labels), tuple(labels)[::-1]) not in self.sequences:
            raise ValueError(f"the index holds no paths along {labels}")
        return self.built().stored(labels, alpha)

    @property
    def paths(self) -> dict[int, DataFrame]:
        return self.built().paths

    @property
    def hist(self) -> DataFrame:
        return self.built().hist


def _laid_out(rows: DataFrame, n: int) -> DataFrame:
    """Rows in ranges of (label_key, p), a file each."""
    return rows.repartitionByRange(max(1, -(-n // FILE_ROWS)), "label_key", "p").sortWithinPartitions("label_key", "p")


def _bucket(p: float, beta: float, gamma: float) -> int:
    return int(round((p - beta) / gamma, 9) // 1)


def build_path_index(eg: EntityGraph, L: int = 3, beta: float = 0.1, gamma: float = 0.1) -> PathIndex:
    """One job a length; the write between them is the barrier. Expansion needs both orientations, storage one."""
    paths, level = {}, seed_paths(eg, beta)
    for n in range(L + 1):
        level = materialise(level.select(columns(n)), f"paths-{n}")
        rows = canonical(level, n, eg.directed).withColumn("bucket", bucket_of(F.col("p"), beta, gamma))
        paths[n] = materialise(_laid_out(rows, level.count()), f"index-{n}")
        if n < L:
            level = extend_paths(level, eg, n, beta)
    idx = PathIndex(paths, eg, L, beta, gamma)
    idx.hist = materialise(path_histogram(idx), "hist")
    return idx


def path_counts(eg: EntityGraph, L: int, betas: tuple[float, ...]) -> list[tuple[float, int, int]]:
    """beta, length, paths that an index of that threshold holds. The least threshold's paths hold those of all others; what
    the next length needs is written, and the longest paths are counted as they are found."""
    found, level = {}, seed_paths(eg, min(betas))
    for n in range(L + 1):
        level = level.select(columns(n)) if n == L else materialise(level.select(columns(n)), f"paths-{n}")
        told = canonical(level, n, eg.directed).agg(*[F.count(F.when(F.col("p") >= b - EPS, 1)) for b in betas]).first()
        found |= {(b, n): told[k] for k, b in enumerate(betas)}
        if n < L:
            level = extend_paths(level, eg, n, min(betas))
    return [(b, n, found[b, n]) for b in betas for n in range(L + 1)]


def on_demand(eg: EntityGraph, labels: list[str], alpha: float) -> DataFrame:
    """The same paths without an index, by expansion along the label sequence."""
    level = seed_paths(eg, alpha, labels[0])
    for i, label in enumerate(labels[1:]):
        level = extend_paths(level, eg, i, alpha, label)
    return with_worlds(level.select(columns(len(labels) - 1)), eg, [str(i) for i in range(len(labels))])


def index_sequences(eg: EntityGraph, L: int, beta: float, gamma: float, sequences: set[tuple[str, ...]]) -> PathIndex:
    """The part of the index that holds these label sequences, of an edge or more."""
    edges = materialise(labelled_edges(eg, {x for s in sequences for x in zip(s, s[1:])}, beta), "labelled")
    paths = {}
    for n in range(1, L + 1):
        found = [joined_edges(edges, list(s), beta).select(columns(n)) for s in sorted(sequences) if len(s) == n + 1]
        if found:
            rows = canonical(reduce(DataFrame.unionByName, found), n, False).withColumn("bucket", bucket_of(F.col("p"), beta, gamma))
            paths[n] = materialise(rows.repartitionByRange("label_key", "p").sortWithinPartitions("label_key", "p"), f"index-{n}")
    idx = PathIndex(paths, eg, L, beta, gamma)
    idx.hist = materialise(path_histogram(idx), "hist")
    return idx


def turned(paths: DataFrame, length: int) -> DataFrame:
    """The same paths from their last node, worlds included."""
    nodes = [F.col(f"{c}_{length - i}").alias(f"{c}_{i}") for i in range(length + 1) for c in (*PER_NODE, "w")]
    return paths.select(*nodes, *[F.col(f"e_{length - 1 - i}").alias(f"e_{i}") for i in range(length)], "ple", "pn", "p")


def labelled_edges(eg: EntityGraph, pairs: set[tuple[str, str]], beta: float) -> DataFrame:
    """Paths of one edge between the labels of ``pairs``, with the worlds of both ends: the lesser label first, both
    directions where they are equal. Undirected graphs without correlated edges."""
    keys = sorted({"|".join(sorted(x)) for x in pairs})
    ends = lambda labels: F.col("label").isin(sorted(labels))
    first, second = {min(x) for x in pairs}, {max(x) for x in pairs}
    node = lambda i, labels: eg.nodes().filter(ends(labels)).select(*[F.col(a).alias(f"{b}_{i}") for a, b in (("e", "n"), ("label", "l"), ("q", "q"), ("c", "c"), ("m", "m"), ("w", "w"))])
    rows = eg.edges.filter(F.col("p") >= beta - EPS).select(F.col("src").alias("n_0"), F.col("dst").alias("n_1"), F.col("p").alias("e_0"))
    rows = rows.join(node(0, first), "n_0").filter(F.col("e_0") * F.col("q_0") >= beta - EPS).join(node(1, second), "n_1")
    rows = rows.filter(label_key(1).isin(keys)).withColumn("ple", F.col("q_0") * F.col("e_0") * F.col("q_1"))
    return _scored(rows.filter(F.col("ple") >= beta - EPS), 1, beta).select(*columns(1), "w_0", "w_1")


def joined_edges(edges: DataFrame, labels: list[str], alpha: float) -> DataFrame:
    """Paths along a label sequence from ``labelled_edges`` of its pairs. A path's parts are no less probable than it."""

    def step(i: int) -> DataFrame:
        a, b = labels[i], labels[i + 1]
        rows = edges.filter((F.col("l_0") == min(a, b)) & (F.col("l_1") == max(a, b)) & (F.col("p") >= alpha - EPS))
        return rows if a <= b else turned(rows, 1)

    rows = step(0)
    for i in range(1, len(labels) - 1):
        j, more = i + 1, step(i)
        far = [F.col(f"{c}_1").alias(f"{c}_{j}") for c in (*PER_NODE, "w")]
        rows = rows.drop("p", "pn").join(more.select(F.col("n_0").alias(f"n_{i}"), *far, F.col("e_0").alias(f"e_{i}")), f"n_{i}")
        for k in range(i):
            rows = rows.filter(F.col(f"n_{k}") != F.col(f"n_{j}"))
        rows = rows.withColumn("ple", F.col("ple") * F.col(f"e_{i}") * F.col(f"q_{j}")).filter(F.col("ple") >= alpha - EPS)
        rows = _scored(rows, j, alpha)
    return rows


def path_histogram(idx: PathIndex) -> DataFrame:
    """label_key, point, n_paths: paths with p of the point or more; both directions of a palindrome count."""
    parts = []
    for n, df in idx.paths.items():
        back = F.concat_ws("|", F.reverse(F.split("label_key", "[|]")))
        twice = F.when((F.lit(n > 0 and not idx.eg.directed)) & (F.col("label_key") == back), 2).otherwise(1)
        counts = df.groupBy("label_key").agg(*[F.sum(F.when(F.col("p") >= x - EPS, twice).otherwise(0)).alias(f"c{i}") for i, x in enumerate(idx.points)])
        parts.append(counts.select("label_key", F.explode(F.array(*[F.struct(F.lit(x).alias("point"), F.col(f"c{i}").alias("n_paths")) for i, x in enumerate(idx.points)])).alias("x")).select("label_key", "x.point", "x.n_paths"))
    out = parts[0]
    for x in parts[1:]:
        out = out.unionByName(x)
    return out


def estimate_count(points: list[tuple[float, float]], alpha: float) -> float:
    """A count at any alpha from counts at points: exponential between positive ones, else linear."""
    points = sorted(points)
    if alpha <= points[0][0]:
        return points[0][1]
    for (a, x), (b, y) in zip(points, points[1:]):
        if alpha <= b + EPS:
            t = (alpha - a) / (b - a)
            return x ** (1 - t) * y**t if x > 0 and y > 0 else x + (y - x) * t
    return points[-1][1]


def load_counts(idx: PathIndex, keys: list[str]) -> dict[str, list[tuple[float, float]]]:
    """Histograms of the label sequences that a pattern's paths need: one filtered read."""
    out: dict[str, list[tuple[float, float]]] = {}
    for r in idx.hist.filter(F.col("label_key").isin(keys)).collect():
        out.setdefault(r["label_key"], []).append((r["point"], float(r["n_paths"])))
    return out


def exact_count(idx: PathIndex, labels: list[str], alpha: float) -> int:
    return idx.lookup(labels, alpha).count()


def node_context(eg: EntityGraph) -> DataFrame:
    """e, label, n (neighbours that can carry the label), ppu and fpu (greatest edge and edge times label
    probability towards one). Correlated edges count at their greatest over the unknown own label."""
    labels = eg.labels.select(F.col("entity_id").alias("dst"), "label", F.col("p").alias("q"))
    edges = eg.edges.withColumnRenamed("l_dst", "label") if eg.conditional else eg.edges
    if eg.directed:
        # a pattern node needs neighbours on either side; counting both only weakens the tests
        edges = edges.unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "p"))
    rows = edges.join(labels, ["dst", "label"] if eg.conditional else ["dst"])
    n = F.count_distinct("dst") if eg.conditional else F.count(F.lit(1))
    return rows.groupBy(F.col("src").alias("e"), "label").agg(n.alias("n"), F.max("p").alias("ppu"), F.max(F.col("p") * F.col("q")).alias("fpu"))

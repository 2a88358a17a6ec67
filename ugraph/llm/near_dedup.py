"""Near-duplicate documents by MinHash with tensored banding.

A document is its set of distinct word shingles. Two collections of ``side`` sub-keys, of PER_KEY minhashes each, give
side x side table keys, one for each pair of a sub-key of either collection: at a limit of 0.85, 60 minhashes serve 100
tables. Only sub-keys that another text shares are paired at all. In a table bucket every text is held against one
leader; texts whose buckets then still span several components are held against each other across components. Every
candidate pair is confirmed on full shingle sets, after tests which no linked pair fails: set sizes; the shingles that
only one of the texts in question has; and a least number of one-byte minhashes equal (a pair at the limit fails this
with a probability of at most FAIL).

``side`` follows from the limit: a linked pair at the limit misses all tables with a probability of at most MISS.

Defined cases: null and empty texts have empty sets and link to nothing; equal sets are one class however many texts
have them; rows of equal doc_id are documents of their own; a class whose doc_ids are all null has a null
component_id; extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
from functools import cache
from math import comb

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import blobs, map_arrow, materialise, slices
from .components import components

SHINGLE, PERCENT = 3, 85
PER_KEY, MISS, FAIL = 3, 2e-4, 6e-7


def side_of(percent: int) -> int:
    """Sub-keys of either collection: the least even number that keeps to MISS at a limit of ``percent``."""
    one = 1 - (percent / 100) ** PER_KEY
    return next(s for s in range(2, 1 << 16, 2) if 2 * one**s <= MISS)


def least_equal(percent: int) -> int:
    """How many minhashes agree at least, but with a probability of FAIL, in a pair at the limit."""
    n, j = 2 * side_of(percent) * PER_KEY, percent / 100
    below, k = 0.0, 0
    while below + comb(n, k) * j**k * (1 - j) ** (n - k) <= FAIL:
        below += comb(n, k) * j**k * (1 - j) ** (n - k)
        k += 1
    return k


@cache
def _functions(hashes: int) -> tuple[np.ndarray, np.ndarray]:
    """Odd factors and summands of the hash functions."""
    rng = np.random.default_rng(101)
    return (rng.integers(1, 1 << 63, hashes, dtype=np.uint64) << np.uint64(1)) | np.uint64(1), rng.integers(0, 1 << 63, hashes, dtype=np.uint64)


def _mix(x: np.ndarray) -> np.ndarray:
    x = x ^ (x >> np.uint64(31))
    x = x * np.uint64(0x9E3779B97F4A7C15)
    return x ^ (x >> np.uint64(29))


def shingle_set(text: str, width: int = SHINGLE) -> np.ndarray:
    """Sorted 64-bit hashes of the distinct shingles; a text of fewer words is one shingle of all of them."""
    words = text.encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return np.empty(0, np.uint64)
    known = {w: xxhash.xxh3_64_intdigest(w) for w in set(words)}
    h = np.fromiter(map(known.__getitem__, words), np.uint64, len(words))
    n = max(1, len(h) - width + 1)
    out = np.full(n, len(h) if len(h) < width else width, np.uint64)
    for i in range(min(width, len(h))):
        out = _mix(out * np.uint64(0xD6E8FEB86659FD93) + h[i : i + n])
    return np.unique(out)


def minhashes(shingles: np.ndarray, hashes: int) -> np.ndarray:
    low, (multiply, add) = np.full(hashes, np.iinfo(np.uint64).max, np.uint64), _functions(hashes)
    for a in range(0, len(shingles), 4096):
        part = shingles[a : a + 4096]
        low = np.minimum(low, (part[None, :] * multiply[:, None] + add[:, None]).min(axis=1))
    return low


def _sub_keys(low: np.ndarray) -> np.ndarray:
    """Keys of PER_KEY minhashes each."""
    parts = low.reshape(len(low), -1, PER_KEY)
    key = np.zeros(parts.shape[:2], np.uint64)
    for i in range(PER_KEY):
        key = _mix(key * np.uint64(0xA24BAED4963EE407) + parts[:, :, i])
    return key


def set_name(shingles: np.ndarray) -> bytes:
    return hashlib.blake2b(shingles.tobytes(), digest_size=16).digest()


SIGNED = "rid long, doc_id long, text_hash long, n long, name binary, keys array<long>, bytes array<long>"


def _sign(width: int, hashes: int):
    def run(batches):
        for batch in batches:
            for part in slices(batch, "text"):
                sets = [shingle_set(t or "", width) for t in part.column("text").to_pylist()]
                low = np.array([minhashes(s, hashes) for s in sets], dtype=np.uint64).reshape(-1, hashes)
                keys = _sub_keys(low)
                sketch = (_mix(low) >> np.uint64(56)).reshape(len(sets), -1, 4)
                words = (sketch << (np.arange(4, dtype=np.uint64) * np.uint64(8))).sum(axis=2, dtype=np.uint64)
                names = b"".join(set_name(s) for s in sets)

                def lists(a):
                    return pa.ListArray.from_arrays(pa.array(np.arange(len(sets) + 1, dtype=np.int32) * a.shape[1]), pa.array(np.ascontiguousarray(a).ravel().view(np.int64)))

                yield pa.RecordBatch.from_arrays(
                    [part.column("rid"), part.column("doc_id"), part.column("text_hash"), pa.array([len(s) for s in sets], pa.int64()), blobs(names, np.arange(len(sets) + 1) * 16), lists(keys), lists(words)],
                    names=["rid", "doc_id", "text_hash", "n", "name", "keys", "bytes"],
                )

    return run


def _sets(width: int):
    def run(batches):
        for batch in batches:
            for part in slices(batch, "text"):
                sets = [shingle_set(t or "", width) for t in part.column("text").to_pylist()]
                ends = np.cumsum([0, *map(len, sets)]).astype(np.int32)
                flat = np.concatenate([*sets, np.empty(0, np.uint64)]).view(np.int64)
                yield pa.RecordBatch.from_arrays([part.column("cid"), pa.ListArray.from_arrays(pa.array(ends), pa.array(flat))], names=["cid", "shingles"])

    return run


def _equal_bytes(a: str, b: str, hashes: int) -> str:
    """SQL: how many of the one-byte minhashes agree, four in a number; a zero byte of the difference is one."""
    low, high = 0x7F7F7F7F, 0x80808080
    x = f"({a}[{{i}}] ^ {b}[{{i}}])"
    return " + ".join(f"bit_count(~(((({x} & {low}L) + {low}L) | {x}) & {high}L) & {high}L)".replace("{i}", str(i)) for i in range(hashes // 4))


def _confirm(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """Pairs (u, v) with their intersection and union, whole sets compared."""
    s = sets.select(F.col("cid").alias("u"), F.col("shingles").alias("su"))
    t = sets.select(F.col("cid").alias("v"), F.col("shingles").alias("sv"))
    both = pairs.join(s, "u").join(t, "v").withColumn("common", F.size(F.array_intersect("su", "sv")).cast("long"))
    return both.select("u", "v", "common", (F.size("su") + F.size("sv") - F.col("common")).alias("joint"))


#: Column that tells rows apart, where a caller has put one.
ROW = "__dedup_row"


def _text_rows(docs: DataFrame) -> DataFrame:
    rid = F.col(ROW) if ROW in docs.columns else F.monotonically_increasing_id()
    return docs.select(rid.alias("rid"), F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).withColumn("text_hash", F.xxhash64("text"))


def _sets_of(docs: DataFrame, classes: DataFrame, wanted: DataFrame, width: int) -> DataFrame:
    """cid and whole set of the wanted classes, from the texts of their first documents."""
    keys = [F.coalesce("doc_id", F.lit(-(1 << 63))).alias("k"), "text_hash"]
    named = classes.join(wanted, "cid", "left_semi").select("cid", *keys)
    texts = _text_rows(docs).select(*keys, "text")
    return materialise(map_arrow(texts.join(named, ["k", "text_hash"]).select("cid", "text"), _sets(width), "cid long, shingles array<long>").dropDuplicates(["cid"]), "dedup-sets")


def duplicate_classes(docs: DataFrame, percent: int = PERCENT, width: int = SHINGLE) -> DataFrame:
    """rid, doc_id, n_shingles, and first: the component's first row as (no_id, doc_id, rid), rows with a doc_id before
    those without one."""
    texts = _text_rows(docs).select("rid", "doc_id", "text_hash", "text")
    signed = materialise(map_arrow(texts, _sign(width, 2 * side_of(percent) * PER_KEY), SIGNED), "dedup-signed")
    place = F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "rid")
    names = materialise(signed.filter("n > 0").groupBy("name").agg(F.min("rid").alias("cid"), F.min(place).alias("least")), "dedup-names")
    classes = materialise(signed.join(names.select(F.col("cid").alias("rid"), "least"), "rid").withColumnRenamed("rid", "cid").drop("name"), "dedup-classes")
    linked = _links(docs, classes, percent, width)
    roots = components(linked)
    least = classes.select(F.col("cid").alias("node"), "least")
    found = roots.join(least, "node").groupBy("root").agg(F.min("least").alias("below"))
    found = found.join(least.withColumnRenamed("node", "root").withColumnRenamed("least", "own"), "root").select("root", F.least("below", "own").alias("first"))
    moved = roots.join(found, "root").select(F.col("node").alias("cid"), "first").unionByName(found.select(F.col("root").alias("cid"), "first"))
    named = materialise(names.join(moved, "cid", "left").select("name", F.coalesce("first", "least").alias("first")), "dedup-components")
    out = signed.select("rid", "doc_id", "n", "name").join(named, "name", "left")
    return out.select("rid", "doc_id", F.col("n").alias("n_shingles"), F.when(F.col("n") > 0, F.col("first")).otherwise(place).alias("first"))


def near_duplicates(docs: DataFrame, percent: int = PERCENT, width: int = SHINGLE) -> DataFrame:
    """doc_id, n_shingles, component_id, kept of every document."""
    out = duplicate_classes(docs, percent, width).select("doc_id", "n_shingles", F.col("first.doc_id").alias("component_id"))
    return out.withColumn("kept", F.col("doc_id").eqNullSafe(F.col("component_id")))


def _live(sets: DataFrame, nodes: DataFrame, percent: int) -> DataFrame:
    """Those of ``nodes`` that can link to another one at all: shingles which only one of the texts has are in no
    intersection and in every union of it."""
    spread = sets.join(nodes, "cid", "left_semi").select("cid", F.explode("shingles").alias("s"))
    once = spread.groupBy("s").agg(F.count(F.lit(1)).alias("c"), F.min("cid").alias("cid")).filter("c = 1")
    alone = once.groupBy("cid").agg(F.count(F.lit(1)).alias("alone"))
    size = sets.select("cid", F.size("shingles").alias("n"))
    return nodes.join(alone, "cid", "left").join(size, "cid").filter(f"100 * (n - coalesce(alone, 0)) >= {percent} * n").select("cid")


def _links(docs: DataFrame, classes: DataFrame, percent: int, width: int) -> DataFrame:
    side = side_of(percent)
    subs = classes.select("cid", F.posexplode("keys").alias("pos", "key"))
    common = materialise(subs.groupBy("pos", "key").agg(F.count(F.lit(1)).alias("c")).filter("c > 1"), "dedup-common")
    sides = subs.join(common, ["pos", "key"]).groupBy("cid").agg(
        F.collect_list(F.when(F.col("pos") < side, F.struct("pos", "key"))).alias("a"),
        F.collect_list(F.when(F.col("pos") >= side, F.struct("pos", "key"))).alias("b"),
        F.sum("c").alias("shared"),
    )
    cells = sides.filter("size(a) > 0 and size(b) > 0").select("cid", "shared", F.explode("a").alias("a"), "b").select("cid", "shared", "a", F.explode("b").alias("b"))
    cells = materialise(cells.select("cid", "shared", F.xxhash64("a.pos", "a.key", "b.pos", "b.key").alias("cell")), "dedup-cells")
    # a bucket's leader is the member whose sub-keys most others share: in a group of edited copies, the least edited
    lead = F.max(F.struct("shared", (-F.col("cid")).alias("minus")))
    leaders = materialise(cells.groupBy("cell").agg(lead.alias("top"), F.count(F.lit(1)).alias("c")).filter("c > 1").select("cell", (-F.col("top.minus")).alias("lead")), "dedup-leaders")
    members = materialise(cells.drop("shared").join(leaders, "cell"), "dedup-members")
    facts = classes.select("cid", "n", "bytes")
    u = facts.select(F.col("cid").alias("u"), F.col("n").alias("nu"), F.col("bytes").alias("bu"))
    v = facts.select(F.col("cid").alias("v"), F.col("n").alias("nv"), F.col("bytes").alias("bv"))
    sizes = f"100 * least(nu, nv) >= {percent} * greatest(nu, nv)"
    sketch = f"{_equal_bytes('bu', 'bv', 2 * side * PER_KEY)} >= {least_equal(percent)}"
    stars = members.filter("cid <> lead").select(F.least("lead", "cid").alias("u"), F.greatest("lead", "cid").alias("v")).distinct()
    stars = materialise(stars.join(u, "u").join(v, "v").filter(f"{sizes} AND {sketch}").select("u", "v"), "dedup-stars")
    nodes = members.select("cid").distinct()
    sets = _sets_of(docs, classes, nodes, width)
    enough = f"100 * common >= {percent} * joint"
    first = materialise(_confirm(stars, sets).filter(enough).select("u", "v"), "dedup-links")
    # what no leader has settled: buckets that still hold more than one component
    roots = components(first).withColumnRenamed("node", "cid")
    placed = members.join(materialise(roots, "dedup-roots"), "cid", "left").select("cell", "cid", F.coalesce("root", "cid").alias("root"))
    placed = materialise(placed, "dedup-placed")
    mixed = materialise(placed.groupBy("cell").agg(F.min("root").alias("lo"), F.max("root").alias("hi")).filter("lo <> hi").select("cell"), "dedup-mixed")
    open_ = materialise(placed.join(mixed, "cell"), "dedup-open")
    open_ = materialise(open_.join(_live(sets, open_.select("cid").distinct(), percent), "cid"), "dedup-live")
    second = _across(open_, sets, percent)
    return materialise(first.unionByName(second), "dedup-all-links")


#: Texts of one block; two blocks meet in one task.
BLOCK = 256


def _across(open_: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Links between different components among texts that may share buckets (cell, cid, root).

    The buckets tie texts into clusters. A cluster's texts fall into blocks; every two blocks are compared as wholes,
    by a product of their shingle matrices, and give only the links that join components. No pair becomes a row."""
    least = materialise(open_.groupBy("cell").agg(F.min("cid").alias("m"), F.max("cid").alias("top")).filter("m <> top").drop("top"), "dedup-ties")
    ties = materialise(components(open_.join(least, "cell").select(F.col("cid").alias("u"), F.col("m").alias("v")).filter("u <> v").distinct()), "dedup-clusters")
    roots = ties.select("root").distinct().select(F.col("root").alias("node"), "root")
    ties = ties.unionByName(roots).select(F.col("node").alias("cid"), F.col("root").alias("cluster"))
    counts = ties.groupBy("cluster").agg(F.ceil(F.count(F.lit(1)) / BLOCK).cast("int").alias("blocks"))
    nodes = ties.join(materialise(counts, "dedup-blocks"), "cluster").join(open_.select("cid", "root").distinct(), "cid")
    nodes = nodes.withColumn("own", F.pmod(F.xxhash64("cid"), F.col("blocks")).cast("int"))
    rows = nodes.join(sets, "cid").withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    rows = rows.select("cluster", F.least("own", "other").alias("lo"), F.greatest("own", "other").alias("hi"), "cid", "root", "own", "shingles")
    return rows.groupBy("cluster", "lo", "hi").applyInArrow(_compare(percent), "u long, v long")


def _compare(percent: int):
    def run(table: pa.Table) -> pa.Table:
        lo, hi = table.column("lo")[0].as_py(), table.column("hi")[0].as_py()
        own, cid, root = (np.asarray(table.column(c)) for c in ("own", "cid", "root"))
        lists = table.column("shingles").combine_chunks()
        sizes = np.diff(np.asarray(lists.offsets))
        _, ids, counts = np.unique(np.asarray(lists.flatten()), return_inverse=True, return_counts=True)
        rows = np.repeat(np.arange(len(cid)), sizes)
        shared = counts[ids] > 1
        number = np.cumsum(counts > 1) - 1
        rows, ids = rows[shared], number[ids[shared]]
        common = np.zeros((len(cid), len(cid)), np.float32)
        order = np.argsort(ids, kind="stable")
        rows, ids = rows[order], ids[order]
        for a in range(0, int(ids[-1]) + 1 if len(ids) else 0, 4096):
            x, y = np.searchsorted(ids, (a, a + 4096))
            part = np.zeros((len(cid), 4096), np.float32)
            part[rows[x:y], ids[x:y] - a] = 1
            common += part @ part.T
        joint = sizes[:, None] + sizes[None, :] - common
        hit = 100 * common.astype(np.float64) >= percent * joint
        if lo != hi:
            hit &= (own == lo)[:, None] & (own == hi)[None, :]
        u, v = np.nonzero(hit & (root[:, None] != root[None, :]))
        parent: dict[int, int] = {}

        def find(x):
            while parent.get(x, x) != x:
                parent[x] = parent.get(parent[x], parent[x])
                x = parent[x]
            return x

        out = []
        for i, j in zip(u.tolist(), v.tolist(), strict=True):
            a, b = find(int(root[i])), find(int(root[j]))
            if a != b:
                parent[max(a, b)] = min(a, b)
                out.append((int(cid[i]), int(cid[j])))
        return pa.Table.from_arrays([pa.array([x for x, _ in out], pa.int64()), pa.array([y for _, y in out], pa.int64())], names=["u", "v"])

    return run


def drop_near_duplicates(docs: DataFrame, percent: int = PERCENT, width: int = SHINGLE) -> DataFrame:
    """``docs`` with one row of each group, its own columns kept: the one of least doc_id, of equal ones any; of a group
    without doc_ids any one. Rows are told apart by a number of their own, whatever their doc_ids."""
    numbered = materialise(docs.withColumn(ROW, F.monotonically_increasing_id()), "dedup-rows")
    gone = duplicate_classes(numbered, percent, width).filter("rid <> first.rid").select(F.col("rid").alias(ROW))
    return numbered.join(gone, ROW, "left_anti").select(*[F.col(f"`{c}`") for c in docs.columns])

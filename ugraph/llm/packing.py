"""Lexical retrieval packing into windows of token ids.

Each document's full windows stand alone; what is left of it (its tail) is packed with neighbours. The tails are dealt
into shards of about SHARD_TOKENS ids by their key: of the terms that KEY_TAILS tails or more hold, the one of highest
BM25 weight, so that copies and many related tails meet. A key with more ids than half a shard has shards of its own,
over which its tails are dealt evenly; the others share shards in the order of their ids. A shard holds an inverted
index of its tails with BM25 weights; document frequencies and the mean length are counted over all tails of the corpus
(the terms are token ids, so these counts are bounded by the vocabulary). Each seed, the first unused tail, fetches the
unused tails with the highest scores; they fill its window greedily, whole where they fit, and the best one left is cut
to close the window. All terms of the seed are looked up. The best CANDIDATES are tried first, then the next best ones,
down to those of score 0. What is cut off stays in the index as unused. Only the last window of a shard can hold fewer
than ``window`` ids.

Layout of a store folder (Parquet): ``windows`` — doc_id, n_tokens, first_sequence, full (ids of the document's full
windows, one after the other), tail; ``packed`` — sequence_id, pieces (doc_id, start, length, doc_tokens, offset), ids.
Ids are little-endian, of two bytes where the vocabulary allows it, else of four. ``read_pieces`` gives what lies where,
and the ids, from the stored bytes.

Defined cases: null text is an empty document (its end id is packed); rows of equal or null doc_id are packed each on
its own; ties in score go to the earlier tail; extra columns are ignored; an empty table gives no pieces.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import map_arrow, materialise, new_path, slices, write_table
from .tokens import END_ID, default_path, encoder, with_end

WINDOW = 2048
#: Ids of one shard's tails: what one task indexes at a time.
SHARD_TOKENS = 1 << 20
#: BM25's two constants, and how many of the best unused tails are tried at a time.
K1, B, CANDIDATES = 1.2, 0.75, 48
#: A key is a term which so many tails hold at least.
KEY_TAILS = 8

WINDOWS = "doc_id long, n_tokens long, first_sequence long, full binary, tail binary"
TAILS = "doc_id long, n_tokens long, tail binary, key long"
PACKED = "sequence_id long, pieces array<struct<doc_id:long,start:long,length:long,doc_tokens:long,offset:long>>, ids binary"
PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, ids binary"
#: Sequences packed in shards are numbered from here on.
SHARD_SEQUENCES = 1 << 62


def _stage(path: str, window: int, end_id: int):
    def run(batches):
        from pyspark import TaskContext

        enc = encoder(path)
        kind = id_type(enc.size)
        number = TaskContext.get().partitionId() << 40
        for batch in batches:
            for part in slices(batch, "text"):
                ids, bounds = with_end(*enc.encode(part.column("text")), end_id)
                data = memoryview(ids.astype(kind).tobytes())
                sizes = np.diff(bounds)
                cuts = (bounds[:-1] + sizes // window * window) * kind.itemsize
                ends = bounds * kind.itemsize
                full, tails = ([bytes(data[x:y]) for x, y in zip(a.tolist(), b.tolist(), strict=True)] for a, b in ((ends[:-1], cuts), (cuts, ends[1:])))
                counts = np.concatenate(([0], np.cumsum(sizes // window)))
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(sizes), pa.array(number + counts[:-1]), pa.array(full, pa.binary()), pa.array(tails, pa.binary())], names=["doc_id", "n_tokens", "first_sequence", "full", "tail"])
                number += int(counts[-1])

    return run


def id_type(vocabulary: int) -> np.dtype:
    return np.dtype("<u2" if vocabulary <= 1 << 16 else "<u4")


def _frequencies(vocabulary: int, kind: str):
    """Per task: the number of tails that hold each id."""

    def run(batches):
        df = np.zeros(vocabulary, np.int64)
        for batch in batches:
            for tail in batch.column("tail").to_pylist():
                df[np.unique(np.frombuffer(tail, kind))] += 1
        hit = np.flatnonzero(df)
        yield pa.RecordBatch.from_arrays([pa.array(hit.astype(np.int32)), pa.array(df[hit])], names=["term", "df"])

    return run


class ShardIndex:
    """Inverted index over a shard's tails: for each term, the tails that hold it and their BM25 weights."""

    def __init__(self, tails: list[np.ndarray], idf: np.ndarray, mean: float):
        lengths = np.array([len(t) for t in tails], dtype=np.int64)
        self.n, v = len(tails), np.int64(len(idf))
        pairs, tf = np.unique(np.repeat(np.arange(self.n), lengths) * v + np.concatenate(tails), return_counts=True)
        doc, term = pairs // v, pairs % v
        weight = idf[term] * tf * (K1 + 1) / (tf + K1 * (1 - B + B * lengths[doc] / mean))
        self.rows = np.searchsorted(doc, np.arange(self.n + 1))
        self.terms = term
        order = np.argsort(term, kind="stable")
        self.docs, self.weights = doc[order], weight[order]
        self.starts = np.searchsorted(term[order], np.arange(v + 1))

    def scores(self, seed: int) -> np.ndarray:
        a, b = self.rows[seed], self.rows[seed + 1]
        spans = [(self.starts[t], self.starts[t + 1]) for t in self.terms[a:b].tolist()]
        return np.bincount(np.concatenate([self.docs[x:y] for x, y in spans]), np.concatenate([self.weights[x:y] for x, y in spans]), self.n)


def best(scores: np.ndarray, used: np.ndarray) -> np.ndarray:
    """The unused tails of highest score, best first."""
    ranked = np.flatnonzero(~used)
    if len(ranked) > CANDIDATES:
        least = np.partition(scores[ranked], -CANDIDATES)[-CANDIDATES]
        above, equal = ranked[scores[ranked] > least], ranked[scores[ranked] == least]
        ranked = np.concatenate((above, equal[: CANDIDATES - len(above)]))
    return ranked[np.lexsort((ranked, -scores[ranked]))]


def fill_windows(lengths: np.ndarray, index: ShardIndex, window: int) -> list[list[tuple[int, int, int]]]:
    """Windows as lists of (tail, from, to); every id of every tail lies in exactly one."""
    left, at = lengths.copy(), np.zeros_like(lengths)
    used = left == 0
    windows, first, n = [], 0, len(lengths)
    while True:
        while first < n and used[first]:
            first += 1
        if first == n:
            return windows
        room, placed = window, []

        def place(i: int, k: int) -> int:
            placed.append((i, int(at[i]), int(at[i]) + k))
            at[i] += k
            left[i] -= k
            used[i] = left[i] == 0
            return k

        room -= place(first, min(int(left[first]), room))
        if room:
            scores = index.scores(first)
            ranked = best(scores, used)
            while room and len(ranked):
                for i in ranked.tolist():
                    if left[i] <= room and not used[i]:
                        room -= place(i, int(left[i]))
                        if not room:
                            break
                ranked = ranked[~used[ranked]]
                if room and len(ranked):
                    room -= place(int(ranked[0]), min(int(left[ranked[0]]), room))
                    ranked = ranked[~used[ranked]]
                if room and not len(ranked):
                    ranked = best(scores, used)
        windows.append(placed)


def _keys(idf: np.ndarray, usual: np.ndarray, mean: float, kind: str):
    """The key of every tail; -1 where it has none."""

    def run(batches):
        for batch in batches:
            keys = []
            for tail in batch.column("tail").to_pylist():
                terms, tf = np.unique(np.frombuffer(tail, kind), return_counts=True)
                terms, tf = terms[usual[terms]], tf[usual[terms]]
                weight = idf[terms] * tf / (tf + K1 * (1 - B + B * len(tail) / np.dtype(kind).itemsize / mean))
                keys.append(int(terms[np.argmax(weight)]) if len(terms) else -1)
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in ("doc_id", "n_tokens", "tail")), pa.array(keys, pa.int64())], names=["doc_id", "n_tokens", "tail", "key"])

    return run


def deal(masses: list[tuple[int, int]], shard_tokens: int) -> list[tuple[int, int, int]]:
    """(key, first shard, number of shards) from (key, ids). A key of more than half a shard has its own shards."""
    if sum(n for _, n in masses) <= shard_tokens:
        return [(key, 0, 1) for key, _ in masses]
    shards, room, open_shard, dealt = 0, 0, 0, []
    for key, n in sorted(masses):
        if 2 * n > shard_tokens:
            parts = -(-n // shard_tokens)
            dealt.append((key, shards, parts))
            shards += parts
            continue
        if n > room or not room:
            open_shard, room = shards, shard_tokens
            shards += 1
        dealt.append((key, open_shard, 1))
        room -= n
    return dealt


def _pack(idf: np.ndarray, mean: float, window: int, kind: str):
    def run(table: pa.Table) -> pa.Table:
        rows = sorted(zip(*(table.column(c).to_pylist() for c in ("doc_id", "n_tokens", "tail")), strict=True), key=lambda r: (r[0] is not None, r[0] or 0, r[1], r[2]))
        tails = [np.frombuffer(r[2], kind) for r in rows]
        lengths = np.array([len(t) for t in tails], dtype=np.int64)
        pieces, ids, counts = [], [], [0]
        for placed in fill_windows(lengths, ShardIndex([t.astype(np.int64) for t in tails], idf, mean), window):
            offset = 0
            for i, a, b in placed:
                doc_id, n, _ = rows[i]
                pieces.append((doc_id, n - len(tails[i]) + a, b - a, n, offset))
                offset += b - a
            counts.append(len(pieces))
            ids.append(b"".join(tails[i][a:b].tobytes() for i, a, b in placed))
        fields = ["doc_id", "start", "length", "doc_tokens", "offset"]
        held = pa.StructArray.from_arrays([pa.array(c, pa.int64()) for c in zip(*pieces, strict=True)], names=fields)
        first = SHARD_SEQUENCES + (table.column("shard")[0].as_py() << 32)
        return pa.Table.from_arrays([pa.array(np.arange(first, first + len(ids))), pa.ListArray.from_arrays(pa.array(counts, pa.int32()), held), pa.array(ids, pa.binary())], names=["sequence_id", "pieces", "ids"])

    return run


def _piece_rows(columns: list, data: list[bytes], kind: np.dtype, with_ids: bool) -> pa.RecordBatch:
    """Rows of PIECES from doc_id, start, length, doc_tokens, sequence_id, offset and the stored bytes."""
    wide = [np.frombuffer(x, kind).astype("<u4").tobytes() for x in data]
    doc_id, start, length, n, sequence, offset = (pa.array(c, pa.int64()) for c in columns)
    crcs = pa.array([zlib.crc32(x) for x in wide], pa.int64())
    names = [f.split()[0] for f in PIECES.split(", ")][: 8 if with_ids else 7]
    return pa.RecordBatch.from_arrays([doc_id, start, length, crcs, n, sequence, offset, *([pa.array(wide, pa.binary())] if with_ids else [])], names=names)


def _full_pieces(window: int, kind: np.dtype, with_ids: bool):
    def run(batches):
        size = window * kind.itemsize
        for batch in batches:
            for part in slices(batch, "full"):
                rows, data = [], []
                for doc_id, n, first, full in zip(*(part.column(c).to_pylist() for c in ("doc_id", "n_tokens", "first_sequence", "full")), strict=True):
                    rows += [(doc_id, i * window, window, n, first + i, 0) for i in range(len(full) // size)]
                    data += [full[x : x + size] for x in range(0, len(full), size)]
                if rows:
                    yield _piece_rows(list(zip(*rows, strict=True)), data, kind, with_ids)

    return run


def _packed_pieces(kind: np.dtype, with_ids: bool):
    def run(batches):
        for batch in batches:
            for part in slices(batch, "ids"):
                rows, data = [], []
                for sequence, pieces, ids in zip(*(part.column(c).to_pylist() for c in ("sequence_id", "pieces", "ids")), strict=True):
                    for p in pieces:
                        rows.append((p["doc_id"], p["start"], p["length"], p["doc_tokens"], sequence, p["offset"]))
                        data.append(ids[p["offset"] * kind.itemsize : (p["offset"] + p["length"]) * kind.itemsize])
                if rows:
                    yield _piece_rows(list(zip(*rows, strict=True)), data, kind, with_ids)

    return run


def write_sequences(docs: DataFrame, store: str, path: str | None = None, window: int = WINDOW, end_id: int = END_ID, shard_tokens: int = SHARD_TOKENS) -> None:
    """Encode ``docs`` (doc_id, text), pack them and write the store's tables under ``store``."""
    from .common import ship

    spark = docs.sparkSession
    path = path or default_path()
    size = encoder(path).size
    kind = id_type(size).str
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    write_table(map_arrow(texts, _stage(path, window, end_id), WINDOWS), f"{store}/windows")
    some = spark.read.schema(WINDOWS).parquet(f"{store}/windows").filter("length(tail) > 0").select("doc_id", "n_tokens", "tail")
    tails, ids = some.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.length("tail")), F.lit(0))).first()
    ids //= np.dtype(kind).itemsize
    counts = map_arrow(some.select("tail"), _frequencies(size, kind), "term int, df long").groupBy("term").agg(F.sum("df").alias("df"))
    df = np.zeros(size)
    for term, n in counts.collect():  # at most one row for each entry of the vocabulary
        df[term] = n
    idf = np.log1p((tails - df + 0.5) / (df + 0.5))
    mean = ids / max(tails, 1)
    keyed = materialise(map_arrow(some, _keys(idf, df >= KEY_TAILS, mean, kind), TAILS).withColumn("mid", F.monotonically_increasing_id()), "pack-keys")
    sums = keyed.groupBy("key").agg(F.sum(F.length("tail")).alias("n")).collect()  # at most one row for each entry of the vocabulary
    shares = spark.createDataFrame(deal([(r["key"], -(-r["n"] // np.dtype(kind).itemsize)) for r in sums], shard_tokens), "key long, first long, parts long")
    ship(spark)
    dealt = keyed.join(F.broadcast(shares), "key").withColumn("shard", F.col("first") + F.expr("pmod(xxhash64(mid), parts)"))
    packed = dealt.select("shard", "doc_id", "n_tokens", "tail").groupBy("shard").applyInArrow(_pack(idf, mean, window, kind), PACKED)
    write_table(packed, f"{store}/packed")


def read_pieces(spark: SparkSession, store: str, path: str | None = None, window: int = WINDOW, with_ids: bool = True) -> DataFrame:
    """Which ids of which document lie at which offset of which sequence, and (``with_ids``) the ids as uint32 bytes."""
    kind = id_type(encoder(path or default_path()).size)
    schema = PIECES if with_ids else PIECES.removesuffix(", ids binary")
    full = spark.read.schema(WINDOWS).parquet(f"{store}/windows").filter("length(full) > 0").select("doc_id", "n_tokens", "first_sequence", "full")
    packed = spark.read.schema(PACKED).parquet(f"{store}/packed")
    return map_arrow(full, _full_pieces(window, kind, with_ids), schema).unionByName(map_arrow(packed, _packed_pieces(kind, with_ids), schema))


def pack_documents(docs: DataFrame, path: str | None = None, window: int = WINDOW, end_id: int = END_ID, shard_tokens: int = SHARD_TOKENS, with_ids: bool = True) -> DataFrame:
    """The pieces of all documents, read back from sequences written to the shared folder."""
    spark = docs.sparkSession
    store = new_path(spark, "sequences")
    write_sequences(docs, store, path, window, end_id, shard_tokens)
    return read_pieces(spark, store, path, window, with_ids)

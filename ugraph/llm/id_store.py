"""Content-addressed store of token ids.

A rolling hash cuts each document's id stream into chunks; a chunk is known by the hash of its bytes and is kept once,
in the pack row of the first document (in ascending doc_id order) that holds it. A document's recipe lists its chunks.
A Merkle manifest of three levels holds a root over the leaves of each BLOCK documents, one over the blocks of each pack
partition, and one over those. A reader takes the leaves of the documents from the bytes it has put together, and
``check_manifest`` holds the roots over them against the manifest.

Layout of a store folder (Parquet): ``packs`` — pid, idx, doc_id, local_start, n_tokens, recipe (16-byte hashes), sizes
(ids per chunk), kinds (0 held here only, 1 held here and referenced elsewhere, 2 held elsewhere), n_lent and n_foreign
(chunks of kinds 1 and 2), leaf, payload (the held chunks' ids, little-endian, ``width`` bytes each); ``hot`` — hash,
parts: chunks referenced so often that readers deal their references over parts; ``manifest`` — level, pid, first_idx,
n_docs, n_tokens, root.

Defined cases: null text is an empty document (its ids are the end id alone); rows with equal or null doc_id are
separate documents (nulls first); extra columns are ignored; an empty table gives an empty store.
"""

from __future__ import annotations

import hashlib
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import blobs, discard, heavy_keys, map_arrow, materialise, new_path, read_table, salted_join, slices, write_table
from .tokens import END_ID, default_path, encoder, with_end

HASH_BYTES = 16
#: A cut falls where the low bits of the rolling hash are zero: one id in 2**CUT_BITS, with chunks of MIN to MAX ids.
CUT_BITS, MIN_IDS, MAX_IDS, WINDOW = 8, 64, 2048, 8

STAGED = "doc_id long, n_tokens long, recipe binary, sizes binary, payload binary"
PACKS = "pid int, idx long, doc_id long, local_start long, n_tokens long, recipe binary, sizes binary, kinds binary, n_lent int, n_foreign int, leaf binary, payload binary"
READ = "pid int, idx long, doc_id long, local_start long, n_tokens long, leaf binary, ids binary"
MANIFEST = "level int, pid int, first_idx long, n_docs long, n_tokens long, root string"
#: Documents under one root of the lowest level.
BLOCK = 4096


def chunk_bounds(ids: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """Cut positions of all documents' chunks, document bounds included. A cut depends on the WINDOW ids before it."""
    mixed = ids.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    mixed ^= mixed >> np.uint64(29)
    mixed *= np.uint64(0xBF58476D1CE4E5B9)
    rolled = mixed.copy()
    for j in range(1, WINDOW):
        rolled[j:] += mixed[:-j] << np.uint64(j)
    hits = np.flatnonzero((rolled >> np.uint64(40)) & np.uint64((1 << CUT_BITS) - 1) == 0) + 1
    cuts, at, ends = [0], 0, bounds[1:].tolist()
    hits = hits.tolist()
    k = 0
    for end in ends:
        while True:
            while k < len(hits) and hits[k] < at + MIN_IDS:
                k += 1
            cut = min(hits[k] if k < len(hits) else end, end, at + MAX_IDS)
            if cut >= end:
                break
            cuts.append(cut)
            at = cut
        cuts.append(end)
        at = end
    return np.array(cuts, dtype=np.int64)


def _stage(path: str, width: int):
    kind = np.dtype(f"<u{width}")

    def run(batches):
        enc = encoder(path)
        for batch in batches:
            for part in slices(batch, "text"):
                ids, bounds = with_end(*enc.encode(part.column("text")))
                if not len(bounds) - 1:
                    continue
                cuts = chunk_bounds(ids, bounds)
                data = ids.astype(kind).tobytes()
                view = memoryview(data)
                b = (cuts * width).tolist()
                names = b"".join([hashlib.blake2b(view[b[i] : b[i + 1]], digest_size=HASH_BYTES).digest() for i in range(len(b) - 1)])
                first = np.searchsorted(cuts, bounds)
                yield pa.RecordBatch.from_arrays(
                    [part.column("doc_id"), pa.array(np.diff(bounds)), blobs(names, first * HASH_BYTES), blobs(np.diff(cuts).astype("<u4").tobytes(), first * 4), blobs(data, bounds * width)],
                    names=["doc_id", "n_tokens", "recipe", "sizes", "payload"],
                )

    return run


def _chunk_rows(batches):
    """doc_id, rid, ord, hash of every chunk of a staged table."""
    for batch in batches:
        recipes = batch.column("recipe").to_pylist()
        counts = np.array([len(r) // HASH_BYTES for r in recipes], dtype=np.int64)
        n = int(counts.sum())
        ordinal = np.arange(n) - np.repeat(np.cumsum(counts) - counts, counts)
        of = pa.array(np.repeat(np.arange(len(recipes)), counts))
        yield pa.RecordBatch.from_arrays([batch.column("doc_id").take(of), batch.column("rid").take(of), pa.array(ordinal.astype(np.int32)), blobs(b"".join(recipes), np.arange(n + 1) * HASH_BYTES)], names=["doc_id", "rid", "ord", "hash"])


def _pack(width: int):
    """Rows sorted by rid: a document row, and before it a row with the chunks whose kind isn't 0."""

    def run(batches):
        from pyspark import TaskContext

        notes, idx, start = None, 0, 0
        pid = TaskContext.get().partitionId()
        for batch in batches:
            for part in slices(batch, "payload"):
                out = []
                for r in part.to_pylist():
                    if r["payload"] is None:
                        notes = r
                        continue
                    sizes = np.frombuffer(r["sizes"], "<u4")
                    kinds = np.zeros(len(sizes), np.uint8)
                    if notes is not None and notes["rid"] == r["rid"]:
                        kinds[notes["ords"]] = notes["marks"]
                    payload = r["payload"]
                    foreign = int((kinds == 2).sum())
                    if foreign:
                        ends = np.cumsum(sizes) * width
                        payload = b"".join(payload[e - s * width : e] for e, s, k in zip(ends.tolist(), sizes.tolist(), kinds.tolist(), strict=True) if k != 2)
                    out.append((pid, idx, r["doc_id"], start, r["n_tokens"], r["recipe"], r["sizes"], kinds.tobytes(), int((kinds == 1).sum()), foreign, leaf(r["recipe"], r["n_tokens"]), payload))
                    idx += 1
                    start += r["n_tokens"]
                if out:
                    yield _batch(out, PACKS)

    return run


_KINDS = {"int": pa.int32(), "long": pa.int64(), "binary": pa.binary(), "string": pa.string(), "double": pa.float64(), "boolean": pa.bool_()}


def _batch(rows: list[tuple], schema: str) -> pa.RecordBatch:
    fields = [f.split() for f in schema.split(", ")]
    return pa.RecordBatch.from_arrays([pa.array(c, _KINDS[k]) for c, (_, k) in zip(zip(*rows, strict=True), fields, strict=True)], names=[n for n, _ in fields])


def leaf(recipe: bytes, n_tokens: int) -> bytes:
    return hashlib.blake2b(recipe + n_tokens.to_bytes(8, "little"), digest_size=32).digest()


def manifest_of(leaves: DataFrame) -> DataFrame:
    """The manifest's rows from ``leaves`` (pid, idx, n_tokens, leaf). A root is the hash of what lies under it in order:
    of at most BLOCK leaves, of a partition's blocks, of the partitions."""

    def fold(rows: DataFrame, keys: list, order: str, level: int, root) -> DataFrame:
        held = F.array_sort(F.collect_list(F.struct(F.col(order).alias("at"), root.alias("root"))))
        docs = F.count(F.lit(1)) if level == 0 else F.sum("n_docs")
        out = rows.groupBy(*keys).agg(docs.alias("n_docs"), F.sum("n_tokens").alias("n_tokens"), F.sha2(F.array_join(F.transform(held, lambda x: x["root"]), ""), 256).alias("root"))
        return out.select(F.lit(level).alias("level"), F.col("pid").cast("int").alias("pid"), F.col("first_idx").cast("long").alias("first_idx"), "n_docs", "n_tokens", "root")

    first = (F.floor(F.col("idx") / BLOCK) * BLOCK).alias("first_idx")
    blocks = fold(leaves.select("pid", "idx", first, "n_tokens", "leaf"), ["pid", "first_idx"], "idx", 0, F.lower(F.hex("leaf")))
    parts = fold(blocks.withColumnRenamed("first_idx", "at"), ["pid", F.lit(0).alias("first_idx")], "at", 1, F.col("root"))
    top = fold(parts.select(F.col("pid").alias("at"), "n_docs", "n_tokens", "root"), [F.lit(-1).alias("pid"), F.lit(0).alias("first_idx")], "at", 2, F.col("root"))
    return blocks.unionByName(parts).unionByName(top)


def check_manifest(spark: SparkSession, store: str, leaves: DataFrame) -> None:
    """Raise an error unless the roots over ``leaves`` are those of the manifest."""
    _, manifest = open_store(spark, store)
    key = ["level", "pid", "first_idx"]
    both = manifest.alias("m").join(manifest_of(leaves).alias("f"), key, "full")
    same = F.coalesce((F.col("m.root") == F.col("f.root")) & (F.col("m.n_docs") == F.col("f.n_docs")) & (F.col("m.n_tokens") == F.col("f.n_tokens")), F.lit(False))
    bad = both.filter(~same).select(*key).first()
    if bad is not None:
        raise ValueError(f"the manifest differs from what is stored at level {bad['level']}, partition {bad['pid']}, from document {bad['first_idx']} on")


def write_store(docs: DataFrame, store: str, path: str | None = None, end_id: int = END_ID) -> None:
    """Encode ``docs`` (doc_id, text) and write the store's tables under ``store``."""
    spark = docs.sparkSession
    path = path or default_path()
    width = 2 if encoder(path).size <= 1 << 16 else 4
    staged_path = new_path(spark, "ids-staged")
    staged = map_arrow(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")), _stage(path, width), STAGED)
    # mid is unique and stays with the row, so rows of equal doc_id are told apart
    staged = staged.withColumn("mid", F.monotonically_increasing_id())
    write_table(staged, staged_path)
    staged = read_table(spark, staged_path, staged)
    chunks = map_arrow(staged.select("doc_id", F.col("mid").alias("rid"), "recipe"), _chunk_rows, "doc_id long, rid long, ord int, hash binary")
    # chunks found twice or more, with the first holder in (doc_id, rid, ord) order
    common = chunks.groupBy("hash").agg(F.count(F.lit(1)).alias("c"), F.min(F.struct("doc_id", "rid", "ord")).alias("first")).filter("c > 1")
    common = materialise(common, "ids-common")
    hot = materialise(heavy_keys(common, "hash").repartition(1), "ids-hot")
    write_table(hot, f"{store}/hot")
    marked = salted_join(chunks, common, "hash", hot, F.xxhash64("rid", "ord"))
    is_first = (F.col("first.rid") == F.col("rid")) & (F.col("first.ord") == F.col("ord"))
    notes = marked.groupBy("rid", "doc_id").agg(F.collect_list(F.struct("ord", F.when(is_first, 1).otherwise(2).alias("mark"))).alias("m"))
    notes = materialise(notes, "ids-notes")
    blank = F.lit(None)
    rows = staged.select("doc_id", F.col("mid").alias("rid"), F.lit(1).alias("part"), "n_tokens", "recipe", "sizes", "payload", blank.cast("array<int>").alias("ords"), blank.cast("array<int>").alias("marks"))
    notes = notes.select("doc_id", "rid", F.lit(0).alias("part"), blank.cast("long").alias("n_tokens"), blank.cast("binary").alias("recipe"), blank.cast("binary").alias("sizes"), blank.cast("binary").alias("payload"), F.col("m.ord").alias("ords"), F.col("m.mark").alias("marks"))
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    both = rows.unionByName(notes).repartitionByRange(n, "doc_id", "rid").sortWithinPartitions("doc_id", "rid", "part")
    packs = map_arrow(both, _pack(width), PACKS)
    write_table(packs, f"{store}/packs")
    discard(spark, staged_path)
    packs = read_table(spark, f"{store}/packs", packs)
    write_table(manifest_of(packs), f"{store}/manifest")


def open_store(spark: SparkSession, store: str) -> tuple[DataFrame, DataFrame]:
    """The packs and the manifest, by their fixed schemas."""
    return spark.read.schema(PACKS).parquet(f"{store}/packs"), spark.read.schema(MANIFEST).parquet(f"{store}/manifest")


def _own_chunks(width: int):
    def run(batches):
        for batch in batches:
            for part in slices(batch, "payload"):
                out = []
                for recipe, sizes, kinds, payload in zip(*(part.column(c).to_pylist() for c in ("recipe", "sizes", "kinds", "payload")), strict=True):
                    at = 0
                    for o, (s, k) in enumerate(zip(np.frombuffer(sizes, "<u4").tolist(), kinds, strict=True)):
                        if k == 1:
                            out.append((recipe[o * HASH_BYTES : (o + 1) * HASH_BYTES], payload[at : at + s * width]))
                        at += s * width * (k != 2)
                if out:
                    yield _batch(out, "hash binary, chunk binary")

    return run


def _foreign(batches):
    for batch in batches:
        out = []
        for pid, idx, recipe, kinds in zip(*(batch.column(c).to_pylist() for c in ("pid", "idx", "recipe", "kinds")), strict=True):
            out += [(pid, idx, o, recipe[o * HASH_BYTES : (o + 1) * HASH_BYTES]) for o, k in enumerate(kinds) if k == 2]
        if out:
            yield _batch(out, "pid int, idx long, ord int, hash binary")


def _assemble(width: int):
    """Rows sorted by (pid, idx, ord): foreign chunks come after their document's pack row (ord -1)."""
    kind = np.dtype(f"<u{width}")

    def finish(r, got):
        sizes, kinds = np.frombuffer(r["sizes"], "<u4").tolist(), r["kinds"]
        parts, names, at = [], [], 0
        for o, (s, k) in enumerate(zip(sizes, kinds, strict=True)):
            part = got[o] if k == 2 else r["payload"][at : at + s * width]
            at += s * width * (k != 2)
            names.append(hashlib.blake2b(part, digest_size=HASH_BYTES).digest())
            parts.append(part)
        names = b"".join(names)
        if names != r["recipe"]:
            raise ValueError(f"document {r['doc_id']}: chunks differ from its recipe")
        ids = np.frombuffer(b"".join(parts), kind)
        return r["pid"], r["idx"], r["doc_id"], r["local_start"], len(ids), leaf(names, len(ids)), ids.astype("<u4").tobytes()

    def run(batches):
        row, got = None, {}
        for batch in batches:
            for part in slices(batch, "payload"):
                out = []
                for r in part.to_pylist():
                    if r["ord"] >= 0:
                        got[r["ord"]] = r["payload"]
                        continue
                    if row is not None:
                        out.append(finish(row, got))
                    row, got = r, {}
                if out:
                    yield _batch(out, READ)
        if row is not None:
            yield _batch([finish(row, got)], READ)

    return run


def read_documents(spark: SparkSession, store: str, width: int = 2, per_batch=None, schema: str = READ) -> DataFrame:
    """Documents put together again from the stored chunks: pid, idx, doc_id, local_start, n_tokens, leaf, ids (uint32 bytes).

    Every chunk is hashed and held against the recipe; a difference raises an error. n_tokens and leaf come from the
    bytes read. ``per_batch`` turns the Arrow batches of this schema into others, of ``schema``, before they leave the
    executor."""
    packs, _ = open_store(spark, store)
    hot = spark.read.schema("hash binary, parts int").parquet(f"{store}/hot")
    fields = ["pid", "idx", "ord", "doc_id", "local_start", "recipe", "sizes", "kinds", "payload"]
    run = _assemble(width)
    step = (lambda batches: per_batch(run(batches))) if per_batch else run
    whole = map_arrow(packs.filter("n_foreign = 0").withColumn("ord", F.lit(-1)).select(fields), step, schema)
    parted = packs.filter("n_foreign > 0").withColumn("ord", F.lit(-1)).select(fields)
    lent = map_arrow(packs.filter("n_lent > 0").select("recipe", "sizes", "kinds", "payload"), _own_chunks(width), "hash binary, chunk binary")
    wanted = map_arrow(packs.filter("n_foreign > 0").select("pid", "idx", "recipe", "kinds"), _foreign, "pid int, idx long, ord int, hash binary")
    fetched = salted_join(wanted, lent, "hash", hot, F.xxhash64("pid", "idx", "ord"))
    blank = F.lit(None)
    fetched = fetched.select("pid", "idx", "ord", *[blank.cast(t).alias(c) for c, t in (("doc_id", "long"), ("local_start", "long"), ("recipe", "binary"), ("sizes", "binary"), ("kinds", "binary"))], F.col("chunk").alias("payload"))
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    merged = parted.unionByName(fetched).repartition(n, "pid", "idx").sortWithinPartitions("pid", "idx", "ord")
    return whole.unionByName(map_arrow(merged, step, schema))


def partition_offsets(packs: DataFrame) -> DataFrame:
    """Ids before each pack partition. One row per partition of the write, so it is small by construction."""
    from pyspark.sql import Window

    per = packs.groupBy("pid").agg(F.sum("n_tokens").alias("n"))
    w = Window.orderBy("pid").rowsBetween(Window.unboundedPreceding, -1)
    return per.select("pid", F.coalesce(F.sum("n").over(w), F.lit(0)).alias("before"))


DIGESTS = "pid int, idx long, doc_id long, local_start long, n_tokens long, leaf binary, ids_crc32 long"


def _digests(batches):
    for batch in batches:
        crcs = [zlib.crc32(x.as_buffer()) for x in batch.column("ids")]
        yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(crcs, pa.int64())], names=[*batch.schema.names[:-1], "ids_crc32"])


def store_digest(docs: DataFrame, store: str | None = None) -> DataFrame:
    """op3: write the store, read it back, hold what was read against the manifest, and return doc_id, start, n_tokens,
    ids_crc32 per document."""
    spark = docs.sparkSession
    store = store or new_path(spark, "id-store")
    write_store(docs, store)
    read = materialise(read_documents(spark, store, per_batch=_digests, schema=DIGESTS), "ids-read")
    check_manifest(spark, store, read)
    offsets = F.broadcast(partition_offsets(read))
    return read.join(offsets, "pid").select("doc_id", (F.col("before") + F.col("local_start")).alias("start"), "n_tokens", "ids_crc32")

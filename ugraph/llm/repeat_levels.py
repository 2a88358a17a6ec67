"""A kept logarithmic family of sparse suffix arrays: repeated passages of a corpus that arrives in batches.

``add`` takes a batch of documents. The anchors of its new texts (see ``repeats``) become a suffix array, sorted by
gram, the bytes behind the gram, text and place. It is merge-scanned against every level of the family: suffixes whose
gram stands in the batch and in two places or more are matched, and the spans found in texts of this and of earlier
batches are written. Then the array joins the family as a level, and the levels of equal size class merge into one, so
that a family of n suffixes has at most about log2(n) levels and a suffix is rewritten about as often. ``removed`` gives
the result over all batches so far, equal to that of ``repeats.repeated_spans`` over all of them at once.

Layout of a folder (Parquet): ``members/N`` — the documents of batch N; ``texts/N`` — its texts of LENGTH bytes and more
that no batch before held; ``levels/N`` — the level written with batch N; ``spans/N`` — what batch N found; ``steps/N`` —
the levels in force and the next text number. ``steps/N`` is written last: a batch that failed before is no part of the
family, and adding it again overwrites what it left. One batch is added at a time.

Defined cases: as in ``repeats``; an empty batch changes nothing but the number of batches; a folder without batches
gives no rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import discard, heavy_keys, map_arrow, materialise, salted_join, slices
from .repeats import GRAM, KEPT, LENGTH, NARROW, SHARD_ROWS, SIGNED, _cut, _sign, among_repeated, document_rows, result_rows, spans_of, spots_by_text

#: Suffixes of one file of a level, and the bytes behind a gram by which they are sorted.
FILE_ROWS, BEHIND = 1 << 20, 16

MEMBERS = "doc_id long, n_bytes long, sha string, name binary"
TEXTS = "cid long, name binary, text string"
LEVEL = "gram long, behind binary, cid long, pos long"
SPANS = "cid long, a long, b long"
STATE = "step long, next_cid long, levels array<struct<path:string,rows:long>>"


def _suffixes(batches):
    """The anchors of every text with the bytes behind their grams."""
    for batch in batches:
        for part in slices(batch, "text"):
            for cid, text, spots, grams in zip(*(part.column(c).to_pylist() for c in ("cid", "text", "spots", "grams")), strict=True):
                data, pos = text.encode(), np.frombuffer(spots, "<i8")
                behind = [data[p + GRAM : p + GRAM + BEHIND] for p in pos.tolist()]
                yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(grams, np.int64)), pa.array(behind, pa.binary()), pa.array(np.full(len(pos), cid)), pa.array(pos)], names=["gram", "behind", "cid", "pos"])


def _merged(sizes: list[int]) -> int:
    """How many of the last levels become one: each that is of no greater size class than all behind it together."""
    total, n = sizes[-1], 1
    while n < len(sizes) and sizes[-n - 1].bit_length() <= total.bit_length():
        total += sizes[-n - 1]
        n += 1
    return n


class RepeatLevels:
    """The family kept in ``folder``, which driver and executors share."""

    def __init__(self, spark: SparkSession, folder: str, shard_rows: int = SHARD_ROWS, narrow: int = NARROW):
        self.spark, self.folder, self.shard_rows, self.narrow = spark, folder.rstrip("/"), shard_rows, narrow

    def state(self) -> tuple[int, int, list[tuple[str, int]]]:
        """Batches so far, the next text's number, and path and suffixes of each level, the oldest first."""
        path = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{self.folder}/steps")
        if not path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).exists(path):
            return 0, 0, []
        row = self.spark.read.schema(STATE).parquet(f"{self.folder}/steps/*").orderBy(F.desc("step")).first()
        return (row["step"], row["next_cid"], [(x["path"], x["rows"]) for x in row["levels"]]) if row else (0, 0, [])

    def _read(self, kind: str, schema: str, steps: int) -> DataFrame:
        paths = [f"{self.folder}/{kind}/{i}" for i in range(1, steps + 1)]
        return self.spark.read.schema(schema).parquet(*paths) if paths else self.spark.createDataFrame([], schema)

    def _write(self, df: DataFrame, kind: str, step: int, schema: str) -> DataFrame:
        path = f"{self.folder}/{kind}/{step}"
        df.write.mode("overwrite").option("compression", "zstd").parquet(path)
        return self.spark.read.schema(schema).parquet(path)

    def _level(self, path: str) -> DataFrame:
        return self.spark.read.schema(LEVEL).parquet(path)

    def add(self, docs: DataFrame) -> None:
        """Index and match a batch."""
        done, base, levels = self.state()
        step = done + 1
        texts = document_rows(docs)
        signed = materialise(map_arrow(texts.select("doc_id", "text_hash", "text"), _sign, SIGNED).withColumn("rid", F.monotonically_increasing_id()), "levels-signed")
        self._write(signed.select("doc_id", "n_bytes", "sha", "name"), "members", step, MEMBERS)

        long_ = signed.filter(f"n_bytes >= {LENGTH}")
        first = long_.groupBy("name").agg(F.min("rid").alias("rid")).join(self._read("texts", TEXTS, done).select("name"), "name", "left_anti")
        key = F.coalesce("doc_id", F.lit(-(1 << 63))).alias("k")
        wanted = long_.join(first.select("rid"), "rid", "left_semi").select((F.col("rid") + base).alias("cid"), "name", key, "text_hash", "spots", "grams")
        stored = texts.select(key, "text_hash", "text").join(wanted, ["k", "text_hash"]).dropDuplicates(["cid"])
        stored = materialise(stored.select("cid", "name", "text", "spots", "grams"), "levels-texts")
        fresh = self._write(stored.select("cid", "name", "text"), "texts", step, TEXTS)
        next_cid = fresh.agg(F.coalesce(F.max("cid") + 1, F.lit(base))).first()[0]

        new = materialise(map_arrow(stored.select("cid", "text", "spots", "grams"), _suffixes, LEVEL), "levels-new")
        self._write(self._found(new, [p for p, _ in levels], step), "spans", step, SPANS)

        old = []
        if rows := new.count():
            levels = [*levels, ("", rows)]
            n = _merged([r for _, r in levels])
            old, rows = [p for p, _ in levels[-n:-1]], sum(r for _, r in levels[-n:])
            merged = new
            for path in old:
                merged = merged.unionByName(self._level(path))
            order = ["gram", "behind", "cid", "pos"]
            self._write(merged.repartitionByRange(-(-rows // FILE_ROWS), *order).sortWithinPartitions(*order), "levels", step, LEVEL)
            levels = [*levels[:-n], (f"{self.folder}/levels/{step}", rows)]
        self._write(self.spark.createDataFrame([(step, next_cid, levels)], STATE), "steps", step, STATE)
        for path in old:
            discard(self.spark, path)

    def _found(self, new: DataFrame, paths: list[str], step: int) -> DataFrame:
        """The spans that suffixes of the batch share with one another or with those of the levels at ``paths``."""
        rows, grams = new.select("gram", "cid", "pos"), new.select("gram").distinct()
        for path in paths:
            level = self._level(path).select("gram", "cid", "pos")
            heavy = materialise(heavy_keys(level.groupBy("gram").agg(F.count(F.lit(1)).alias("c")), "gram"), "levels-heavy")
            rows = rows.unionByName(salted_join(level, grams, "gram", heavy, F.xxhash64("cid", "pos")))
        spots = among_repeated(materialise(rows, "levels-scan"), "gram", "levels-grams")
        held = self._read("texts", TEXTS, step).select("cid", "text").join(spots_by_text(spots), "cid")
        return spans_of(held, self.shard_rows, self.narrow)

    def removed(self) -> DataFrame:
        """doc_id, n_bytes, n_removed, n_spans, kept_sha256 and spans of every document of every batch."""
        done, _, _ = self.state()
        members, texts = self._read("members", MEMBERS, done), self._read("texts", TEXTS, done)
        found = self._read("spans", SPANS, done).groupBy("cid").agg(F.collect_set(F.struct("a", "b")).alias("found"))
        cut = materialise(map_arrow(texts.select("cid", "text").join(found, "cid"), _cut, KEPT), "levels-cut")
        copies = members.groupBy("name").agg(F.count(F.lit(1)).alias("copies"))
        named = materialise(copies.join(texts.select("name", "cid"), "name", "left").join(cut, "cid", "left").drop("cid"), "levels-named")
        return result_rows(members, named)

"""What the operators of this subpackage share: written intermediate tables, Arrow batches and checksums."""

from __future__ import annotations

import os
import tempfile
import uuid
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.tables import ship

#: White space by which the text operators split words: space and the five ASCII controls from tab to CR.
WORD = r"[^\x20\x09-\x0D]+"
#: Bytes of text that a Python step holds at once besides a single longer text.
SLICE_BYTES = 4 << 20


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, else a folder in the warehouse
    (cluster) or a temporary one (local master)."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return found.rstrip("/")
    if spark.sparkContext.master.startswith("local") and not spark.sparkContext.master.startswith("local-cluster"):
        return _local_dir()
    return spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_work"


_LOCAL: list[str] = []


def _local_dir() -> str:
    if not _LOCAL:
        import atexit
        import shutil

        _LOCAL.append(tempfile.mkdtemp(prefix="ugraph-"))
        atexit.register(shutil.rmtree, _LOCAL[0], ignore_errors=True)
    return _LOCAL[0]


_WRITTEN: list[str] = []


def new_path(spark: SparkSession, tag: str) -> str:
    path = f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"
    _WRITTEN.append(path)
    return path


def discard_all(spark: SparkSession) -> None:
    """Delete all tables which the operators wrote in this process. DataFrames that they returned read from these: call it
    when the results have been written."""
    while _WRITTEN:
        discard(spark, _WRITTEN.pop())


def write_table(df: DataFrame, path: str) -> None:
    df.write.option("compression", "zstd").parquet(path)


def read_table(spark: SparkSession, path: str, like: DataFrame) -> DataFrame:
    return spark.read.schema(like.schema).parquet(path)


def materialise(df: DataFrame, tag: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it back. This cuts the lineage and outlives lost executors."""
    spark = df.sparkSession
    path = new_path(spark, tag)
    write_table(df, path)
    return read_table(spark, path, df)


def discard(spark: SparkSession, path: str) -> None:
    """Delete a written intermediate table which no later plan reads."""
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


def map_arrow(df: DataFrame, function, schema: str) -> DataFrame:
    """``df.mapInArrow`` with this package present on the executors."""
    ship(df.sparkSession)
    return df.mapInArrow(function, schema)


def least_hashed(rows: DataFrame, most: int, seed: int, *keys: str) -> DataFrame:
    """The ``most`` rows of least hash of ``keys``. Of many rows, only those below a bound on the hash are sorted, twice as
    many as are wanted, so that what reaches one place does not grow with the number of partitions."""
    h = F.xxhash64(*keys, F.lit(seed))
    n = rows.count()
    if n > 4 * most:
        rows = rows.filter(h < F.lit(-(1 << 63) + (1 << 64) * 2 * most // n))
    return rows.orderBy(h, *keys).limit(most)


#: A key is heavy if it holds over this part of the rows: so there are fewer than 1024 heavy keys.
HEAVY = 1024


def heavy_keys(counts: DataFrame, key: str) -> DataFrame:
    """The heavy keys of ``counts`` (one row for each key; ``c``: its rows) and over how many ``parts`` to deal each."""
    share = max(1, (counts.agg(F.sum("c")).first()[0] or 0) // HEAVY)
    return counts.filter(F.col("c") > share).select(key, F.ceil(F.col("c") / share).cast("int").alias("parts"))


def salted_join(rows: DataFrame, one: DataFrame, key: str, heavy: DataFrame, salt) -> DataFrame:
    """``rows`` joined with ``one`` (one row for each key). The rows of a heavy key are dealt over its parts by ``salt``, an
    expression over ``rows``, and its row in ``one`` goes to each part: no key brings its rows into one task. ``heavy`` is
    broadcast: it has fewer than HEAVY rows, and fewer than 2 * HEAVY parts in all."""
    few = F.broadcast(heavy)
    left = rows.join(few, key, "left").withColumn("part", F.when(F.col("parts").isNull(), 0).otherwise(F.pmod(salt, F.col("parts"))).cast("int")).drop("parts")
    right = one.join(few, key, "left").withColumn("part", F.explode(F.sequence(F.lit(0), F.coalesce("parts", F.lit(1)) - 1))).drop("parts")
    return left.join(right, [key, "part"]).drop("part")


def slices(batch: pa.RecordBatch, column: str, limit: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Cut a batch into runs of rows whose ``column`` holds about ``limit`` bytes, so that long texts bound memory."""
    sizes = pc.binary_length(batch.column(column)).fill_null(0).to_pylist()
    start = total = 0
    for i, n in enumerate(sizes):
        if total and total + n > limit:
            yield batch.slice(start, i - start)
            start, total = i, 0
        total += n
    if start < len(sizes):
        yield batch.slice(start)


def blobs(buffer: bytes | memoryview, bounds) -> pa.Array:
    """A binary array over one buffer; ``bounds`` are byte offsets, one more than rows. No copy per row."""
    import numpy as np

    offsets = np.asarray(bounds, dtype=np.int64)
    if offsets[-1] < 2**31:
        return pa.Array.from_buffers(pa.binary(), len(offsets) - 1, [None, pa.py_buffer(offsets.astype(np.int32).tobytes()), pa.py_buffer(buffer)])
    return pa.Array.from_buffers(pa.large_binary(), len(offsets) - 1, [None, pa.py_buffer(offsets.tobytes()), pa.py_buffer(buffer)])

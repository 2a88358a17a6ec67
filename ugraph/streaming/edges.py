"""Reference edges from an event stream: users seen with one event type in one window are linked."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Users of one block, about: two blocks meet in one table of counts.
USER_BLOCK = 2048
#: Pairs over all windows from which blocks pay, and how many times the rows that they ship the pairs must be.
BLOCKS_FROM, PAIRS_A_ROW = 10_000_000, 4


def _timed(events: DataFrame, late: str | None) -> DataFrame:
    if dict(events.dtypes)["ts"] != "timestamp":  # a new column would lose the watermark that a stream has already
        events = events.withColumn("ts", F.col("ts").cast("timestamp"))
    return events.withWatermark("ts", late) if late else events


def _users(rows: DataFrame, window: Column) -> DataFrame:
    grouped = rows.groupBy("event_type", window.alias("w")).agg(F.array_sort(F.collect_set("user_id")).alias("users"))
    return grouped.select("event_type", F.col("w.start").alias("hour"), "users")


def windowed_users(events: DataFrame, width: str = "1 hour", late: str | None = None, slide: str | None = None) -> DataFrame:
    """event_type, hour (the window's start) and the users of that window; windows overlap where ``slide`` is less than
    ``width``. The same plan for a stream (``late``: its watermark) and a table."""
    return _users(_timed(events, late), F.window("ts", width, slide or width))


def session_users(events: DataFrame, gap: str = "30 minutes", late: str | None = None) -> DataFrame:
    """The same for sessions of an event type: events of which none is ``gap`` or more after the one before."""
    return _users(_timed(events, late), F.session_window("ts", gap))


def once(events: DataFrame, keys: list[str], late: str) -> DataFrame:
    """A stream without the repeats of ``keys`` that arrive within the watermark; a table without all repeats."""
    rows = _timed(events, late if events.isStreaming else None)
    return rows.dropDuplicatesWithinWatermark(keys) if events.isStreaming else rows.dropDuplicates(keys)


def pair_counts(windows: DataFrame) -> DataFrame:
    """src, dst and the number of windows that two users share. Where windows hold many of all users, blocks of users meet
    and no pair is shuffled; else a window's users come one row each and meet by key."""
    windows = windows.filter("event_type is not null and hour is not null")
    each = windows.select(F.explode("users").alias("u")).agg(F.approx_count_distinct("u").alias("users"))
    size = F.size("users").cast("long")
    told = windows.agg(F.sum(size).alias("rows"), F.sum(size * (size - 1) / 2).alias("pairs")).crossJoin(each).first()  # one row each
    blocks = max(1, -(-told["users"] // USER_BLOCK))
    if (told["pairs"] or 0) >= max(BLOCKS_FROM, PAIRS_A_ROW * told["rows"] * blocks):
        return _block_counts(windows, blocks)
    rows = windows.select("event_type", "hour", F.explode("users").alias("src"))
    other = rows.select("event_type", "hour", F.col("src").alias("dst"))
    return rows.join(other, ["event_type", "hour"]).filter("src < dst").groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n"))


def _block_counts(windows: DataFrame, blocks: int) -> DataFrame:
    """The same by blocks of users: each pair of blocks counts its shared windows in one table in memory, and gives each
    pair of users once."""
    rows = windows.select("event_type", "hour", F.explode("users").alias("user"))
    rows = rows.groupBy("event_type", "hour", F.pmod(F.xxhash64("user"), F.lit(blocks)).cast("int").alias("block")).agg(F.array_sort(F.collect_list("user")).alias("users"))
    rows = rows.withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    rows = rows.select(F.least("block", "other").alias("lo"), F.greatest("block", "other").alias("hi"), "block", "event_type", F.unix_micros("hour").alias("hour"), "users")

    def shared(table: pa.Table) -> pa.Table:
        block, lists = np.asarray(table.column("block")), table.column("users").combine_chunks()
        kind = np.asarray(table.column("event_type").combine_chunks().dictionary_encode().indices)
        hours, hour = np.unique(np.asarray(table.column("hour")), return_inverse=True)
        window, first, flat = kind.astype(np.int64) * len(hours) + hour, np.asarray(lists.offsets), np.asarray(lists.values)
        sides = []
        for c in ("lo", "hi"):
            own = np.flatnonzero(block == table.column(c)[0].as_py())
            users = np.unique(np.concatenate([flat[first[i] : first[i + 1]] for i in own])) if len(own) else flat[:0]
            sides.append((users, {window[i]: np.searchsorted(users, flat[first[i] : first[i + 1]]) for i in own}))
        (left, in_left), (right, in_right) = sides
        n = np.zeros((len(left), len(right)), dtype=np.int32)
        for w in in_left.keys() & in_right.keys():
            n[np.ix_(in_left[w], in_right[w])] += 1
        i, j = np.nonzero(n)
        a, b, n = left[i], right[j], n[i, j].astype(np.int64)
        if table.column("lo")[0] == table.column("hi")[0]:
            a, b, n = a[a < b], b[a < b], n[a < b]
        return pa.table({"src": np.minimum(a, b), "dst": np.maximum(a, b), "n": n})

    kind = windows.schema["users"].dataType.elementType.simpleString()
    return rows.groupBy("lo", "hi").applyInArrow(shared, f"src {kind}, dst {kind}, n long")


def pair_probabilities(counts: DataFrame, each: float = 0.5) -> DataFrame:
    """src, dst, p: every shared window is evidence of strength ``each``, and one true piece makes the edge."""
    return counts.select("src", "dst", (1 - F.pow(F.lit(1.0 - each), F.col("n"))).alias("p"))


def run_stream(stream: DataFrame, path: str, checkpoint: str, late: str = "1 hour", users=windowed_users):
    """Start the query that appends closed windows under ``path``; each is written once."""
    out = users(stream, late=late)
    return out.writeStream.outputMode("append").format("parquet").option("path", path).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()

"""Mixing sources to target weights by systematic sampling.

Within a source the documents stand in order of size; the prefix sums of their expected copies, moved by one random
offset of the source, give a document one copy for each integer that its interval holds. All of it is DataFrame
work: one range partitioning numbers the rows, and a small table (a row for each source and partition) carries the
running counts across partitions, so that no source has to fit in a task.

Defined cases: null text has size 0; a null source is a source of its own, last in order; a document of size 0 gets
copies as any other and adds no words; rows of equal doc_id are documents of their own; an empty table stays empty.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD, materialise

#: Weights of the sources in code-point order, repeating; most words a source may give, as a multiple of its own.
WEIGHTS, MOST = (5.0, 2.0, 1.0), 3.0
SEED = "mix-1"


def word_count(text: Column) -> Column:
    """Words of a text: one more than the blanks that end a word, found as places where a word starts."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def source_targets(sizes: DataFrame, weights: tuple[float, ...] = WEIGHTS, most: float = MOST) -> DataFrame:
    """source, source_size, target: the words of all documents shared by weight, no source above ``most`` times its
    size. In order of that limit per weight the limited sources come first; the rest share what is left."""
    by = Window.orderBy(F.col("source").asc_nulls_last())
    t = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    t = t.withColumn("k", (F.row_number().over(by) - 1) % len(weights))
    t = t.withColumn("weight", F.element_at(F.array(*[F.lit(w) for w in weights]), (F.col("k") + 1).cast("int")))
    t = t.withColumn("limit", F.col("source_size") * F.lit(most)).withColumn("ratio", F.col("limit") / F.col("weight"))
    before = Window.orderBy("ratio", F.col("source").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.partitionBy()
    t = t.withColumn("spent", F.coalesce(F.sum("limit").over(before), F.lit(0.0)))
    t = t.withColumn("weights_left", F.sum("weight").over(whole) - F.coalesce(F.sum("weight").over(before), F.lit(0.0)))
    t = t.withColumn("level", (F.sum("source_size").over(whole) - F.col("spent")) / F.col("weights_left"))
    # the first source whose ratio is not below its level is the first without a limit; its level holds from there on
    t = t.withColumn("level_free", F.min(F.when(F.col("ratio") >= F.col("level"), F.struct("ratio", "level"))).over(whole)["level"])
    target = F.least(F.col("limit"), F.col("weight") * F.col("level_free"))
    return t.select("source", "source_size", F.coalesce(target, F.col("limit")).alias("target"))


def offset_of(source: Column, seed: str = SEED) -> Column:
    """A number in [0, 1) from the source's name: the first 32 bits of a digest."""
    name = F.concat(F.lit(f"{seed}:"), F.coalesce(F.concat(F.lit("="), source), F.lit("null")))
    return F.conv(F.substring(F.md5(name), 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)


def with_copies(rows: DataFrame, tag: str = "mix", weights: tuple[float, ...] = WEIGHTS, most: float = MOST, seed: str = SEED) -> DataFrame:
    """``rows`` (doc_id, source, mix_size and any others) with mix_source_size, mix_target and mix_copies."""
    n = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    key = [F.col("source").asc_nulls_last(), F.col("mix_size"), F.col("doc_id")]
    placed = rows.repartitionByRange(n, *key).sortWithinPartitions(*key).withColumn("mix_id", F.monotonically_increasing_id())
    placed = materialise(placed, tag)
    part = F.shiftright("mix_id", 33)
    # a row for each source and partition of the write: no more than sources plus partitions
    runs = placed.groupBy("source", part.alias("part")).agg(F.count(F.lit(1)).alias("n"), F.min("mix_id").alias("first"), F.sum("mix_size").alias("size"))
    runs = materialise(runs, f"{tag}-runs")
    before = Window.partitionBy("source").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    runs = runs.withColumn("rank_base", F.coalesce(F.sum("n").over(before), F.lit(0)))
    runs = runs.join(F.broadcast(source_targets(runs, weights, most)).withColumnRenamed("source", "s"), F.col("source").eqNullSafe(F.col("s")))
    runs = runs.select(F.col("source").alias("run_source"), F.col("part").alias("run_part"), "first", "rank_base", F.col("source_size").alias("mix_source_size"), F.col("target").alias("mix_target"))
    joined = placed.join(F.broadcast(runs), (part == F.col("run_part")) & F.col("source").eqNullSafe(F.col("run_source")))
    rate = F.when(F.col("mix_source_size") > 0, F.col("mix_target") / F.col("mix_source_size")).otherwise(F.lit(0.0))
    rank = F.col("rank_base") + F.col("mix_id") - F.col("first")
    u = offset_of(F.col("source"), seed)
    copies = (F.floor((rank + 1) * rate + u) - F.floor(rank * rate + u)).cast("long")
    return joined.withColumn("mix_copies", copies).drop("mix_id", "run_source", "run_part", "first", "rank_base")


def mix_digest(docs: DataFrame) -> DataFrame:
    """op5: doc_id, size, source_size, target, taken."""
    rows = docs.select("doc_id", "source", word_count(F.col("text")).alias("mix_size"))
    return with_copies(rows).select("doc_id", F.col("mix_size").alias("size"), F.col("mix_source_size").alias("source_size"), F.col("mix_target").alias("target"), (F.col("mix_copies") * F.col("mix_size")).alias("taken"))


def mix_documents(docs: DataFrame) -> DataFrame:
    """The mix itself: each row of ``docs`` as often as it is taken, with its own columns."""
    rows = docs.withColumn("mix_size", word_count(F.col("text")))
    taken = with_copies(rows, "mix-docs").filter("mix_copies > 0")
    return taken.withColumn("mix_copy", F.explode(F.sequence(F.lit(1), F.col("mix_copies").cast("int")))).select(*[F.col(f"`{c}`") for c in docs.columns])


#: The same rows in SQL. The order of equal sizes is by doc_id, as above.
MIX_SQL = r"""
WITH sized AS (
  SELECT doc_id, source, CAST(coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS BIGINT) AS size FROM documents),
per AS (SELECT source, CAST(sum(size) AS DOUBLE) AS source_size FROM sized GROUP BY source),
weighted AS (SELECT source, source_size, CASE (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 WHEN 0 THEN 5.0::DOUBLE WHEN 1 THEN 2.0::DOUBLE ELSE 1.0::DOUBLE END AS weight FROM per),
limited AS (SELECT *, 3.0::DOUBLE * source_size AS cap, 3.0::DOUBLE * source_size / weight AS ratio FROM weighted),
levels AS (
  SELECT *, (sum(source_size) OVER () - coalesce(sum(cap) OVER w, 0)) / (sum(weight) OVER () - coalesce(sum(weight) OVER w, 0)) AS level
  FROM limited WINDOW w AS (ORDER BY ratio, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
free AS (SELECT level FROM levels WHERE ratio >= level ORDER BY ratio, level LIMIT 1),
targets AS (SELECT source, source_size, least(cap, weight * (SELECT level FROM free)) AS target,
  CAST(('0x' || substr(md5('mix-1:' || coalesce('=' || source, 'null')), 1, 8)) AS BIGINT)::DOUBLE / 4294967296.0::DOUBLE AS u FROM levels),
ranked AS (
  SELECT s.doc_id, s.size, t.source_size, t.target, t.u, CASE WHEN t.source_size > 0 THEN t.target / t.source_size ELSE 0 END AS rate,
         row_number() OVER (PARTITION BY s.source ORDER BY s.size, s.doc_id) - 1 AS rank
  FROM sized s JOIN targets t ON s.source IS NOT DISTINCT FROM t.source)
SELECT doc_id, size, CAST(source_size AS BIGINT) AS source_size, target,
       CAST((floor((rank + 1) * rate + u) - floor(rank * rate + u)) AS BIGINT) * size AS taken
FROM ranked
"""

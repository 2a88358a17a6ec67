"""Cumulative-snapshot collapse of logged conversations, and rendering of those that remain, by DataFrame functions.

Logs often hold a conversation again and again as it grows. Each turn gets two 64-bit digests of its place and
content; the running exclusive-or of those is the hash of the turns so far. A conversation whose last hash is among
the running hashes of a longer one at the same turn is a snapshot of it and goes, by an anti-join; of equal
conversations the one of least conv_id stays. A turn's place is its rank by (turn, role, text) in the conversation.

Defined cases: rows without a conv_id belong to no conversation and are left out; null role or text count as values
of their own and render as empty; repeated rows count as turns; extra columns are ignored; an empty table gives none.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import materialise


def running_hashes(conversations: DataFrame) -> DataFrame:
    """conv_id, place, role, text, h1 and h2 (hashes of the turns up to this one), n_turns."""
    order = [F.col("turn").asc_nulls_first(), F.col("role").asc_nulls_first(), F.col("text").asc_nulls_first()]
    turns = conversations.filter("conv_id is not null").select("conv_id", "turn", F.col("role").cast("string").alias("role"), F.col("text").cast("string").alias("text"))
    by = Window.partitionBy("conv_id").orderBy(*order)
    placed = turns.withColumn("place", F.row_number().over(by).cast("long"))
    content = ["place", F.col("role").isNull(), F.coalesce("role", F.lit("")), F.col("text").isNull(), F.coalesce("text", F.lit(""))]
    so_far = Window.partitionBy("conv_id").orderBy("place").rowsBetween(Window.unboundedPreceding, 0)
    for name, seed in (("h1", "a"), ("h2", "b")):
        placed = placed.withColumn(name, F.bit_xor(F.xxhash64(F.lit(seed), *content)).over(so_far))
    return placed.withColumn("n_turns", F.count(F.lit(1)).over(Window.partitionBy("conv_id")))


def collapse(conversations: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The hashed turns, and conv_id, n_turns, n_copies of the conversations that remain."""
    hashed = materialise(running_hashes(conversations), "chat-turns")
    keys = ["place", "h1", "h2"]
    whole = hashed.filter("place = n_turns").groupBy(*keys).agg(F.min("conv_id").alias("conv_id"), F.count(F.lit(1)).alias("n_copies"))
    inner = hashed.filter("place < n_turns").select(*keys).distinct()
    kept = whole.join(inner, keys, "left_anti")
    return hashed, kept.select("conv_id", F.col("place").alias("n_turns"), "n_copies")


def render(conversations: DataFrame, opening: str = "<|", middle: str = "|>\n", closing: str = "\n") -> DataFrame:
    """op7: conv_id, n_turns, n_copies and the rendered text of every maximal conversation."""
    hashed, kept = collapse(conversations)
    turns = hashed.select("conv_id", "place", "role", "text").join(kept, "conv_id")
    turn = F.concat(F.lit(opening), F.coalesce("role", F.lit("")), F.lit(middle), F.coalesce("text", F.lit("")), F.lit(closing))
    grouped = turns.groupBy("conv_id", "n_turns", "n_copies").agg(F.sort_array(F.collect_list(F.struct("place", turn.alias("line")))).alias("lines"))
    return grouped.select("conv_id", "n_turns", "n_copies", F.array_join("lines.line", "").alias("text"))


#: The same rows in SQL, by comparing the turns themselves.
CHAT_SQL = r"""
WITH placed AS (
  SELECT conv_id, row_number() OVER (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role NULLS FIRST, text NULLS FIRST) AS place, role, text
  FROM conversations WHERE conv_id IS NOT NULL),
lined AS (
  SELECT conv_id, place, '<|' || coalesce(role, '') || '|>' || chr(10) || coalesce(text, '') || chr(10) AS line,
         CASE WHEN role IS NULL THEN 'n' ELSE 'r' || length(role) || ':' || role END || CASE WHEN text IS NULL THEN 'n' ELSE 't' || length(text) || ':' || text END AS mark
  FROM placed),
prefixes AS (
  SELECT conv_id, place, string_agg(line, '' ORDER BY place) OVER w AS body, string_agg(mark, '|' ORDER BY place) OVER w AS marks,
         count(*) OVER (PARTITION BY conv_id) AS n_turns
  FROM lined WINDOW w AS (PARTITION BY conv_id ORDER BY place ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)),
whole AS (SELECT min(conv_id) AS conv_id, place AS n_turns, count(*) AS n_copies, marks, min(body) AS text FROM prefixes WHERE place = n_turns GROUP BY place, marks)
SELECT conv_id, CAST(n_turns AS BIGINT) AS n_turns, CAST(n_copies AS BIGINT) AS n_copies, text FROM whole w
WHERE NOT EXISTS (SELECT 1 FROM prefixes p WHERE p.place < p.n_turns AND p.place = w.n_turns AND p.marks = w.marks)
"""

"""Reference graphs derived from the given tables, and the SQL of the same derivations."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.tables import u, u_sql
from ..operators.entity_graph import ReferenceGraph


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def costar_edges(spark: SparkSession, sf_dir: str, share: float = 0.2, directed: bool = False) -> DataFrame:
    """Parts of the two dearest lines of an order are linked; directed: from the dearest."""
    by = Window.partitionBy("l_orderkey").orderBy(F.desc("l_extendedprice"), "l_linenumber", "l_partkey")
    top = _table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", F.row_number().over(by).alias("rn")).filter("rn <= 2")
    pair = top.groupBy("l_orderkey").agg(F.max(F.when(F.col("rn") == 1, F.col("l_partkey"))).alias("a"), F.max(F.when(F.col("rn") == 2, F.col("l_partkey"))).alias("b")).filter("a <> b")
    ends = (F.col("a"), F.col("b")) if directed else (F.least("a", "b"), F.greatest("a", "b"))
    pair = pair.select(ends[0].alias("src"), ends[1].alias("dst")).distinct()
    key = F.col("src") * 20011 + F.col("dst")
    return pair.withColumn("p", F.when(u(key, 3) < share, u(key, 4)).otherwise(F.lit(1.0))).filter("p > 0")


def part_labels(spark: SparkSession, sf_dir: str, share: float = 0.2) -> DataFrame:
    part = _table(spark, sf_dir, "part").select("p_partkey", "p_type")
    kinds = [r[0] for r in part.select("p_type").distinct().orderBy("p_type").collect()]  # the label alphabet
    other = F.element_at(F.array(*[F.lit(k) for k in kinds]), ((F.col("p_partkey") + 3) % len(kinds) + 1).cast("int"))
    rows = part.withColumn("other", other).withColumn("split", (u(F.col("p_partkey"), 1) < share) & (F.col("other") != F.col("p_type")))
    own = 0.5 + 0.5 * u(F.col("p_partkey"), 2)
    both = F.when(F.col("split"), F.array(F.struct(F.col("p_type").alias("label"), own.alias("p")), F.struct(F.col("other").alias("label"), (1 - own).alias("p")))).otherwise(F.array(F.struct(F.col("p_type").alias("label"), F.lit(1.0).alias("p"))))
    return rows.select(F.col("p_partkey").alias("ref_id"), F.explode(both).alias("x")).select("ref_id", "x.label", "x.p").filter("p > 0")


def part_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Consecutive keys of equal name, brand and, where there are 1,000 parts or more, size; four to a block at most."""
    part = _table(spark, sf_dir, "part")
    size = F.col("p_size") if part.count() >= 1000 else F.lit(0)
    by = Window.partitionBy("p_name", "p_brand", size).orderBy("p_partkey")
    rows = part.select(F.col("p_partkey").alias("set_id"), F.row_number().over(by).alias("rn"), F.lead("p_partkey").over(by).alias("b")).filter("rn <= 3 and b is not null")
    return rows.select("set_id", F.array("set_id", "b").alias("members"), (0.05 + 0.9 * u(F.col("set_id"), 5)).alias("p"))


def costar(spark: SparkSession, sf_dir: str, share: float = 0.2, directed: bool = False) -> ReferenceGraph:
    return ReferenceGraph(part_labels(spark, sf_dir, share), costar_edges(spark, sf_dir, share, directed), part_sets(spark, sf_dir), directed)


def collab_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers who bought the same part of the same supplier; n such purchases give 1 - 0.5**n."""
    line = _table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey")
    orders = _table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey")
    bought = line.join(orders, "l_orderkey").select("l_partkey", "l_suppkey", "o_custkey").distinct()
    other = bought.select("l_partkey", "l_suppkey", F.col("o_custkey").alias("dst"))
    pair = bought.join(other, ["l_partkey", "l_suppkey"]).filter("o_custkey < dst").groupBy(F.col("o_custkey").alias("src"), "dst").agg(F.count(F.lit(1)).alias("n"))
    return pair.select("src", "dst", (1 - F.pow(F.lit(0.5), "n")).alias("p"))


def customer_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("ref_id"), F.col("c_mktsegment").alias("label"), F.lit(1.0).alias("p"))


def deletion_keys(name: Column) -> Column:
    """The string, and the string without each one of its characters; of strings of over 20 characters also without two.
    Strings within that many edits of one another share a key."""
    once = lambda x: F.transform(F.sequence(F.lit(1), F.length(x)), lambda i: F.concat(F.substring(x, F.lit(1), i - 1), F.substring(x, i + 1, F.length(x))))
    some = F.when(F.length(name) > 0, once(name)).otherwise(F.array())
    twice = F.when(F.length(name) > 20, F.flatten(F.transform(once(name), once))).otherwise(F.array().cast("array<string>"))
    return F.array_distinct(F.concat(F.array(name), some, twice))


def similar_customers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """a, b, distance: customers of one nation and segment whose names (of up to 30 characters) have a similarity over 0.9,
    found by the deletion keys that they share and confirmed on the names."""
    rows = _table(spark, sf_dir, "customer").select("c_nationkey", "c_mktsegment", F.col("c_custkey").alias("a"), "c_name")
    keyed = rows.withColumn("key", F.explode(deletion_keys(F.col("c_name"))))
    other = keyed.select("c_nationkey", "c_mktsegment", "key", F.col("a").alias("b"), F.col("c_name").alias("other"))
    pairs = keyed.join(other, ["c_nationkey", "c_mktsegment", "key"]).filter("a < b").select("a", "b", "c_name", "other").distinct()
    near = F.levenshtein("c_name", "other")
    return pairs.filter(1 - near / F.length("c_name") > 0.9).select("a", "b", near.alias("distance"))


#: A pair's set has the number a * SET_FACTOR + b.
SET_FACTOR = 100003


def customer_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every pair of customers of one nation and segment whose names are similar."""
    rows = similar_customers(spark, sf_dir).withColumn("set_id", F.col("a") * SET_FACTOR + F.col("b"))
    return rows.select("set_id", F.array("a", "b").alias("members"), (0.05 + 0.9 * u(F.col("set_id"), 5)).alias("p"))


def collab(spark: SparkSession, sf_dir: str, correlated: bool = True) -> ReferenceGraph:
    """Edges that hold less often between different labels: 0.8 of the base probability."""
    edges, labels = collab_edges(spark, sf_dir), customer_labels(spark, sf_dir)
    cpt = None
    if correlated:
        kinds = labels.select("label").distinct()
        a, b = kinds.select(F.col("label").alias("l_src")), kinds.select(F.col("label").alias("l_dst"))
        pairs = F.broadcast(a.crossJoin(b))  # label pairs of the alphabet
        cpt = edges.crossJoin(pairs).select("src", "dst", "l_src", "l_dst", F.when(F.col("l_src") == F.col("l_dst"), F.col("p")).otherwise(0.8 * F.col("p")).alias("p"))
    return ReferenceGraph(labels, edges, customer_sets(spark, sf_dir), False, cpt)


def tiny(spark: SparkSession) -> ReferenceGraph:
    """The expert-finding example: four mentions, the last two of which may be one person."""
    labels = spark.createDataFrame([(1, "i", 0.75), (1, "r", 0.25), (2, "a", 1.0), (3, "r", 1.0), (4, "i", 1.0)], "ref_id long, label string, p double")
    edges = spark.createDataFrame([(1, 2, 0.9), (2, 3, 1.0), (2, 4, 0.5)], "src long, dst long, p double")
    return ReferenceGraph(labels, edges, spark.createDataFrame([(3, [3, 4], 0.8)], "set_id long, members array<long>, p double"))


def doc_duplicate_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents of equal text: least doc_id and number."""
    return _table(spark, sf_dir, "documents").groupBy(F.sha2("text", 256).alias("k")).agg(F.min("doc_id").alias("set_id"), F.count(F.lit(1)).alias("n")).filter("n > 1").select("set_id", "n")


def costar_sql(share: float = 0.2, directed: bool = False) -> str:
    """Common table expressions from the tables to entity_labels, entity_edges, entities and marginals."""
    ends = ("a.l_partkey", "b.l_partkey") if directed else ("least(a.l_partkey, b.l_partkey)", "greatest(a.l_partkey, b.l_partkey)")
    both = "SELECT src, dst, p FROM ref_edges" + ("" if directed else " UNION ALL SELECT dst, src, p FROM ref_edges")
    key = "src * 20011 + dst"
    return f"""
ranked AS (SELECT l_orderkey, l_partkey, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_extendedprice DESC, l_linenumber, l_partkey) AS rn FROM lineitem),
pairs AS (SELECT DISTINCT {ends[0]} AS src, {ends[1]} AS dst FROM ranked a JOIN ranked b ON a.l_orderkey = b.l_orderkey AND a.rn = 1 AND b.rn = 2 AND a.l_partkey <> b.l_partkey),
ref_edges AS (SELECT * FROM (SELECT src, dst, CASE WHEN {u_sql(key, 3)} < {share}::DOUBLE THEN {u_sql(key, 4)} ELSE 1.0::DOUBLE END AS p FROM pairs) WHERE p > 0),
kinds AS (SELECT t, row_number() OVER (ORDER BY t) - 1 AS pos FROM (SELECT DISTINCT p_type AS t FROM part)),
split AS (SELECT p_partkey AS ref_id, p_type AS own, t AS other, {u_sql("p_partkey", 1)} < {share}::DOUBLE AND t <> p_type AS two, 0.5::DOUBLE + 0.5::DOUBLE * {u_sql("p_partkey", 2)} AS q
  FROM part JOIN kinds ON pos = (p_partkey + 3) % (SELECT count(*) FROM kinds)),
ref_labels AS (SELECT * FROM (SELECT ref_id, own AS label, CASE WHEN two THEN q ELSE 1.0::DOUBLE END AS p FROM split UNION ALL SELECT ref_id, other, 1.0::DOUBLE - q FROM split WHERE two) WHERE p > 0),
blocks AS (SELECT p_partkey AS set_id, row_number() OVER w AS rn, lead(p_partkey) OVER w AS b FROM (SELECT *, CASE WHEN (SELECT count(*) FROM part) >= 1000 THEN p_size ELSE 0 END AS sz FROM part) WINDOW w AS (PARTITION BY p_name, p_brand, sz ORDER BY p_partkey)),
ref_sets AS (SELECT set_id, set_id AS a, b, 0.05::DOUBLE + 0.9::DOUBLE * {u_sql("set_id", 5)} AS p FROM blocks WHERE rn <= 3 AND b IS NOT NULL),
{identity_sql()},
both_ways AS ({both}),
{entity_sql()}"""


def identity_sql() -> str:
    """From ref_sets (pairs a, b in chains) and ref_labels to entities, worlds and marginals. With sets of two, a world
    is a matching; in a chain of four at most it has two pairs at most."""
    return """
touch AS (SELECT set_id, a AS ref_id, p FROM ref_sets UNION ALL SELECT set_id, b, p FROM ref_sets),
prior AS (SELECT ref_id, exp(avg(ln(greatest(sqrt(p * (1 - p)), 1e-6::DOUBLE)))) AS q FROM touch GROUP BY ref_id),
reach AS (
  SELECT ref_id, least(min(x1), min(x2), min(x3)) AS comp_id FROM (
    SELECT t.ref_id, least(s1.a, s1.b) AS x1, least(s2.a, s2.b) AS x2, least(s3.a, s3.b) AS x3
    FROM touch t JOIN ref_sets s1 ON s1.set_id = t.set_id
    JOIN ref_sets s2 ON s2.a IN (s1.a, s1.b) OR s2.b IN (s1.a, s1.b)
    JOIN ref_sets s3 ON s3.a IN (s2.a, s2.b) OR s3.b IN (s2.a, s2.b)) GROUP BY ref_id),
tied AS (
  SELECT entity_id, comp_id, CAST(1 AS BIGINT) << CAST(row_number() OVER (PARTITION BY comp_id ORDER BY entity_id) - 1 AS INTEGER) AS mask FROM (
    SELECT ref_id AS entity_id, comp_id FROM reach UNION ALL SELECT s.set_id + 1000000000, r.comp_id FROM ref_sets s JOIN reach r ON r.ref_id = s.a)),
gain AS (SELECT s.set_id, s.a, s.b, r.comp_id, s.p * s.p / (pa.q * pb.q) AS g, t.mask AS m, ta.mask | tb.mask AS gone
  FROM ref_sets s JOIN prior pa ON pa.ref_id = s.a JOIN prior pb ON pb.ref_id = s.b JOIN reach r ON r.ref_id = s.a
  JOIN tied t ON t.entity_id = s.set_id + 1000000000 JOIN tied ta ON ta.entity_id = s.a JOIN tied tb ON tb.entity_id = s.b),
empty_world AS (SELECT r.comp_id, CAST(sum(t.mask) AS BIGINT) AS mask FROM reach r JOIN tied t ON t.entity_id = r.ref_id GROUP BY r.comp_id),
weighed AS (
  SELECT comp_id, mask, 1.0::DOUBLE AS wt FROM empty_world
  UNION ALL SELECT e.comp_id, e.mask - g.gone + g.m, g.g FROM empty_world e JOIN gain g ON g.comp_id = e.comp_id
  UNION ALL SELECT e.comp_id, e.mask - g.gone - h.gone + g.m + h.m, g.g * h.g FROM empty_world e JOIN gain g ON g.comp_id = e.comp_id
    JOIN gain h ON h.comp_id = e.comp_id AND g.set_id < h.set_id AND g.a NOT IN (h.a, h.b) AND g.b NOT IN (h.a, h.b)),
worlds AS (SELECT comp_id, mask, wt / sum(wt) OVER (PARTITION BY comp_id) AS p FROM weighed),
marginals AS (SELECT w.comp_id, s.mask, sum(w.p) AS p FROM worlds w JOIN (SELECT CAST(range AS BIGINT) AS mask FROM range(1, 1024)) s ON (w.mask & s.mask) = s.mask GROUP BY w.comp_id, s.mask),
members AS (SELECT DISTINCT ref_id AS entity_id, ref_id, 1 AS size FROM ref_labels UNION ALL SELECT set_id + 1000000000, ref_id, 2 FROM touch),
entities AS (SELECT m.entity_id, t.comp_id, coalesce(t.mask, 0) AS mask, coalesce(k.p, 1.0::DOUBLE) AS p_exist FROM (SELECT DISTINCT entity_id FROM members) m
  LEFT JOIN tied t ON t.entity_id = m.entity_id LEFT JOIN marginals k ON k.comp_id = t.comp_id AND k.mask = t.mask)"""


def entity_sql() -> str:
    return """
entity_labels AS (SELECT m.entity_id, l.label, sum(l.p) / max(m.size) AS p FROM members m JOIN ref_labels l ON l.ref_id = m.ref_id GROUP BY m.entity_id, l.label),
entity_edges AS (SELECT * FROM (
  SELECT s.entity_id AS src, t.entity_id AS dst, sum(e.p) / max(s.size * t.size) AS p FROM both_ways e JOIN members s ON s.ref_id = e.src JOIN members t ON t.ref_id = e.dst
  WHERE s.entity_id <> t.entity_id GROUP BY s.entity_id, t.entity_id) x
  WHERE NOT EXISTS (SELECT 1 FROM members c JOIN members d ON c.ref_id = d.ref_id WHERE c.entity_id = x.src AND d.entity_id = x.dst))"""

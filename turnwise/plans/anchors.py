"""Anchor pool and stratified pick, built on the given tables.

An anchor is a (segment, priority, status, year) combination that the orders hold.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import drift
from ..operators import construct, sampling
from ..sources.io import table

PARAMETERS = ["segment", "priority", "status", "year"]


def facts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lines with their order's four parameters; money in whole cents."""
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", F.col("o_orderpriority").alias("priority"), F.col("o_orderstatus").alias("status"), F.year("o_orderdate").alias("year"))
    customers = table(spark, sf_dir, "customer").select("c_custkey", F.col("c_mktsegment").alias("segment"))
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_returnflag", F.round(F.col("l_extendedprice") * 100).cast("long").alias("cents"))
    placed = orders.join(customers, F.col("o_custkey") == F.col("c_custkey"))
    return lines.join(placed, F.col("l_orderkey") == F.col("o_orderkey")).select(*PARAMETERS, "l_returnflag", "cents")


def key_of() -> F.Column:
    return F.concat_ws("/", *[F.col(p).cast("string") for p in PARAMETERS])


def anchors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """anchor_key, parameters, n_lines, tier, split, subtype."""
    pool = facts(spark, sf_dir).groupBy(*PARAMETERS).agg(F.count("*").alias("n_lines"))
    named = pool.withColumn("anchor_key", key_of())
    tier = F.when(F.col("priority").isin("1-URGENT", "2-HIGH"), "advanced").when(F.col("priority") == "5-LOW", "basic").otherwise("intermediate")
    named = named.withColumn("tier", tier).withColumn("split", F.when(F.col("year") % 2 == 0, "dev").otherwise("train"))
    items = F.array(*[drift.item("FILTER", f"{p} = ?", F.col(p)) for p in PARAMETERS], drift.item("PROJECT", "l_returnflag"))
    return construct.assign_subtype(named.withColumn("items", items), "items", "anchor_key").drop("items")


def anchor_catalogue(spark: SparkSession, sf_dir: str) -> DataFrame:
    return anchors(spark, sf_dir).select(*PARAMETERS, "n_lines")


def anchor_stratified(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sampling.stratified(anchors(spark, sf_dir), ["tier", "split"], "anchor_key", per_stratum=10).select("tier", "split", "anchor_key")


def anchor_allotted(spark: SparkSession, sf_dir: str) -> DataFrame:
    picked = sampling.stratified(anchors(spark, sf_dir), ["tier", "split"], "anchor_key", n_total=100)
    return picked.groupBy("tier", "split").agg(F.count("*").alias("n"))


def anchor_subtypes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return anchors(spark, sf_dir).select("anchor_key", "subtype")


_A = """
WITH f AS (SELECT c_mktsegment AS segment, o_orderpriority AS priority, o_orderstatus AS status, CAST(year(o_orderdate) AS INT) AS year, l_returnflag, CAST(round(l_extendedprice * 100) AS BIGINT) AS cents
  FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey),
a0 AS (SELECT segment, priority, status, year, count(*) AS n_lines, concat_ws('/', segment, priority, status, CAST(year AS VARCHAR)) AS anchor_key FROM f GROUP BY segment, priority, status, year),
a AS (SELECT *, CASE WHEN priority IN ('1-URGENT', '2-HIGH') THEN 'advanced' WHEN priority = '5-LOW' THEN 'basic' ELSE 'intermediate' END AS tier,
  CASE WHEN year % 2 = 0 THEN 'dev' ELSE 'train' END AS split,
  CASE (row_number() OVER (ORDER BY md5(anchor_key), anchor_key) - 1) % 3 WHEN 0 THEN 'value' WHEN 1 THEN 'constraint' ELSE 'projection' END AS subtype FROM a0)
"""
QUERIES = {
    f.__name__: f
    for f in (anchor_catalogue, anchor_stratified, anchor_allotted, anchor_subtypes)
}
ORACLES = {
    "anchor_catalogue": _A + "SELECT segment, priority, status, year, n_lines FROM a",
    "anchor_stratified": _A + "SELECT tier, split, anchor_key FROM (SELECT *, row_number() OVER (PARTITION BY tier, split ORDER BY md5('42|' || anchor_key), anchor_key) AS r FROM a) x WHERE r <= 10",
    "anchor_allotted": _A
    + """SELECT tier, split, least(n, CAST(base AS BIGINT) + CASE WHEN row_number() OVER (ORDER BY exact - base DESC, tier, split) <= 100 - sum(base) OVER () THEN 1 ELSE 0 END) AS n
    FROM (SELECT tier, split, n, 100.0 * n / sum(n) OVER () AS exact, floor(100.0 * n / sum(n) OVER ()) AS base FROM (SELECT tier, split, count(*) AS n FROM a GROUP BY tier, split) x) y""",
    "anchor_subtypes": _A + "SELECT anchor_key, subtype FROM a",
}

"""Revision log: the lines of an order as successive states of one request, each compared with the next.

State of a line: filters returnflag, linestatus, and a discount floor if the discount is at least 0.05; outputs
one of three aggregates by quantity modulo 3, and a limit if the quantity is over 40.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions import complexity, drift
from ..sources.io import table

TIES = ["l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_extendedprice"]


def state() -> Column:
    floor = F.when(F.col("l_discount") >= 0.05, drift.item("FILTER", "lineitem.l_discount >= ?", F.lit("0.05")))
    limit = F.when(F.col("l_quantity") > 40, drift.item("LIMIT", "?", F.lit("10")))
    aggregate = F.struct(
        F.lit("PROJECT").alias("kind"), F.lit("").alias("scope"), F.concat(F.lit("aggregate "), (F.col("l_quantity").cast("long") % 3).cast("string")).alias("skeleton"), F.array().cast("array<string>").alias("literals")
    )
    items = F.array(drift.item("FILTER", "lineitem.l_returnflag = ?", F.col("l_returnflag")), drift.item("FILTER", "lineitem.l_linestatus = ?", F.col("l_linestatus")), floor, aggregate, limit)
    return F.array_sort(F.array_compact(items))


def revisions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """order_key, step, pre, post: one exchange by order."""
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", *TIES, "l_discount", "l_quantity", "l_returnflag", "l_linestatus")
    w = Window.partitionBy("l_orderkey").orderBy(*TIES)
    steps = lines.select(F.col("l_orderkey").alias("order_key"), F.row_number().over(w).alias("step"), state().alias("pre"), F.lead(state()).over(w).alias("post"))
    return steps.filter("post IS NOT NULL")


def drift_status(spark: SparkSession, sf_dir: str) -> DataFrame:
    return revisions(spark, sf_dir).select("order_key", "step", drift.is_drift(F.col("pre"), F.col("post")).alias("is_drift"))


def drift_subtype(spark: SparkSession, sf_dir: str) -> DataFrame:
    return revisions(spark, sf_dir).groupBy(drift.classify(F.col("pre"), F.col("post")).alias("subtype")).agg(F.count("*").alias("n"))


def _spelled(items: Column) -> Column:
    return F.array_join(F.array_sort(F.transform(items, lambda x: F.concat(x["skeleton"], F.lit("="), F.array_join(x["literals"], ",")))), "|")


def drift_delta(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = drift.delta(F.col("pre"), F.col("post"))
    return revisions(spark, sf_dir).select("order_key", "step", *[_spelled(d[x]).alias(x) for x in ("lost", "gained", "kept")])


def drift_lost_long(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The relational form of the test: an anti join of exploded commitments."""
    r = revisions(spark, sf_dir)
    long = lambda c: r.select("order_key", "step", F.inline(c))
    found = drift.lost(long("pre"), long("post"), ["order_key", "step"])
    return found.select("order_key", "step", "kind", "skeleton", F.coalesce(F.get("literals", F.lit(0)), F.lit("")).alias("literal"))


def drift_admissible(spark: SparkSession, sf_dir: str) -> DataFrame:
    a = drift.admissible(F.col("pre"))
    return revisions(spark, sf_dir).select("order_key", "step", *[F.array_contains(a, k).alias(f"can_{k}") for k in (drift.VALUE, drift.CONSTRAINT, drift.PROJECTION)])


def single_literal_swap(spark: SparkSession, sf_dir: str) -> DataFrame:
    return revisions(spark, sf_dir).select("order_key", "step", drift.single_literal_swap(drift.filters_of(F.col("pre")), drift.filters_of(F.col("post"))).alias("swap"))


def drift_split(spark: SparkSession, sf_dir: str) -> DataFrame:
    w, o = drift.split(F.col("pre"))
    return revisions(spark, sf_dir).select("order_key", "step", _spelled(w).alias("filters"), _spelled(o).alias("outputs"))


def complexity_tiers(spark: SparkSession, sf_dir: str) -> DataFrame:
    points = complexity.score(F.col("pre"), subtype=drift.classify(F.col("pre"), F.col("post")))
    scored = revisions(spark, sf_dir).select(points.alias("score"))
    return scored.groupBy(complexity.tier(F.col("score"), (4, 5)).alias("tier")).agg(F.count("*").alias("n"), F.min("score").alias("min_score"), F.max("score").alias("max_score"))


def post_complexity(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = revisions(spark, sf_dir).select(drift.classify(F.col("pre"), F.col("post")).alias("subtype"), complexity.score(F.col("post")).alias("score"))
    return r.groupBy("subtype").agg(F.count("*").alias("n"), F.round(F.avg("score"), 6).alias("mean_score"))


_P = """
WITH s AS (SELECT l_orderkey AS order_key, row_number() OVER w AS step, l_returnflag AS rf, l_linestatus AS ls,
  l_discount >= 0.05 AS dc, CAST(l_quantity AS BIGINT) % 3 AS ag, l_quantity > 40 AS lm
  FROM lineitem WINDOW w AS (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_shipdate, l_extendedprice)),
p AS (SELECT a.*, b.rf AS rf2, b.ls AS ls2, b.dc AS dc2, b.ag AS ag2, b.lm AS lm2 FROM s a JOIN s b ON a.order_key = b.order_key AND b.step = a.step + 1),
q AS (SELECT *, (rf <> rf2 OR ls <> ls2 OR (dc AND NOT dc2) OR ag <> ag2 OR (lm AND NOT lm2)) AS is_drift,
  (dc = dc2 AND CAST(rf <> rf2 AS INT) + CAST(ls <> ls2 AS INT) = 1) AS swap FROM p),
c AS (SELECT *, CASE WHEN NOT is_drift THEN 'not_drift' WHEN ag = ag2 AND lm = lm2 AND swap THEN 'value'
  WHEN ag = ag2 AND lm = lm2 AND rf = rf2 AND ls = ls2 AND dc AND NOT dc2 THEN 'constraint'
  WHEN rf = rf2 AND ls = ls2 AND dc = dc2 THEN 'projection' ELSE 'reject' END AS subtype FROM q),
i AS (SELECT order_key, step, unnest([
    {'k': 'FILTER', 's': 'lineitem.l_returnflag = ?', 'a': rf, 'b': rf2}, {'k': 'FILTER', 's': 'lineitem.l_linestatus = ?', 'a': ls, 'b': ls2},
    {'k': 'FILTER', 's': 'lineitem.l_discount >= ?', 'a': CASE WHEN dc THEN '0.05' END, 'b': CASE WHEN dc2 THEN '0.05' END},
    {'k': 'LIMIT', 's': '?', 'a': CASE WHEN lm THEN '10' END, 'b': CASE WHEN lm2 THEN '10' END},
    {'k': 'PROJECT', 's': 'aggregate 0', 'a': CASE WHEN ag = 0 THEN '' END, 'b': CASE WHEN ag2 = 0 THEN '' END},
    {'k': 'PROJECT', 's': 'aggregate 1', 'a': CASE WHEN ag = 1 THEN '' END, 'b': CASE WHEN ag2 = 1 THEN '' END},
    {'k': 'PROJECT', 's': 'aggregate 2', 'a': CASE WHEN ag = 2 THEN '' END, 'b': CASE WHEN ag2 = 2 THEN '' END}]) AS x FROM p),
e AS (SELECT order_key, step, x.k AS kind, x.s AS skeleton, x.a AS a, x.b AS b FROM i)
"""
_AGG = "coalesce(string_agg(skeleton || '=' || {v}, '|' ORDER BY skeleton || '=' || {v}) FILTER ({c}), '')"
_SCORE = "2 + CAST({p}dc{n} AS INT) + 1 + CAST({p}lm{n} AS INT)"

QUERIES = {f.__name__: f for f in (drift_status, drift_subtype, drift_delta, drift_lost_long, drift_admissible, single_literal_swap, drift_split, complexity_tiers, post_complexity)}
ORACLES = {
    "drift_status": _P + "SELECT order_key, step, is_drift FROM q",
    "drift_subtype": _P + "SELECT subtype, count(*) AS n FROM c GROUP BY subtype",
    "drift_delta": _P
    + f"SELECT order_key, step, {_AGG.format(v='a', c='a IS NOT NULL AND a IS DISTINCT FROM b')} AS lost, {_AGG.format(v='b', c='b IS NOT NULL AND a IS DISTINCT FROM b')} AS gained, "
    + f"{_AGG.format(v='a', c='a = b')} AS kept FROM e GROUP BY order_key, step",
    "drift_lost_long": _P + "SELECT order_key, step, kind, skeleton, a AS literal FROM e WHERE a IS NOT NULL AND a IS DISTINCT FROM b",
    "drift_admissible": _P + "SELECT order_key, step, true AS can_value, true AS can_constraint, true AS can_projection FROM q",
    "single_literal_swap": _P + "SELECT order_key, step, swap FROM q",
    "drift_split": _P
    + f"""SELECT order_key, step, {_AGG.format(v='a', c="a IS NOT NULL AND kind = 'FILTER'")} AS filters, {_AGG.format(v='a', c="a IS NOT NULL AND kind <> 'FILTER'")} AS outputs FROM e GROUP BY order_key, step""",
    "complexity_tiers": _P
    + f"""SELECT CASE WHEN score <= 4 THEN 'basic' WHEN score <= 5 THEN 'intermediate' ELSE 'advanced' END AS tier, count(*) AS n, min(score) AS min_score, max(score) AS max_score
    FROM (SELECT CAST({_SCORE.format(p='', n='')} + CASE WHEN subtype IN ('constraint', 'projection') THEN 1 ELSE 0 END AS INT) AS score FROM c) x GROUP BY 1""",
    "post_complexity": _P + f"SELECT subtype, count(*) AS n, round(avg({_SCORE.format(p='', n='2')}), 6) AS mean_score FROM c GROUP BY subtype",
}

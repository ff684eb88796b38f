"""Chain verdicts with two judges, human-style panels with kappa, and label agreement."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions import chain
from ..operators import panel
from ..sources.io import cut, table
from .common import luck, luck_sql, r6
from .drift_log import TIES


def layer_terms(spark: SparkSession, sf_dir: str) -> DataFrame:
    """part_key, needs, supplies: what the second layer needs, and what the first one's other reading supplies.

    The next part is found within ranges of keys; only each range's last part asks for the first one of a later range,
    which a join of one row a range answers. No task sees the whole list. The ranges are kept: their bounds are sampled
    and merged as the plan goes, so two evaluations would not agree on them.
    """
    at = F.asc_nulls_last("p_partkey")
    p = cut(table(spark, sf_dir, "part").select("p_partkey", "p_name").repartitionByRange(at).withColumn("range", F.spark_partition_id()))
    name = F.struct("p_name")  # not null where there is a next part, whatever its name
    here = p.withColumn("following", F.lead(name).over(Window.partitionBy("range").orderBy(at)))
    firsts = p.groupBy("range").agg(F.min_by(name, F.struct(F.col("p_partkey").isNull(), "p_partkey")).alias("name"))  # one row a range
    after = firsts.withColumn("at", F.col("range")).select("at", "name")
    nexts = firsts.select("range").join(F.broadcast(after), F.col("at") > F.col("range")).groupBy("range").agg(F.min_by("name", "at").alias("next_name"))
    pairs = here.join(F.broadcast(nexts), "range", "left").withColumn("following", F.coalesce("following", "next_name")["p_name"]).filter("following IS NOT NULL")
    return pairs.select(F.col("p_partkey").alias("part_key"), chain.terms(F.col("p_name")).alias("needs"), chain.terms(F.col("following")).alias("supplies"))


def chains(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Consecutive parts: the second layer needs the words of one name, the other reading supplies those of the next."""
    return layer_terms(spark, sf_dir).select("part_key", chain.counterfactual(F.col("needs"), F.col("supplies")).alias("verdict"))


def chain_verdict(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chains(spark, sf_dir).groupBy("verdict").agg(F.count("*").alias("n"))


def chain_qualified(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chains(spark, sf_dir).filter(chain.qualifies(F.col("verdict")))


def judge_votes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two judges a order by hash: three verdicts."""
    orders = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("candidate"))
    votes = orders.withColumn("judge", F.explode(F.array(F.lit("j1"), F.lit("j2"))))
    n = luck("vote", F.col("judge"), F.col("candidate"))
    return votes.withColumn("verdict", F.when(n < 6000, chain.ELIMINATED).when(n < 9000, chain.TRANSFORMED).otherwise(chain.INVARIANT))


def judge_agreement(spark: SparkSession, sf_dir: str) -> DataFrame:
    return panel.agreement(judge_votes(spark, sf_dir), "candidate", "verdict").select("n", "n_agree", r6(F.col("agreement")).alias("agreement"))


def judge_consensus(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = judge_votes(spark, sf_dir)
    one = panel.consensus(v, "candidate", chain.qualifies(F.col("verdict")))  # one aggregate serves the three rules
    counts = one.agg(*[F.count_if(panel.rule_of(rule)).alias(rule) for rule in panel.RULES])
    return counts.select(F.inline(F.array(*[F.struct(F.lit(rule).alias("rule"), F.col(rule).alias("n")) for rule in panel.RULES])))


def label_agreement(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = table(spark, sf_dir, "documents").select("doc_id", "lang")
    l = table(spark, sf_dir, "labels").join(d, "doc_id")
    votes = l.select("doc_id", "lang", F.explode(F.array("quality", 1 - F.col("toxic"))).alias("v"))
    return panel.agreement(votes, "doc_id", "v", ["lang"]).select("lang", "n", r6(F.col("agreement")).alias("agreement"))


def ratings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The first five lines of an order as five raters; status O accepts. split: the order's status."""
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", *TIES, "l_linestatus")
    n = F.row_number().over(Window.partitionBy("l_orderkey").orderBy(*TIES))
    size = F.count("*").over(Window.partitionBy("l_orderkey"))
    five = lines.select(F.col("l_orderkey").alias("sample_id"), n.alias("annotator"), size.alias("lines"), (F.col("l_linestatus") == "O").alias("pass")).filter("annotator <= 5 AND lines >= 5")
    orders = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("sample_id"), F.col("o_orderstatus").alias("split"))
    return five.join(orders, "sample_id").select("sample_id", "split", "annotator", "pass")


def panel_acceptance(spark: SparkSession, sf_dir: str) -> DataFrame:
    a = panel.acceptance(ratings(spark, sf_dir), ok="pass", by=["split"])
    return a.select("split", "n", r6(F.col("majority")).alias("majority"), r6(F.col("strict")).alias("strict"))


def panel_overall(spark: SparkSession, sf_dir: str) -> DataFrame:
    a = panel.acceptance(ratings(spark, sf_dir), ok="pass")
    return a.select("n", r6(F.col("majority")).alias("majority"), r6(F.col("strict")).alias("strict"))


def fleiss_kappa(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = ratings(spark, sf_dir)
    parts = panel.fleiss_kappa(r, "sample_id", "pass", ["split"]).select("split", "n", r6(F.col("kappa")).alias("kappa"))
    whole = panel.fleiss_kappa(r, "sample_id", "pass").select(F.lit(None).cast("string").alias("split"), "n", r6(F.col("kappa")).alias("kappa"))
    return parts.unionByName(whole)


def checklist(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three items for each rater of an order: returned lines do not apply to the third."""
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", *TIES, "l_linestatus", "l_returnflag", "l_discount")
    n = F.row_number().over(Window.partitionBy("l_orderkey").orderBy(*TIES))
    rated = lines.withColumn("annotator", n).filter("annotator <= 5")
    def item(name: str, applicable: F.Column, passed: F.Column) -> F.Column:
        return F.struct(F.lit(name).alias("item"), applicable.alias("applicable"), passed.alias("pass"))

    items = F.array(
        item("dependency", F.lit(True), F.col("l_discount") < 0.09), item("retraction", F.lit(True), F.col("l_linestatus") == "O"), item("coherence", F.col("l_returnflag") != "R", F.col("l_discount") > 0.01)
    )
    return rated.select(F.col("l_orderkey").alias("sample_id"), "annotator", F.inline(items))


def checklist_verdicts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return panel.item_verdict(checklist(spark, sf_dir)).groupBy("annotator").agg(F.count("*").alias("n"), F.count_if("ok").alias("n_ok"))


def criterion_rates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return panel.criterion_rates(checklist(spark, sf_dir)).select("item", "n", r6(F.col("rate")).alias("rate"))


_C = """
WITH p AS (SELECT p_partkey AS part_key, list_distinct(string_split(p_name, ' ')) AS needs, lead(p_name) OVER (ORDER BY p_partkey) AS nxt FROM part),
c AS (SELECT part_key, CASE WHEN k = 0 THEN 'eliminated' WHEN k < len(needs) THEN 'transformed' ELSE 'invariant' END AS verdict
  FROM (SELECT part_key, needs, len(list_intersect(needs, string_split(nxt, ' '))) AS k FROM p WHERE nxt IS NOT NULL) x)
"""
_V = f"""
WITH v AS (SELECT o_orderkey AS candidate, j AS judge, {luck_sql("'vote'", 'j', 'CAST(o_orderkey AS VARCHAR)')} AS n FROM orders, (VALUES ('j1'), ('j2')) AS t(j)),
w AS (SELECT candidate, CASE WHEN n < 6000 THEN 'eliminated' WHEN n < 9000 THEN 'transformed' ELSE 'invariant' END AS verdict FROM v)
"""
_R = """
WITH l AS (SELECT l_orderkey AS sample_id, l_linestatus = 'O' AS ok, l_linestatus, l_returnflag, l_discount, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_shipdate, l_extendedprice) AS annotator,
  count(*) OVER (PARTITION BY l_orderkey) AS lines FROM lineitem),
s AS (SELECT sample_id, o_orderstatus AS split, count_if(ok) AS yes FROM l JOIN orders ON sample_id = o_orderkey WHERE annotator <= 5 AND lines >= 5 GROUP BY sample_id, o_orderstatus),
k AS (SELECT split, count(*) AS n, avg((yes * (yes - 1) + (5 - yes) * (4 - yes)) / 20.0) AS p, sum(yes) / (5.0 * count(*)) AS q FROM s GROUP BY ROLLUP (split)),
i AS (SELECT sample_id, annotator, unnest(['dependency', 'retraction', 'coherence']) AS item, unnest([true, true, l_returnflag <> 'R']) AS applicable, unnest([l_discount < 0.09, ok, l_discount > 0.01]) AS pass FROM l WHERE annotator <= 5)
"""
QUERIES = {
    f.__name__: f for f in (chain_verdict, chain_qualified, judge_agreement, judge_consensus, label_agreement, panel_acceptance, panel_overall, fleiss_kappa, checklist_verdicts, criterion_rates)
}
ORACLES = {
    "chain_verdict": _C + "SELECT verdict, count(*) AS n FROM c GROUP BY verdict",
    "chain_qualified": _C + "SELECT part_key, verdict FROM c WHERE verdict <> 'invariant'",
    "judge_agreement": _V + "SELECT count(*) AS n, count_if(a = b) AS n_agree, round(avg(CAST(a = b AS INT)), 6) AS agreement FROM (SELECT candidate, min(verdict) AS a, max(verdict) AS b FROM w GROUP BY candidate) x",
    "judge_consensus": _V
    + "SELECT rule, CASE rule WHEN 'any' THEN anyone ELSE everyone END AS n FROM (SELECT count_if(y = 2) AS everyone, count_if(y > 0) AS anyone FROM (SELECT candidate, count_if(verdict <> 'invariant') AS y FROM w GROUP BY candidate) x) z, (VALUES ('unanimous'), ('majority'), ('any')) AS t(rule)",
    "label_agreement": "SELECT lang, count(*) AS n, round(avg(CAST(quality = 1 - toxic AS INT)), 6) AS agreement FROM labels JOIN documents USING (doc_id) GROUP BY lang",
    "panel_acceptance": _R + "SELECT split, count(*) AS n, round(avg(CAST(yes >= 3 AS INT)), 6) AS majority, round(avg(CAST(yes = 5 AS INT)), 6) AS strict FROM s GROUP BY split",
    "panel_overall": _R + "SELECT count(*) AS n, round(avg(CAST(yes >= 3 AS INT)), 6) AS majority, round(avg(CAST(yes = 5 AS INT)), 6) AS strict FROM s",
    "fleiss_kappa": _R + "SELECT split, n, round((p - (q * q + (1 - q) * (1 - q))) / (1 - (q * q + (1 - q) * (1 - q))), 6) AS kappa FROM k",
    "checklist_verdicts": _R + "SELECT annotator, count(*) AS n, count_if(ok) AS n_ok FROM (SELECT sample_id, annotator, bool_and(pass OR NOT applicable) AS ok FROM i GROUP BY sample_id, annotator) x GROUP BY annotator",
    "criterion_rates": _R + "SELECT item, count(*) AS n, round(avg(CAST(pass AS INT)), 6) AS rate FROM i WHERE applicable GROUP BY item",
}
